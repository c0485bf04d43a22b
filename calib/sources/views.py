"""Training views over the given tables: wide columns x0.. or arrays, a label y of -1 or 1, and a random order."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from calib.sources.order import BLOCKS, digest, digits, with_order

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
#: (column, centre, spread) of the numeric features of a line item, and the planted separator.
LINE_FEATURES = [("l_quantity", 25.5, 14.43), ("l_extendedprice", 53000.0, 30000.0), ("l_discount", 0.05, 0.0316), ("l_tax", 0.04, 0.0258)]
LINE_PLANTED = [1.0, 0.5, -0.75, 0.25]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def wide(d: int) -> list[str]:
    return [f"x{j}" for j in range(d)]


def as_array(df: DataFrame, d: int) -> DataFrame:
    """x0.. as one array column x."""
    keep = [c for c in df.columns if c not in wide(d)]
    return df.select(*keep, F.array(*wide(d)).alias("x"))


def _line(spark: SparkSession, sf_dir: str, y, blocks: int) -> DataFrame:
    df = table(spark, sf_dir, "lineitem")
    cols = [((F.col(c) - m) / s).alias(f"x{j}") for j, (c, m, s) in enumerate(LINE_FEATURES)]
    df = df.select(*LINE_KEY, "l_returnflag", "l_linestatus", *cols, F.lit(1.0).alias("x4"))
    return with_order(df.withColumn("y", y), LINE_KEY, blocks)


def _sign(c: Column) -> Column:
    return F.when(c > 0, 1.0).otherwise(-1.0)


def v_line(spark: SparkSession, sf_dir: str, blocks: int = BLOCKS) -> DataFrame:
    """V1: line items with a planted separator and 5 % flipped labels; d = 5."""
    score = sum((F.col(f"x{j}") * v for j, v in enumerate(LINE_PLANTED)), F.lit(0.0))
    flip = digits(digest(LINE_KEY), 9) % 100 < 5
    return _line(spark, sf_dir, _sign(score) * F.when(flip, -1.0).otherwise(1.0), blocks)


def v_noise(spark: SparkSession, sf_dir: str, blocks: int = BLOCKS) -> DataFrame:
    """V6: line items with a label that the features say nothing about; d = 5."""
    return _line(spark, sf_dir, F.when(F.col("l_returnflag") == "R", 1.0).otherwise(-1.0), blocks)


STAR_D = 54
_STAR_NUMBERS = [("l_quantity", 25.5, 14.43), ("l_extendedprice", 53000.0, 30000.0), ("l_discount", 0.05, 0.0316), ("l_tax", 0.04, 0.0258), ("o_totalprice", 250000.0, 150000.0), ("c_acctbal", 4500.0, 3200.0), ("p_size", 25.5, 14.4), ("p_retailprice", 1400.0, 400.0), ("s_acctbal", 4500.0, 3200.0)]
#: Column and how many of its values, in order of the values, get an indicator.
_STAR_KINDS = [("c_mktsegment", 5), ("o_orderpriority", 5), ("o_orderstatus", 3), ("r_name", 5), ("l_linestatus", 2), ("l_returnflag", 3), ("p_type", 6)]
STAR_PLANTED = {0: 1.0, 1: 0.5, 2: -0.75, 4: 0.5, 5: 0.25, 7: -0.5, 9: 0.75, 14: -0.5}


def star_joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line items with their order, customer, region, part and supplier. Only the dimensions of fixed size are hinted."""
    t = lambda n: table(spark, sf_dir, n)
    nation = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    customer = t("customer").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_acctbal", "c_mktsegment", "r_name")
    orders = t("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "o_totalprice", "o_orderstatus", "o_orderpriority", "c_acctbal", "c_mktsegment", "r_name")
    part = t("part").select("p_partkey", "p_size", "p_retailprice", "p_type")
    supplier = t("supplier").select("s_suppkey", "s_acctbal")
    df = t("lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return df.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))


def star_features() -> list[Column]:
    """The 54 features by what star_rows keeps of them."""
    x = [F.col(f"v{j}") for j in range(len(_STAR_NUMBERS))]
    for c, n in _STAR_KINDS:
        x += [(F.col(f"kind_{c}") == k).cast("double") for k in range(n)]
    x += [(F.col("month") == k).cast("double") for k in range(1, 13)]
    return x + [x[0] * x[1], x[1] * x[2], x[0] * x[4], F.lit(1.0)]


def star_rows(spark: SparkSession, sf_dir: str, blocks: int = BLOCKS) -> DataFrame:
    """V2 with nine numbers, the classes of seven kinds and the month in place of its features, which star_array makes of them: a quarter of the bytes to move and store."""
    df = star_joined(spark, sf_dir)
    numbers = [((F.col(c) - m) / s).alias(f"v{j}") for j, (c, m, s) in enumerate(_STAR_NUMBERS)]
    kinds = [F.pmod(F.crc32(F.col(c).cast("binary")), F.lit(n)).cast("byte").alias(f"kind_{c}") for c, n in _STAR_KINDS]
    df = df.select(*LINE_KEY, *numbers, *kinds, F.month("l_shipdate").cast("byte").alias("month"))
    x = star_features()
    score = sum((x[j] * v for j, v in STAR_PLANTED.items()), F.lit(0.0))
    flip = digits(digest(LINE_KEY), 9) % 100 < 5
    return with_order(df.withColumn("y", _sign(score) * F.when(flip, -1.0).otherwise(1.0)), LINE_KEY, blocks)


def star_array(df: DataFrame) -> DataFrame:
    """Rows of star_rows with their features as one array x."""
    made = {f"v{j}" for j in range(len(_STAR_NUMBERS))} | {f"kind_{c}" for c, _ in _STAR_KINDS} | {"month"}
    return df.select(*(c for c in df.columns if c not in made), F.array(*star_features()).alias("x"))


def v_star(spark: SparkSession, sf_dir: str, blocks: int = BLOCKS) -> DataFrame:
    """V2: 54 features of the star: 9 numbers, 41 indicators of values by rank, 3 products and a bias; planted on 8 of them."""
    x = [c.alias(f"x{j}") for j, c in enumerate(star_features())]
    return star_rows(spark, sf_dir, blocks).select(*LINE_KEY, *x, "y", "ord", "blk")


def v_embed(spark: SparkSession, sf_dir: str, positive=range(5), blocks: int = BLOCKS) -> DataFrame:
    """V3: embeddings and a bias as an array; +1 for the labels in `positive`."""
    df = table(spark, sf_dir, "embeddings")
    x = F.concat(F.transform("embedding", lambda v: v.cast("double")), F.array(F.lit(1.0)))
    y = F.when(F.col("label").isin(*positive), 1.0).otherwise(-1.0)
    return with_order(df.select("vec_id", x.alias("x"), y.alias("y")), ["vec_id"], blocks)


def text_features(text: Column) -> list[Column]:
    """Seven numbers and a bias: log length, words, word length, distinct share, digit, letter and punctuation share."""
    t = F.coalesce(text, F.lit(""))
    words = F.filter(F.split(F.lower(t), r"[ \t\n\x0B\f\r]+"), lambda w: w != "")
    n, chars = F.size(words), F.greatest(F.length(t), F.lit(1))
    count = lambda p: F.length(F.regexp_replace(t, p, "")) / chars
    return [F.log(chars.cast("double") + 1), n / 1000, F.when(n > 0, F.length(F.concat_ws("", words)) / n).otherwise(0.0), F.when(n > 0, F.size(F.array_distinct(words)) / n).otherwise(0.0), count("[^0-9]"), count("[^a-zA-Z]"), count("[^.,;:!?]"), F.lit(1.0)]


def v_doc(spark: SparkSession, sf_dir: str, label: str = "quality", blocks: int = BLOCKS) -> DataFrame:
    """V4: numbers of labelled documents; d = 8."""
    df = table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id")
    x = [c.alias(f"x{j}") for j, c in enumerate(text_features(F.col("text")))]
    return with_order(df.select("doc_id", *x, F.when(F.col(label) == 1, 1.0).otherwise(-1.0).alias("y")), ["doc_id"], blocks)


def bound(value: Column, f) -> Column:
    """f(value), where value is evaluated once; within a lambda of f it would otherwise be evaluated for every element."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def hashed_bag(df: DataFrame, key: list[str], text: Column, y: Column, bits: int) -> DataFrame:
    """Sparse examples: idx and val of hashed token counts of unit length, by key; texts without tokens keep empty arrays."""
    words = F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[ \t\n\x0B\f\r]+"), lambda w: w != "")
    slots = F.transform(words, lambda w: F.conv(F.substring(F.md5(w), 1, 8), 16, 10).cast("long") % (1 << bits))

    def counted(s: Column, at: Column) -> Column:
        """Each slot of the sorted ones and how often it is there; at: where runs of equal ones begin."""
        counts = F.transform(at, lambda i, j: (F.coalesce(F.get(at, j + 1), F.size(s)) - i).cast("double"))
        return F.struct(F.transform(at, lambda i: F.get(s, i)).alias("idx"), counts.alias("c"))

    runs = lambda s: F.filter(F.transform(s, lambda _, i: i), lambda i: (i == 0) | (F.get(s, i) != F.get(s, i - 1)))
    bag = bound(F.sort_array(slots), lambda s: bound(runs(s), lambda at: counted(s, at)))
    rows = df.select(*key, y.alias("y"), F.explode(F.array(bag)).alias("bag"))  # exploded, so that no filter above builds it once more
    norm = F.sqrt(F.aggregate("bag.c", F.lit(0.0), lambda a, v: a + v * v))
    return rows.select(*key, F.col("bag.idx").alias("idx"), bound(norm, lambda z: F.transform("bag.c", lambda v: v / z)).alias("val"), "y")


def v_bow(spark: SparkSession, sf_dir: str, bits: int = 12, blocks: int = BLOCKS) -> DataFrame:
    """V5: hashed words of documents; +1 for English."""
    df = table(spark, sf_dir, "documents")
    y = F.when(F.col("lang") == "en", 1.0).otherwise(-1.0)
    return with_order(hashed_bag(df, ["doc_id"], F.col("text"), y, bits), ["doc_id"], blocks)


def v_page(spark: SparkSession, sf_dir: str, bits: int = 12, blocks: int = BLOCKS) -> DataFrame:
    """V7: hashed tags and words of pages; the label is the parity of a hash of the url."""
    df = table(spark, sf_dir, "pages")
    y = F.when(F.conv(F.substring(F.md5("url"), 1, 1), 16, 10).cast("int") % 2 == 0, 1.0).otherwise(-1.0)
    return with_order(hashed_bag(df, ["page_id"], F.regexp_replace("html", "[<>]", " "), y, bits), ["page_id"], blocks)


def v_conv(spark: SparkSession, sf_dir: str, bits: int = 12, blocks: int = BLOCKS) -> DataFrame:
    """V8: hashed words of conversation turns; user against assistant."""
    df = table(spark, sf_dir, "conversations").where(F.col("role").isin("user", "assistant"))
    y = F.when(F.col("role") == "user", 1.0).otherwise(-1.0)
    return with_order(hashed_bag(df, ["conv_id", "turn"], F.col("text"), y, bits), ["conv_id", "turn"], blocks)


def event_features(df: DataFrame) -> DataFrame:
    """V9's columns over a batch or a stream of events; d = 6 and planted on value and k."""
    k = F.coalesce(F.get_json_object("props", "$.k").cast("double"), F.lit(0.0)) / 100
    hour = F.hour("ts") * (2 * 3.141592653589793 / 24)
    x = [F.log1p(F.greatest(F.col("value"), F.lit(0.0))), F.sin(hour), F.cos(hour), F.dayofweek("ts") / 7.0, k, F.lit(1.0)]
    df = df.select("event_id", "user_id", "ts", *(c.alias(f"x{j}") for j, c in enumerate(x)))
    return df.withColumn("y", _sign(F.col("x0") - 4 * F.col("x4") - 1.0))


def v_event(spark: SparkSession, sf_dir: str, blocks: int = BLOCKS) -> DataFrame:
    return with_order(event_features(table(spark, sf_dir, "events")), ["event_id"], blocks)


def check(df: DataFrame, d: int) -> dict[str, int]:
    """Counts of what would spoil a training view: nulls, non-finite features, other labels."""
    bad = [F.col(c).isNull() | F.isnan(c) | (F.abs(c) == float("inf")) for c in wide(d)]
    any_bad = bad[0]
    for b in bad[1:]:
        any_bad |= b
    r = df.agg(F.count("*").alias("rows"), F.sum(any_bad.cast("long")).alias("bad"), F.sum((~F.col("y").isin(-1.0, 1.0)).cast("long")).alias("labels")).first()
    return {"rows": r["rows"], "bad": r["bad"] or 0, "labels": r["labels"] or 0}
