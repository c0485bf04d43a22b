"""Near duplicates: SuperMinHash signatures, banding, exact verification and union-find grouping.

A signature takes, for each element of a set, the ranks of a random permutation in turn: rank j goes to a
random position not yet taken with the value j plus a random fraction, and each position keeps its least
value. The ranks of an element are correlated, which lowers the variance, and once every position holds a
value below j no later rank can matter, which ends most sets after a few ranks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from calib.llm.shared import drop_tables, materialize

SHINGLE = 5
#: Similarity to reach, in hundredths.
PERCENT = 75
#: Signature positions; four of 16 bits each make the 64-bit key of a band. A pair at 0.75 shares one of the 32 bands but for 5 in a million.
POSITIONS = 128
BANDS = POSITIONS // 4
#: Positions that must agree before full sets are compared. At 0.75 fewer agree in 2 of ten million pairs, so the bands decide what is lost.
AGREE = 70
#: Leaders that a class is compared with before the rest of its buckets, and edges of one task's union-find.
LEADS, EDGES = 8, 200_000
#: Set elements and members of a block; a bucket is compared by pairs of blocks.
BLOCK_ELEMENTS, BLOCK_MEMBERS = 1 << 20, 2048
#: Ids that may be broadcast, and classes of very many copies.
BROADCAST_IDS, HEAVY = 2_000_000, 100_000
#: Text bytes that are hashed together.
BLOCK = 1 << 20
#: Set elements that are signed together.
ELEMENTS = 1 << 16

_P, _MASK = np.uint64(0x9E3779B97F4A7C15), (1 << 64) - 1
_INV = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_WORD_SLOTS = np.array([0xA24BAED4963EE407, 0x9FB21C651E98DF25, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93], dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser; changes its argument."""
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _powers(base: np.uint64, n: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.cumprod(np.concatenate(([np.uint64(1)], np.full(n, base, dtype=np.uint64))))


_pow, _inv = _powers(_P, BLOCK), _powers(_INV, BLOCK)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of consecutive texts, A-Z lower-cased, and how many each text has. data: UTF-8 bytes of all."""
    global _pow, _inv
    counts = np.zeros(len(offsets) - 1, dtype=np.int64)
    if not len(data):
        return np.zeros(0, np.uint64), counts
    if len(data) >= len(_pow):
        _pow, _inv = _powers(_P, len(data)), _powers(_INV, len(data))
    blank = (data == 32) | ((data >= 9) & (data <= 13))
    first, edge = np.zeros(len(data), dtype=bool), np.zeros(len(data), dtype=bool)  # of a text, its first and last byte
    filled = offsets[1:] > offsets[:-1]
    first[offsets[:-1][filled]] = True
    edge[offsets[1:][filled] - 1] = True
    new, last = ~blank, ~blank
    new[1:] &= blank[:-1] | first[1:]
    last[:-1] &= blank[1:] | edge[:-1]
    starts, ends = np.flatnonzero(new), np.flatnonzero(last) + 1
    code = data.astype(np.uint64)
    code += np.uint64(32) * ((data >= 65) & (data <= 90)) + np.uint64(1)
    total = np.concatenate(([np.uint64(0)], np.cumsum(code * _pow[: len(data)])))
    h = (total[ends] - total[starts]) * _inv[starts]
    h += (ends - starts).astype(np.uint64) * np.uint64(0xD1342543DE82EF95)
    counts[:] = np.searchsorted(starts, offsets[1:]) - np.searchsorted(starts, offsets[:-1])
    return mix(h), counts


def shingle_sets(texts: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct shingle hashes) of every text that has a word; a text of fewer than five words has one shingle."""
    texts = texts.cast(pa.large_string())
    at = 0
    while at < len(texts):
        all_offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
        upto = max(at + 1, int(np.searchsorted(all_offsets, all_offsets[at] + BLOCK, side="right")) - 1)
        offsets = all_offsets[at : upto + 1]
        data = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]] if texts.buffers()[2] and offsets[-1] > offsets[0] else np.zeros(0, np.uint8)
        h, counts = word_hashes(data, offsets - offsets[0])
        ends = np.cumsum(counts)
        n = max(0, len(h) - SHINGLE + 1)
        s = np.zeros(n, dtype=np.uint64)
        for k in range(SHINGLE):
            s += h[k : n + k] * _WORD_SLOTS[k]
        s = mix(s)
        for i, (c, e) in enumerate(zip(counts.tolist(), ends.tolist())):
            if c >= SHINGLE:
                x = np.sort(s[e - c : e - SHINGLE + 1])
                yield at + i, x[np.concatenate(([True], x[1:] != x[:-1]))]
            elif c:
                yield at + i, mix((h[e - c : e] * _WORD_SLOTS[:c]).sum(keepdims=True, dtype=np.uint64) + np.uint64(c))
        at = upto


def super_minhash(sets: list[np.ndarray], positions: int = POSITIONS) -> np.ndarray:
    """A row of 16-bit signature values for each set; sets must not be empty."""
    m, n = positions, len(sets)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    elements = np.concatenate(sets) if n else np.zeros(0, np.uint64)
    best = np.full(n * m, np.uint64(_MASK))
    taken = None
    for j in range(m):
        u = mix(elements + np.uint64((j + 1) * 0x9E3779B97F4A7C15 & _MASK))
        k = j + ((u >> np.uint64(48)) % np.uint64(m - j)).astype(np.int64)
        value = np.uint64(j << 48) | (mix(u ^ np.uint64(0x2545F4914F6CDD1D)) >> np.uint64(16))
        if taken is None:
            spot = k
        else:
            rows = np.arange(len(elements))
            spot = taken[rows, k].astype(np.int64)
            taken[rows, k] = taken[:, j]
        np.minimum.at(best, owner * m + spot, value)
        open_ = (best.reshape(n, m).max(axis=1) >> np.uint64(48)) > np.uint64(j)
        if not open_.any():
            break
        on = open_[owner]
        if taken is None:
            taken = np.tile(np.arange(m, dtype=np.uint8 if m <= 256 else np.int32), (int(on.sum()), 1))
            taken[np.arange(len(taken)), k[on]] = 0
        elif not on.all():
            taken = taken[on]
        elements, owner = elements[on], owner[on]
    return best.reshape(n, m).astype(np.uint16)


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, digest (16 bytes of the whole set) and bands (64-bit keys); the last two are null for an empty set."""
    import xxhash  # noqa: F401  fails here rather than in a task

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        def signed(held):
            part, size = [], 0
            for _, x in held:
                if part and size + len(x) > ELEMENTS:
                    yield super_minhash(part)
                    part, size = [], 0
                part.append(x)
                size += len(x)
            if part:
                yield super_minhash(part)

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                b = batch.slice(at, 256)
                n, digests, bands = np.zeros(b.num_rows, np.int64), [None] * b.num_rows, [None] * b.num_rows
                held = list(shingle_sets(b.column("text")))
                for (i, s), keys in zip(held, (row for block in signed(held) for row in block.view(np.int64))):
                    n[i], digests[i], bands[i] = len(s), xxhash.xxh3_128_digest(s.tobytes()), keys
                yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n), pa.array(digests, pa.binary()), pa.array(bands, pa.list_(pa.int64()))], names=["doc_id", "n_shingles", "digest", "bands"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, n_shingles long, digest binary, bands array<long>")


def full_sets(docs: DataFrame) -> DataFrame:
    """doc_id and its whole set of shingle hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                b = batch.slice(at, 256)
                held = list(shingle_sets(b.column("text")))
                if held:
                    yield pa.RecordBatch.from_arrays([b.column("doc_id").take(pa.array([i for i, _ in held])), pa.array([s.view(np.int64) for _, s in held], pa.list_(pa.int64()))], names=["doc_id", "shingles"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, "doc_id long, shingles array<long>")


def _agreeing(a: str, b: str):
    """Column: how many positions of two signatures agree."""
    lanes = "+".join(f"if((z & {0xFFFF << 16 * k if k < 3 else -(1 << 48)}L) = 0, 1, 0)" for k in range(4))
    return F.expr(f"aggregate(zip_with({a}, {b}, (x, y) -> x ^ y), 0, (n, z) -> n + {lanes})")


def confirmed(pairs: DataFrame, reps: DataFrame, sets: DataFrame, made: list[str]) -> DataFrame:
    """Those pairs (a, b) of doc_ids whose full sets reach the similarity. Pairs whose signatures differ too much are not compared."""
    side = lambda c: reps.select(F.col("rep").alias(c), F.col("bands").alias(f"{c}_bands"))
    close = pairs.join(side("a"), "a").join(side("b"), "b").where(_agreeing("a_bands", "b_bands") >= AGREE).select("a", "b").distinct()
    close = materialize(close, "close", made)
    side = lambda c: sets.select(F.col("doc_id").alias(c), F.col("shingles").alias(f"{c}_set"))
    both = close.join(side("a"), "a").join(side("b"), "b").withColumn("common", F.size(F.array_intersect("a_set", "b_set")))
    return materialize(both.where(F.col("common") * (100 + PERCENT) >= PERCENT * (F.size("a_set") + F.size("b_set"))).select("a", "b").distinct(), "links", made)


def only(docs: DataFrame, ids: DataFrame, keep: bool = True) -> DataFrame:
    """The rows of docs whose doc_id is (or is not) in ids. Up to BROADCAST_IDS are broadcast, so that texts stay where they are."""
    if ids.count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    return docs.join(ids, "doc_id", "left_semi" if keep else "left_anti").select(docs.columns)


def _local_unions(edges: DataFrame) -> DataFrame:
    """Union-find inside each task, over at most so many nodes at once: its edges become stars around their least node."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict[int, int] = {}

        def find(x: int) -> int:
            root = x
            while (up := parent.setdefault(root, root)) != root:
                root = up
            while parent[x] != root:
                parent[x], x = root, parent[x]
            return root

        def stars() -> pa.RecordBatch:
            rows = [(x, r) for x in list(parent) if (r := find(x)) != x]
            parent.clear()
            return pa.RecordBatch.from_arrays([pa.array([x for x, _ in rows], pa.int64()), pa.array([r for _, r in rows], pa.int64())], names=["a", "b"])

        for batch in batches:
            for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                a, b = find(a), find(b)
                parent[max(a, b)] = min(a, b)
            if len(parent) > EDGES:
                yield stars()
        yield stars()

    few = max(1, -(-edges.count() // EDGES))
    return edges.select("a", "b").coalesce(few).mapInArrow(run, "a long, b long")


def components(edges: DataFrame, made: list[str] | None = None) -> DataFrame:
    """(node, component) for every node of edges (a, b): the least node that it reaches. The table of the result is noted in `made`.

    Stars are joined until nothing changes. The neighbours of one node meet in one task, as far as union-find inside
    the tasks before has left any; nothing is gathered from them there but their least.
    """
    spark, last = edges.sparkSession, []
    edges = materialize(_local_unions(edges), "unions", last)
    mark = (0, None)
    while True:
        # every neighbour above a node, and then every neighbour below it, moves to the least of them
        sym = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = sym.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
        up = sym.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        up = up.where("a <> b").distinct()
        low = up.groupBy("a").agg(F.min("b").alias("m"))
        down = up.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b")))
        now: list[str] = []
        edges = materialize(down.where("a <> b").distinct(), "stars", now)
        drop_tables(spark, last)
        last = now
        seen = edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(seen) == mark:
            if made is not None:
                made += last
            return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
        mark = tuple(seen)


def near_duplicates(docs: DataFrame, made: list[str] | None = None) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row of docs (doc_id, text).

    Rows with the same set are one class, of which the least doc_id stands for all. Every class is first compared
    with leaders of its bands' buckets, so that a bucket of one group never needs all its pairs. Buckets that then
    still hold several groups are compared in full, block by block, inside tasks that give out only the links by
    which groups grow together. No bucket is cut off. Null and empty texts are linked with nothing; rows with one
    doc_id count as one document; a null doc_id is never linked. Tables that the result does not rest on are deleted
    here; the two that it does are noted in `made`.
    """
    spark, made, spent = docs.sparkSession, [] if made is None else made, []
    found = materialize(signatures(docs), "signatures", made)
    usable = found.where("n_shingles > 0 AND doc_id IS NOT NULL")
    least = usable.groupBy("digest").agg(F.min(F.struct("doc_id", "bands", "n_shingles")).alias("x"), F.count("*").alias("copies"))
    reps = materialize(least.select("digest", F.col("x.doc_id").alias("rep"), F.col("x.bands").alias("bands"), F.col("x.n_shingles").alias("n"), "copies"), "classes", spent)
    buckets = reps.select("rep", "n", F.posexplode("bands").alias("band", "value")).select(F.xxhash64("band", "value").alias("key"), "band", "rep", "n")
    shared = buckets.groupBy("key").agg(F.min("rep").alias("lo"), F.max("rep").alias("hi")).where("lo < hi")
    members = materialize(buckets.join(shared, "key"), "members", spent)
    sets = materialize(full_sets(only(docs.select("doc_id", "text"), materialize(members.select(F.col("rep").alias("doc_id")).distinct(), "wanted", spent))), "sets", spent)
    links = confirmed(nearest(members.select("rep", F.explode(F.array("lo", "hi")).alias("lead")).where("rep <> lead")), reps, sets, spent)
    groups = components(links, spent)
    more = materialize(block_links(block_pairs(mixed_buckets(members.drop("lo", "hi"), groups)), reps, sets), "links", spent)
    if not more.isEmpty():
        groups = components(links.union(more), spent)
    moved = reps.join(groups, reps.rep == groups.node).where("component <> rep").select("digest", F.col("component").alias("component_id"))
    first = reps.select("digest", "rep", "copies").join(moved, "digest", "left").select("digest", F.coalesce("component_id", "rep").alias("component_id"), "copies")
    first = materialize(first, "firsts", made)
    drop_tables(spark, spent)
    # classes of very many copies, of which there are HEAVY at most, are broadcast
    heavy = F.col("copies") > max(1000, found.count() // HEAVY)
    rows = found.select("doc_id", "n_shingles", "digest").join(F.broadcast(first.where(heavy).select("digest", F.col("component_id").alias("heavy"))), "digest", "left")
    rest = rows.where("heavy IS NULL AND digest IS NOT NULL").join(first.where(~heavy).select("digest", "component_id"), "digest", "left")
    out = rest.select("doc_id", "n_shingles", "component_id").union(rows.where("heavy IS NOT NULL OR digest IS NULL").select("doc_id", "n_shingles", F.col("heavy")))
    own = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), own).alias("component_id"), F.coalesce(F.col("doc_id") == own, F.lit(False)).alias("kept"))


def nearest(leads: DataFrame) -> DataFrame:
    """Pairs (a, b) of each rep and the LEADS leaders with whom it shares most buckets. What is left out is compared with the rest later."""
    counts = leads.groupBy("rep", "lead").agg(F.count("*").alias("n"))
    best = counts.withColumn("at", F.row_number().over(Window.partitionBy("rep").orderBy(F.desc("n"), "lead"))).where(F.col("at") <= LEADS)
    return best.select(F.greatest("rep", "lead").alias("a"), F.least("rep", "lead").alias("b")).distinct()


def mixed_buckets(members: DataFrame, groups: DataFrame) -> DataFrame:
    """Members (key, band, rep, n) of buckets that hold several groups, with their group grp and the bucket's size.

    Of buckets with the same members only that of the first band stays: a pair is compared in the first band that it shares.
    """
    label = groups.union(groups.select("component", "component").distinct())
    placed = members.join(label, members.rep == label.node, "left").select("key", "band", "rep", "n", F.coalesce("component", "rep").alias("grp"))
    size = [F.count("*").alias("members"), F.sum("n").alias("elements"), F.bit_xor(F.xxhash64("rep")).alias("x"), F.bit_xor(F.xxhash64("rep", F.lit(1))).alias("y")]
    several = placed.groupBy("key").agg(F.min("band").alias("first"), F.min("grp").alias("lo"), F.max("grp").alias("hi"), *size).where("lo < hi")
    several = several.groupBy("x", "y", "members", "elements").agg(F.min(F.struct("first", "key")).alias("k")).select("k.key", "members", "elements")
    return placed.join(several, "key")


def block_pairs(rows: DataFrame) -> DataFrame:
    """Each bucket's members in blocks of bounded size, a row for every pair (i, j) of blocks that a member's own block is part of."""
    blocks = F.ceil(F.greatest(F.col("elements") / BLOCK_ELEMENTS, F.col("members") / BLOCK_MEMBERS)).cast("int")
    rows = rows.withColumn("blocks", blocks).withColumn("block", F.pmod(F.xxhash64("rep", "key"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    return rows.withColumn("other", other).select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "block", "band", "rep", "grp")


def block_links(rows: DataFrame, reps: DataFrame, sets: DataFrame) -> DataFrame:
    """Links (a, b) that join the groups of each pair of blocks, from full sets; a forest for each pair, not all its links."""
    rows = rows.join(reps.select("rep", "bands"), "rep").join(sets.select(F.col("doc_id").alias("rep"), "shingles"), "rep")
    rows = rows.select("key", "i", "j", "block", "band", "rep", "grp", "bands", "shingles").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j", "rep")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []  # slices of one pair of blocks

        def done() -> pa.RecordBatch:
            links = forest(pa.Table.from_batches(held).combine_chunks())
            held.clear()
            return pa.RecordBatch.from_arrays([pa.array([x for x, _ in links], pa.int64()), pa.array([x for _, x in links], pa.int64())], names=["a", "b"])

        now = None
        for b in batches:
            if not b.num_rows:
                continue
            key = np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("key", "i", "j")], axis=1)
            edges = [0, *(np.flatnonzero((key[1:] != key[:-1]).any(axis=1)) + 1).tolist(), len(key)]
            for start, end in zip(edges, edges[1:]):
                if held and tuple(key[start]) != now:
                    yield done()
                now = tuple(key[start])
                held.append(b.slice(start, end - start))
        if held:
            yield done()

    return rows.mapInArrow(run, "a long, b long").distinct()


def forest(rows: pa.Table) -> list[tuple[int, int]]:
    """Links that join the groups in a pair of blocks. A row is compared with the later ones that are not yet in its group, whose first shared band this is."""
    get = lambda c: rows.column(c).to_numpy()
    rep, block, band, n = get("rep"), get("block"), int(rows.column("band")[0].as_py()), rows.num_rows
    label = np.unique(get("grp"), return_inverse=True)[1]
    two = rows.column("i")[0] != rows.column("j")[0]
    bands = rows.column("bands").combine_chunks().flatten().to_numpy().reshape(n, BANDS)
    lanes = np.ascontiguousarray(bands).view(np.uint16).reshape(n, POSITIONS)
    held = rows.column("shingles").combine_chunks()
    size = held.value_lengths().to_numpy().astype(np.int64)
    place = np.unique(held.flatten().to_numpy(), return_inverse=True)[1]
    start, mine, out = np.cumsum(size) - size, np.zeros(int(place.max(initial=-1)) + 1, dtype=np.int64), []
    for a in range(n - 1):
        b = np.flatnonzero(label[a + 1 :] != label[a]) + a + 1
        if two:
            b = b[block[b] != block[a]]
        b = b[100 * np.minimum(size[b], size[a]) >= PERCENT * np.maximum(size[b], size[a])]
        if band:
            b = b[~(bands[b, :band] == bands[a, :band]).any(axis=1)]
        b = b[(lanes[b] == lanes[a]).sum(axis=1) >= AGREE]
        if not len(b):
            continue
        mine[place[start[a] : start[a] + size[a]]] = 1
        cuts = [0, *(np.flatnonzero(np.diff(np.cumsum(size[b]) // ELEMENTS)) + 1).tolist(), len(b)]
        for c in (b[x:y] for x, y in zip(cuts, cuts[1:])):
            c = c[label[c] != label[a]]
            if not len(c):
                continue
            first = np.cumsum(size[c]) - size[c]
            common = np.add.reduceat(mine[place[np.repeat(start[c] - first, size[c]) + np.arange(int(size[c].sum()))]], first)
            for x in c[common * (100 + PERCENT) >= PERCENT * (size[a] + size[c])].tolist():
                if label[x] != label[a]:
                    out.append((int(max(rep[a], rep[x])), int(min(rep[a], rep[x]))))
                    label[label == label[x]] = label[a]
        mine[place[start[a] : start[a] + size[a]]] = 0
    return out


def keep_one_of_each(spark: SparkSession, docs: DataFrame) -> DataFrame:
    """docs without the documents that another one of their group stands for."""
    made: list[str] = []
    gone = materialize(near_duplicates(docs, made).where(~F.col("kept") & F.col("doc_id").isNotNull()).select("doc_id").distinct(), "gone")
    drop_tables(spark, made)
    return only(docs, gone, keep=False)
