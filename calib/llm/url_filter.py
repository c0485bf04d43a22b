"""URL filters over a sorted digest array: 64-bit xxhash keys, memory-mapped, with the full strings beside them."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator, Sequence
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from calib.llm.shared import plus

#: (verdict, host, path prefix).
RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]
#: Second-level names that are blocked whatever comes before or after them.
BLOCKED_HOSTS = [f"{name}.example.{tld}" for name in ("cheap-pills", "free-bets", "adult-x", "spam-farm", "casino-win", "ads-track") for tld in ("com", "net", "org")]
#: Most bytes of keys and strings that one array may hold; a longer list is to be cut into several filters.
MOST_BYTES = 1 << 30


def write_array(entries: Sequence[tuple[str, int]], path: str) -> None:
    """A file with the sorted digests of strings, the number of each, and the strings for confirmation.

    Layout: count; digests; numbers; offsets of the strings; their UTF-8 bytes.
    """
    import xxhash

    raw = [(xxhash.xxh64_intdigest(s.encode()), n, s.encode()) for s, n in dict(entries).items()]
    if sum(len(s) + 24 for _, _, s in raw) > MOST_BYTES:
        raise ValueError(f"the list needs more than {MOST_BYTES} bytes; cut it into several filters")
    raw.sort()
    with open(path, "wb") as f:
        f.write(np.array([len(raw)], "<u8").tobytes() + np.array([k for k, _, _ in raw], "<u8").tobytes() + np.array([n for _, n, _ in raw], "<i8").tobytes())
        f.write(np.cumsum([0, *(len(s) for _, _, s in raw)]).astype("<i8").tobytes() + b"".join(s for _, _, s in raw))


class DigestArray:
    """Read-only view of a file of write_array()."""

    def __init__(self, path: str):
        n = int(np.fromfile(path, "<u8", 1)[0])
        self.keys = np.memmap(path, "<u8", "r", 8, n) if n else np.zeros(0, "<u8")
        self.numbers = np.memmap(path, "<i8", "r", 8 + 8 * n, n) if n else np.zeros(0, "<i8")
        self.offsets = np.memmap(path, "<i8", "r", 8 + 16 * n, n + 1)
        self.strings = np.memmap(path, "u1", "r", 8 + 16 * n + 8 * (n + 1)) if os.path.getsize(path) > 16 + 24 * n else np.zeros(0, "u1")

    def find(self, probes: list[str]) -> np.ndarray:
        """The number of each string, or -1. Digests are searched all at once; a hit counts only if the stored string is the same."""
        import xxhash

        out = np.full(len(probes), -1, dtype=np.int64)
        if not len(self.keys) or not probes:
            return out
        sought = np.array([xxhash.xxh64_intdigest(s.encode()) for s in probes], dtype=np.uint64)
        at = np.searchsorted(self.keys, sought)
        hit = np.flatnonzero(self.keys[np.minimum(at, len(self.keys) - 1)] == sought)
        for i in hit[at[hit] < len(self.keys)].tolist():
            k = int(at[i])
            while k < len(self.keys) and self.keys[k] == sought[i]:  # strings of one digest stand side by side
                if self.strings[self.offsets[k] : self.offsets[k + 1]].tobytes() == probes[i].encode():
                    out[i] = self.numbers[k]
                    break
                k += 1
        return out


def spread(spark: SparkSession, entries: Sequence[tuple[str, int]], tag: str) -> str:
    """Sends a digest array to every executor; the name by which SparkFiles finds it there."""
    name = f"{tag}-{uuid.uuid4().hex}.digests"
    path = Path(tempfile.mkdtemp(prefix="calib-"), name)
    write_array(entries, str(path))
    spark.sparkContext.addFile(str(path))
    return name


def suffixes(host: str) -> list[str]:
    """The host and the domains above it."""
    labels = host.split(".")
    return [".".join(labels[k:]) for k in range(len(labels))] if host else []


def url_parts(docs: DataFrame) -> DataFrame:
    """docs with host and path of the url; both are empty for null or a url without ://."""
    url = F.coalesce(F.col("url").cast("string"), F.lit(""))
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(u, locate('://', u) + 3)")).otherwise("")
    rows = docs.withColumn("u", url).withColumn("u", rest)
    host = F.regexp_extract("u", r"(?s)^([^/?#]*)", 1)
    rows = rows.withColumn("host", F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    return rows.withColumn("path", F.regexp_extract("u", r"(?s)^[^/?#]*([^?#]*)", 1)).drop("u")


def judge(pages: DataFrame, rules=RULES, blocked=BLOCKED_HOSTS) -> DataFrame:
    """page_id, host, path, rule and verdict of every page.

    A rule fits its host and all hosts below it whose path starts as the rule has it; the longest wins, and of
    equally long ones the first. Where none fits, the url is blocked if its host, or a domain above it, is in
    `blocked`. Ties, repeated rows and nulls need no care: each row is judged by itself.
    """
    spark = pages.sparkSession
    texts = [f"{h}{p}" for _, h, p in rules]
    rule_file = spread(spark, [(f"{h} {p}", k) for k, (_, h, p) in reversed(list(enumerate(rules)))], "rules")
    host_file = spread(spark, [(h, 0) for h in blocked], "hosts")
    lengths = sorted({len(p) for _, _, p in rules})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        by_rule, by_host = DigestArray(SparkFiles.get(rule_file)), DigestArray(SparkFiles.get(host_file))
        for b in batches:
            hosts, paths = b.column("host").to_pylist(), b.column("path").to_pylist()
            probes, owner = [], []
            for i, (h, p) in enumerate(zip(hosts, paths)):
                for s in suffixes(h):
                    for n in lengths:
                        if len(p) >= n:
                            probes.append(f"{s} {p[:n]}")
                            owner.append(i)
            rule = [None] * len(hosts)
            found = by_rule.find(probes)
            for i, k in zip(owner, found.tolist()):
                if k >= 0 and (rule[i] is None or (len(texts[k]), -k) > (len(texts[rule[i]]), -rule[i])):
                    rule[i] = k
            names = [(i, s) for i, h in enumerate(hosts) if rule[i] is None for s in suffixes(h)]
            bad = {i for (i, _), k in zip(names, by_host.find([s for _, s in names]).tolist()) if k >= 0}
            verdicts = ["block" if i in bad else "allow" if k is None else rules[k][0] for i, k in enumerate(rule)]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([None if k is None else texts[k] for k in rule], pa.string()), pa.array(verdicts, pa.string())], names=["page_id", "host", "path", "rule", "verdict"])

    rows = url_parts(pages.select("page_id", "url")).select("page_id", "host", "path")
    return rows.mapInArrow(run, plus(rows, rule="string", verdict="string"))
