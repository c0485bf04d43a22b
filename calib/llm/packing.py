"""Best-two-fit packing of tokenised documents into sequences of a fixed length.

The packer sees only how many pieces there are of each length, at most `size` numbers, so it fills all
sequences of the corpus together whatever its size: a filled sequence is a pattern of lengths with the
number of times it is used. Pieces then find their places by their rank among the pieces of their length.
"""

from __future__ import annotations

import json
import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from calib.llm.encoding import le32
from calib.llm.shared import materialize, plus

SEQUENCE = 1024
#: Ranks are counted in this many parts for each length, so that no length meets in one task.
PARTS = 64
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
#: Fixed value: how byte-level tokenizers split a text into words.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174]
#: The character by which such a vocabulary file writes each byte.
_BYTE_OF = {chr(b): b for b in _plain} | {chr(256 + k): b for k, b in enumerate(b for b in range(256) if b not in _plain)}
_encoders: dict = {}


def text_encoder(path: str):
    """A function from a text to its ids, for a byte-level BPE file of the `tokenizers` library; kept for the process.

    The file's vocabulary serves as ranks for the faster tiktoken, which gives the same ids (the tests compare
    them). A text that spells out a special token goes to the tokenizer itself, which gives that token's id.
    """
    if path not in _encoders:
        import tiktoken
        from tokenizers import Tokenizer

        tok = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            vocab = json.load(f)["model"]["vocab"]
        ranks = {bytes(map(_BYTE_OF.__getitem__, t)): i for t, i in vocab.items()}
        fast = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        special = [t.content for t in tok.get_added_tokens_decoder().values()]

        def encode(text: str) -> bytes:
            if any(s in text for s in special):
                return le32(tok.encode(text, add_special_tokens=False).ids)
            return fast.encode_to_numpy(text, disallowed_special=()).astype("<u4").tobytes()

        _encoders[path] = encode
    return _encoders[path]


def cut(n: int, size: int) -> list[tuple[int, int]]:
    """(start, length) of a document's pieces: all of `size`, but the first has what is left over."""
    head = n % size or min(n, size)
    return [(0, head)] + [(s, size) for s in range(head, n, size)] if n else []


def pieces(docs: DataFrame, path: str, end_id: int = 2, size: int = SEQUENCE) -> DataFrame:
    """A row for each piece of each document. Null and empty texts give one piece with the end id alone.

    Other columns of `docs` are not read; a null doc_id stays null.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = text_encoder(path), le32([end_id])
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                rows = []
                for i, text in zip(part.column("doc_id").to_pylist(), part.column("text").to_pylist()):
                    ids = encode(text or "") + end
                    for k, (s, n) in enumerate(cut(len(ids) // 4, size)):
                        rows.append((i, k, s, n, zlib.crc32(ids[4 * s : 4 * (s + n)])))
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(run, PIECES)


def fill(counts: dict[int, int], size: int = SEQUENCE) -> list[tuple[list[int], int]]:
    """Patterns (lengths in one sequence, times used) that place every piece.

    A sequence takes the longest piece that still fits, again and again. If a gap stays, its smallest piece
    gives way to the two waiting pieces that fill gap and place most tightly, where two such pieces exist.
    The same choice repeats until a length runs out, so whole runs are placed at once.
    """
    left = np.zeros(size + 1, dtype=np.int64)
    for length, n in counts.items():
        left[length] += n
    out = []
    while left.any():
        gap, bin_ = size, []
        while (fit := np.flatnonzero(left[: gap + 1])).size:
            take = int(fit[-1])
            times = min(gap // take, int(left[take]))
            bin_ += [take] * times
            left[take] -= times
            gap -= take * times
        if gap and len(bin_) > 1:
            small = bin_[-1]
            room = gap + small
            waiting = np.flatnonzero(left[: room + 1])
            below = np.zeros(room + 1, dtype=np.int64)  # the longest waiting piece up to each length
            below[waiting] = waiting
            below = np.maximum.accumulate(below)
            best = (small, 0, 0)
            for a in waiting[::-1].tolist():
                if 2 * a < best[0]:
                    break
                b = int(below[min(room - a, a)])
                if b == a and left[a] < 2:
                    b = int(below[a - 1])
                if b and a + b > best[0]:
                    best = (a + b, a, b)
            if best[2]:
                bin_[-1:] = best[1:]
                left[small] += 1
                left[best[1]] -= 1
                left[best[2]] -= 1
        more = min(int(left[x]) // k for x, k in Counter(bin_).items())
        for x, k in Counter(bin_).items():
            left[x] -= more * k
        out.append((bin_, more + 1))
    return out


def places(patterns: list[tuple[list[int], int]]) -> np.ndarray:
    """Rows (length, first rank, first sequence, offset), by length and rank: where each run of ranks goes."""
    rows, rank, sequence = [], Counter(), 0
    for bin_, times in patterns:
        offset = 0
        for x in bin_:
            rows.append((x, rank[x], sequence, offset))
            rank[x] += times
            offset += x
        sequence += times
    return np.array(sorted(rows), dtype=np.int64).reshape(-1, 4)


def pack(rows: DataFrame, size: int = SEQUENCE) -> DataFrame:
    """Adds sequence_id and offset to rows that have doc_id, piece and length (1 to size).

    Runs over `rows` twice, so give it a table. What the driver gathers and sends is bounded by `size`.
    Repeated rows are placed one by one; an empty table gives an empty result.
    """
    spark = rows.sparkSession
    rows = rows.withColumn("_part", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(PARTS)).cast("int"))
    found = rows.groupBy("length", "_part").count().collect()
    base, total = {}, Counter()
    for r in sorted(found):
        base[r[0] * PARTS + r[1]] = total[r[0]]
        total[r[0]] += r[2]
    place = places(fill(total, size))
    sent = spark.sparkContext.broadcast((np.array(sorted(base)), np.array([base[k] for k in sorted(base)]), place))
    ranked = rows.withColumn("_rank", F.row_number().over(Window.partitionBy("length", "_part").orderBy("doc_id", "piece")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, bases, place = sent.value
        runs = place[:, 0] << 48 | place[:, 1]
        for b in batches:
            if not b.num_rows:
                continue
            length, part, rank = (b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("length", "_part", "_rank"))
            rank = bases[np.searchsorted(keys, length * PARTS + part)] + rank - 1
            at = place[np.searchsorted(runs, length << 48 | rank, side="right") - 1]
            kept = b.drop_columns(["_part", "_rank"])
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(at[:, 2] + rank - at[:, 1]), pa.array(at[:, 3])], names=[*kept.schema.names, "sequence_id", "offset"])

    return ranked.mapInArrow(run, plus(rows.drop("_part"), sequence_id="long", offset="long"))


def pack_documents(docs: DataFrame, path: str, end_id: int = 2, size: int = SEQUENCE) -> DataFrame:
    """Tokenises, cuts and packs whole documents: PIECES with sequence_id and offset."""
    return pack(materialize(pieces(docs, path, end_id, size), "pieces"), size)
