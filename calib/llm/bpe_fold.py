"""Byte-level BPE encoding and decoding, with the merges folded by Spark's higher-order functions.

A word starts as the ids of its bytes. A fold then merges, one at a time, the leftmost adjacent pair of least
rank, looked up in a literal rank map, until no pair of the word is in it. The most frequent words of the
corpus are merged once and sent to all tasks as a dictionary of bounded size; other words are merged once in
each run of texts that has them. Python and Arrow only split texts into words and put ids and pieces together.
"""

from __future__ import annotations

import base64
import heapq
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.llm.encoding import ODD_BLANK, le32, space_chunks
from calib.llm.shared import materialize, plus

#: Most words in the dictionary that is sent to the tasks, and most bytes of a word there.
DICTIONARY, WORD_BYTES = 1_000_000, 64
#: Bits of an id; ids from MARK on stand for words whose ids are not known yet.
ID_BITS = 21
MARK = 1 << 31
#: Words of more bytes are merged with a heap, because the fold copies a word with every merge.
LONGEST_FOLDED = 400
#: Ids that are decoded together, and chunks whose ids are put together.
PIECES = 1 << 18
#: Most chunks of text that a task takes together, unless one text has more.
CHUNKS = 400_000
#: Chunks that are cut by one search.
AT_ONCE = 1 << 12
#: Chunks and rare words in a row of news. The JVM does badly with rows of half a megabyte and more.
NEWS, RARE = 1 << 12, 1 << 10
#: Words, where the ids of each end, with 0 in front, and ids (32 bits each).
Known = tuple[pa.StringArray, np.ndarray, np.ndarray]
#: Texts that must not be cut at every space, chunks with blanks at their ends, and chunks of plain letters: all for Arrow's regular expressions.
_UNEVEN, _BLANK_ENDS, _LETTERS = f"^ | $|  | \n|\n |{ODD_BLANK.pattern}", f" |^\n|\n$|{ODD_BLANK.pattern}", "^[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+$"


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


def pair_ranks(ranks: dict[bytes, int]) -> dict[tuple[int, int], int]:
    """Rank of every adjacent pair of tokens whose bytes together are a token."""
    out = {}
    for token, r in ranks.items():
        for k in range(1, len(token)):
            a, b = ranks.get(token[:k]), ranks.get(token[k:])
            if a is not None and b is not None:
                out[a, b] = r
    return out


def rank_map(pairs: dict[tuple[int, int], int]) -> tuple[np.ndarray, np.ndarray]:
    """(starts, table): the rank of (a, b) is in table[starts[a] + b], beside a + 1, which tells whether the entry is a's.

    The rows of all left ids lie over one another, each shifted to the first place where its entries fall on free ones.
    """
    ab, rank = np.array(list(pairs), dtype=np.int64).reshape(-1, 2), np.array(list(pairs.values()), dtype=np.int64)
    top = int(max(ab.max(initial=0), rank.max(initial=0), 255)) + 1
    if top >> ID_BITS:
        raise ValueError(f"ids of more than {ID_BITS} bits")
    order = np.lexsort((ab[:, 1], ab[:, 0]))
    ab, rank = ab[order], rank[order]
    left, first, count = np.unique(ab[:, 0], return_index=True, return_counts=True)
    starts, table = np.zeros(top, dtype=np.int64), np.zeros(2 * top + 2 * len(rank) + 4096, dtype=np.int64)
    at, before = 0, 0
    for k in np.argsort(-count, kind="stable").tolist():
        n = int(count[k])
        row = ab[first[k] : first[k] + n, 1]
        if n != before:
            at, before = 0, n  # rows of one size search on from where the last of them was put
        step = max(1, min(2048, 200_000 // n))  # places tried at once
        while True:
            if at + step + top > len(table):
                table = np.concatenate([table, np.zeros_like(table)])
            free = np.arange(at, at + step)
            for b in row[:4].tolist():
                free = free[table[free + b] == 0]
            free = free[(table[free[:, None] + row] == 0).all(axis=1)] if len(free) else free
            if len(free):
                at = int(free[0])
                break
            at += step
        starts[left[k]] = at
        table[at + row] = (left[k] + 1) << ID_BITS | rank[first[k] : first[k] + n]
    return starts, table[: int(starts.max()) + top]


def _rank_sql(a: str, b: str) -> str:
    """A pair's rank, or a number of more bits."""
    return f"(m.t[m.s[{a}] + {b}] ^ shiftleft({a} + 1, {ID_BITS}))"


def fold_sql(ids: str) -> str:
    """SQL for the ids of one word, from the ids of its bytes; m holds the rank map."""
    ranks = f"transform(s, (x, i) -> {_rank_sql('x', 'get(s, i + 1)')})"
    merge = "transform(array(cast(array_position(r, least) as int)), p -> concat(slice(s, 1, p - 1), array(least), slice(s, p + 2, size(s))))[0]"
    step = f"transform(array({ranks}), r -> transform(array(array_min(r)), least -> if(least < {1 << ID_BITS}L, {merge}, s))[0])[0]"
    return f"if(size({ids}) < 2, {ids}, aggregate(sequence(2, size({ids})), {ids}, (s, _) -> {step}))"


def merged(words: str, ranks: dict[bytes, int], maps: tuple[np.ndarray, np.ndarray], bytes_given: bool = False):
    """Column: the ids of each word of an array column: binary words, or (bytes_given) arrays of their bytes' ids. The rank map is a literal."""
    starts, table = maps
    lit = lambda xs: f"cast(split('{','.join(map(str, xs))}', ',') as array<bigint>)"
    if not bytes_given:
        cut = "if(length(x) = 0, cast(array() as array<bigint>), transform(sequence(1, length(x)), i -> m.b[cast(conv(hex(substring(x, i, 1)), 16, 10) as int)]))"
        words = f"transform({words}, x -> {cut})"
    literal = f"named_struct('t', {lit(table.tolist())}, 's', {lit(starts.tolist())}, 'b', {lit(ranks[bytes([b])] for b in range(256))})"
    return F.expr(f"transform(array({literal}), m -> transform({words}, w -> {fold_sql('w')}))[0]")


def heap_merged(word: bytes, byte_rank: np.ndarray, starts: np.ndarray, table: np.ndarray) -> bytes:
    """The ids of one very long word, by the same merges in the same order."""
    ids = byte_rank[np.frombuffer(word, np.uint8)].tolist()
    n = len(ids)
    before, after = list(range(-1, n - 1)), list(range(1, n + 1))

    def rank(a: int, b: int) -> int:
        return int(table[starts[a] + b]) ^ (a + 1) << ID_BITS

    x = np.array(ids, dtype=np.int64)
    found = table[starts[x[:-1]] + x[1:]] ^ (x[:-1] + 1) << ID_BITS
    heap = [(r, i) for i, r in enumerate(found.tolist()) if r < 1 << ID_BITS]
    heapq.heapify(heap)
    while heap:
        r, i = heapq.heappop(heap)
        j = after[i] if ids[i] >= 0 else n
        if j >= n or rank(ids[i], ids[j]) != r:
            continue  # one of the two has been merged meanwhile
        ids[i], ids[j], after[i] = r, -1, after[j]
        if after[i] < n:
            before[after[i]] = i
            if (up := rank(r, ids[after[i]])) < 1 << ID_BITS:
                heapq.heappush(heap, (up, i))
        if before[i] >= 0 and (up := rank(ids[before[i]], r)) < 1 << ID_BITS:
            heapq.heappush(heap, (up, before[i]))
    return le32([v for v in ids if v >= 0])


@cache
def stand_ins() -> dict[int, str]:
    """For characters that regex and tiktoken put into different classes, because they know different versions of Unicode: one of tiktoken's class."""
    import regex
    import tiktoken

    every = "".join(map(chr, chain(range(0xD800), range(0xE000, 0x110000))))
    each_byte = {bytes([b]): b for b in range(256)}
    out = {}
    classes = ((r"\p{L}", "a"), (r"\p{N}", "1"), (r"\s", "\t"))
    found = [(set(bytes(tiktoken.Encoding(p, pat_str=p, mergeable_ranks=each_byte, special_tokens={}).encode_ordinary(every)).decode()), set(regex.findall(p, every)), c) for p, c in classes]
    for theirs, ours, _ in found:
        out |= dict.fromkeys(map(ord, ours - theirs), "!")
    for theirs, ours, c in found:
        out |= dict.fromkeys(map(ord, theirs - ours), c)
    return out


def _splitter(pattern: str, others: dict[int, str]):
    """Cuts a text into words as tiktoken does; others: what stand_ins() gave."""
    import regex

    matches = regex.compile(pattern)
    if not others:
        return matches.findall
    usual = frozenset(map(chr, others)).isdisjoint

    def split(text: str) -> list[str]:
        if text.isascii() or usual(text):
            return matches.findall(text)
        return [text[m.start() : m.end()] for m in matches.finditer(text.translate(others))]

    return split


@dataclass
class Cut:
    """Texts as numbers of distinct chunks, and those chunks as numbers of distinct words."""

    order: np.ndarray  #: the rows of the texts given, in the order that they have here
    codes: np.ndarray  #: the chunks of all texts
    ends: np.ndarray  #: where each text's chunks end, with 0 in front
    words: pa.StringArray  #: distinct words
    of_chunks: np.ndarray  #: the words of all chunks
    word_ends: np.ndarray  #: where each chunk's words end, with 0 in front


def runs(texts: pa.Array, most: int) -> Iterator[pa.StringArray]:
    """Texts, without nulls, in runs of at most so many chunks, or of one text. Longer chunks count as several."""
    texts = pc.fill_null(texts, "")
    chunks = np.maximum(pc.count_substring(texts, " ").to_numpy(zero_copy_only=False) + 1, pc.binary_length(texts).to_numpy(zero_copy_only=False) // 8)
    ends, a = np.concatenate(([0], np.cumsum(chunks, dtype=np.int64))), 0
    while a < len(texts):
        b = max(a + 1, int(np.searchsorted(ends, ends[a] + most, side="right")) - 1)
        yield texts.slice(a, b - a)
        a = b


def cut(split, texts: pa.StringArray) -> Cut:
    """Chunks are cut and numbered by Arrow, so that Python sees each of them once, however often the texts have it. A chunk that a space precedes and the same one at the start of a text are two."""
    odd = pc.match_substring_regex(texts, _UNEVEN).to_numpy(zero_copy_only=False)
    order = np.concatenate([np.flatnonzero(~odd), np.flatnonzero(odd)])
    lists = pc.split_pattern(texts.filter(pa.array(~odd)) if odd.any() else texts, " ")
    if odd.any():
        lists = pa.concat_arrays([lists, pa.array(map(space_chunks, texts.filter(pa.array(odd)).to_pylist()), pa.list_(pa.string()))])
    every, ends = lists.flatten(), np.concatenate(([0], np.cumsum(lists.value_lengths().to_numpy())))
    heads = every.take(pa.array(ends[:-1])).dictionary_encode()
    inner = np.ones(every.offset + len(every), bool)
    inner[every.offset + ends[:-1]] = False
    _, offsets, data = every.buffers()
    rest = pa.StringArray.from_buffers(len(every), offsets, data, pa.py_buffer(np.packbits(inner, bitorder="little")), offset=every.offset).dictionary_encode()
    codes = rest.indices.fill_null(0).to_numpy().copy()
    after = rest.dictionary
    letters = pc.match_substring_regex(after, _LETTERS).to_numpy(zero_copy_only=False)
    number = np.empty(len(after), np.int32)  # plain letters first
    number[np.concatenate([np.flatnonzero(letters), np.flatnonzero(~letters)])] = np.arange(len(after))
    codes = number[codes] if len(after) else codes
    codes[ends[:-1]] = len(after) + heads.indices.to_numpy()
    plain = pc.binary_join_element_wise(pa.scalar(" "), after.filter(pa.array(letters)), "")
    found, sizes = cut_apart(split, after.filter(pa.array(~letters)))
    first = [split(c) for c in heads.dictionary.to_pylist()]
    words = pa.concat_arrays([plain, found, pa.array(chain.from_iterable(first), pa.string())]).dictionary_encode()
    sizes = np.concatenate([[0], np.ones(len(plain), np.int64), sizes, np.array(list(map(len, first)), np.int64)])
    return Cut(order, codes, ends, words.dictionary, words.indices.to_numpy(), np.cumsum(sizes).astype(np.int64))


def cut_apart(split, chunks: pa.StringArray) -> tuple[pa.StringArray, np.ndarray]:
    """The words of chunks that a space precedes, and how many each has. Chunks without blanks at their ends are cut many at a time; each then gives one word that starts with a space."""
    out, sizes = [], []
    for at in range(0, len(chunks), AT_ONCE):
        some = chunks.slice(at, AT_ONCE)
        if not pc.any(pc.match_substring_regex(some, _BLANK_ENDS)).as_py():
            words = pa.array(split(" " + " ".join(some.to_pylist())), pa.string())
            starts = np.flatnonzero(pc.starts_with(words, " ").to_numpy(zero_copy_only=False))
            if len(starts) == len(some):
                out.append(words)
                sizes.append(np.diff(starts, append=len(words)))
                continue
        each = [split(" " + c) for c in some.to_pylist()]
        out.append(pa.array(chain.from_iterable(each), pa.string()))
        sizes.append(np.array(list(map(len, each)), np.int64))
    return (pa.concat_arrays(out), np.concatenate(sizes)) if out else (pa.array([], pa.string()), np.zeros(0, np.int64))


def word_counts(docs: DataFrame, pattern: str) -> DataFrame:
    """(word, n) over all texts; n is partial where a task gives a word again."""
    others = stand_ins()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = _splitter(pattern, others)
        for b in batches:
            for texts in runs(b.column("text"), CHUNKS):
                c = cut(split, texts)
                of_chunk = np.bincount(c.codes, minlength=len(c.word_ends) - 1)
                n = np.bincount(c.of_chunks, np.repeat(of_chunk, np.diff(c.word_ends)), len(c.words))
                yield pa.RecordBatch.from_arrays([c.words, pa.array(n.astype(np.int64))], names=["word", "n"])

    return docs.select(F.col("text").cast("string")).mapInArrow(run, "word string, n long")


def dictionary(docs: DataFrame, pattern: str, ranks: dict[bytes, int], maps: tuple[np.ndarray, np.ndarray], limit: int = DICTIONARY) -> Known:
    """The most frequent words, at most `limit`, and the ids of each. Which counts make the limit is read off a histogram."""
    counts = word_counts(docs, pattern).groupBy("word").agg(F.sum("n").alias("n")).where(F.expr(f"n > 1 AND octet_length(word) <= {WORD_BYTES}"))
    counts = materialize(counts, "words")
    step = F.floor(F.log2(F.col("n").cast("double")) * 16)
    room, least = limit, None
    for r in sorted(counts.groupBy(step.alias("step")).count().collect(), reverse=True):
        room -= r["count"]
        if room < 0:
            break
        least = r["step"]
    if least is None:
        return pa.array([], pa.string()), np.zeros(1, np.int64), np.zeros(0, "<u4")
    found = counts.where(step >= least).select("word", merged("array(encode(word, 'UTF-8'))", ranks, maps)[0].alias("ids")).toArrow()
    ids = found.column("ids").combine_chunks()
    return found.column("word").combine_chunks().cast(pa.string()), np.concatenate(([0], np.cumsum(ids.value_lengths().to_numpy()))).astype(np.int64), ids.flatten().to_numpy(zero_copy_only=False).astype("<u4")


def look_up(known: Known, words: pa.StringArray, merge_long) -> tuple[np.ndarray, np.ndarray, np.ndarray, pa.BinaryArray]:
    """(ids, start, size, rare): where the ids of each word are, with a mark for each of the rare words, which are still to be merged."""
    theirs, at, ids = known
    of_theirs = pc.index_in(theirs, words)  # the smaller side is hashed
    place = np.full(len(words), -1)
    place[of_theirs.drop_null().to_numpy()] = np.flatnonzero(of_theirs.is_valid().to_numpy(zero_copy_only=False))
    start, size = at[place], at[place + 1] - at[place]  # put right below for those not found
    missing = np.flatnonzero(place < 0)
    long = pc.binary_length(words).to_numpy(zero_copy_only=False)[missing] > LONGEST_FOLDED
    rare, pool = missing[~long], [ids, np.arange(MARK, MARK + int((~long).sum()), dtype="<u4")]
    start[rare], size[rare] = len(ids) + np.arange(len(rare)), 1
    used = len(ids) + len(rare)
    for k in missing[long].tolist():
        pool.append(np.frombuffer(merge_long(words[k].as_py().encode()), "<u4"))
        start[k], size[k] = used, len(pool[-1])
        used += len(pool[-1])
    return np.concatenate(pool), start, size, words.take(pa.array(rare)).cast(pa.binary())


_TASK = "doc_id long, chunks binary, news boolean, afresh boolean, sizes binary, ids binary, rare array<array<long>>"


def encode(docs: DataFrame, pattern: str, ranks: dict[bytes, int], decoded: bool = False) -> DataFrame:
    """doc_id and ids (little-endian unsigned 32-bit) of every whole text; null and empty texts have none. decoded: also what decode() would give, in the same pass.

    A task turns a run of texts into numbers of chunks, and sends rows of news before them: the ids of the run's
    chunks, as far as known, and words to be merged. The fold runs over the news, and the task's second half
    puts ids in place of numbers. Other columns are not read, and repeated rows are encoded one by one.
    Words of more than LONGEST_FOLDED bytes are merged with a heap, in time that grows little faster than they.
    """
    sc = docs.sparkSession.sparkContext
    maps, others = rank_map(pair_ranks(ranks)), stand_ins()
    byte_rank = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int64)
    sent, sent_maps = sc.broadcast(dictionary(docs, pattern, ranks, maps)), sc.broadcast(maps)

    def news(c: Cut) -> Iterator[pa.RecordBatch]:
        ids, start, size, rare = look_up(sent.value, c.words, lambda w: heap_merged(w, byte_rank, *sent_maps.value))
        each = size[c.of_chunks]
        ends = np.concatenate(([0], np.cumsum(each)))[c.word_ends]
        ids = ids[spread(start[c.of_chunks], each)]
        for k in range(max(1, -(-len(ends) // NEWS), -(-len(rare) // RARE))):
            some = ends[k * NEWS : (k + 1) * NEWS + 1]
            head = [np.diff(some).astype(np.int32).tobytes(), ids[some[0] : some[-1]].tobytes()] if len(some) else [b"", b""]
            data, byte_ends = _flat(rare.slice(k * RARE, RARE))
            words = pa.ListArray.from_arrays(pa.array(byte_ends, pa.int32()), pa.array(byte_rank[data], pa.int64()))
            yield _rows(pa.nulls(1, pa.int64()), pa.array([b""], pa.binary()), True, k == 0, *head, pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), words))

    def assemble(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split = _splitter(pattern, others)
        for batch in batches:
            at = 0
            for texts in runs(batch.column("text"), CHUNKS):
                c = cut(split, texts)
                yield from news(c)
                none = pa.ListArray.from_arrays(pa.array(np.zeros(len(texts) + 1), pa.int32()), pa.array([], pa.list_(pa.int64())))
                yield _rows(batch.column("doc_id").take(pa.array(at + c.order)), _binary(c.codes.view(np.uint8), 4 * c.ends), False, False, b"", b"", none)
                at += len(texts)

    pieces = Pieces(ranks) if decoded else None
    schema = "doc_id long, ids binary" + ", decoded binary" * decoded

    def complete(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = Run()
        for batch in batches:
            told = np.flatnonzero(batch.column("news").to_numpy(zero_copy_only=False))
            starts = sorted({0, *told.tolist(), *(told + 1).tolist()} - {batch.num_rows})  # a batch may begin with news or amid the texts of earlier ones
            told = set(told.tolist())
            for at, end in zip(starts, [*starts[1:], batch.num_rows]):
                if at in told:
                    known.add(batch.slice(at, 1))
                elif end > at:
                    yield from finished(batch.slice(at, end - at), known)

    def finished(b: pa.RecordBatch, known: Run) -> Iterator[pa.RecordBatch]:
        codes, ends = _flat(b.column("chunks"))
        codes, ends, a = codes.view(np.int32), ends // 4, 0
        while a < b.num_rows:
            z = max(a + 1, int(np.searchsorted(ends, ends[a] + PIECES, side="right")) - 1)
            ids, id_ends = known.ids_of(codes[ends[a] : ends[z]], ends[a : z + 1] - ends[a])
            more = [pieces.joined(ids, id_ends)] if decoded else []
            yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(a, z - a), _binary(ids.view(np.uint8), 4 * id_ends), *more], names=["doc_id", "ids", "decoded"][: 2 + decoded])
            a = z

    rows = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(assemble, _TASK)
    rows = rows.withColumn("rare", merged("rare", ranks, maps, bytes_given=True))
    return rows.mapInArrow(complete, schema)


def _rows(doc_id: pa.Array, chunks: pa.Array, news: bool, afresh: bool, sizes: bytes, ids: bytes, rare: pa.Array) -> pa.RecordBatch:
    """Rows as in _TASK, which have all but doc_id, chunks and rare in common."""
    n = len(doc_id)
    return pa.RecordBatch.from_arrays([doc_id, chunks, pa.array([news] * n), pa.array([afresh] * n), pa.array([sizes] * n, pa.binary()), pa.array([ids] * n, pa.binary()), rare], names=["doc_id", "chunks", "news", "afresh", "sizes", "ids", "rare"])


class Run:
    """The ids of the chunks of a run of texts by their numbers: first as its news come in, then as they are asked for."""

    def __init__(self):
        self.told, self.size, self.flat, self.start = [], np.zeros(0, np.int64), np.zeros(0, "<u4"), np.zeros(0, np.int64)

    def add(self, row: pa.RecordBatch) -> None:
        if row.column("afresh")[0].as_py():
            self.told = []
        words = row.column("rare").flatten()
        self.told.append((np.frombuffer(row.column("sizes")[0].as_py(), np.int32), np.frombuffer(row.column("ids")[0].as_py(), "<u4"), words.value_lengths().to_numpy(), words.flatten().to_numpy(zero_copy_only=False).astype("<u4")))

    def fill(self) -> None:
        """Puts ids in the place of marks."""
        size, flat, lengths, rare = map(np.concatenate, zip(*self.told))
        self.told, size, lengths = [], size.astype(np.int64), lengths.astype(np.int64)
        marks = np.flatnonzero(flat >= MARK)
        if len(marks):
            k = flat[marks].astype(np.int64) - MARK
            each = np.ones(len(flat), np.int64)
            each[marks] = lengths[k]
            ends = np.cumsum(each)
            flat = np.repeat(flat, each)
            flat[spread(ends[marks] - lengths[k], lengths[k])] = rare[spread((np.cumsum(lengths) - lengths)[k], lengths[k])]
            size = np.diff(np.concatenate(([0], ends))[np.concatenate(([0], np.cumsum(size)))])
        self.size, self.flat, self.start = size, flat, np.cumsum(size) - size

    def ids_of(self, chunks: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of texts by their chunks, and where each text's end; ends: where its chunks do, with 0 in front."""
        if self.told:
            self.fill()
        size = self.size[chunks]
        return self.flat[spread(self.start[chunks], size)], np.concatenate(([0], np.cumsum(size)))[ends]


class Pieces:
    """The binary piece of every id, end to end."""

    def __init__(self, ranks: dict[bytes, int]):
        pieces = [b""] * (max(ranks.values(), default=-1) + 1)
        for t, r in ranks.items():
            pieces[r] = t
        self.bytes = np.frombuffer(b"".join(pieces), np.uint8)
        self.size = np.array(list(map(len, pieces)), np.int64)
        self.start = np.cumsum(self.size) - self.size

    def joined(self, ids: np.ndarray, ends: np.ndarray) -> pa.Array:
        """The bytes that ids stand for, of all texts; ends: where each text's ids end, with 0 in front. Texts are taken together up to some size."""
        out, a = [], 0
        while a < len(ends) - 1:
            b = max(a + 1, int(np.searchsorted(ends, ends[a] + PIECES, side="right")) - 1)
            x = ids[ends[a] : ends[b]]
            size = self.size[x]
            out.append(_binary(self.bytes[spread(self.start[x], size)], np.concatenate(([0], np.cumsum(size)))[ends[a : b + 1] - ends[a]]))
            a = b
        return pa.concat_arrays(out) if out else pa.array([], pa.binary())


def spread(start: np.ndarray, size: np.ndarray) -> np.ndarray:
    """start, start + 1, .. for each run, one after the other."""
    ends = np.cumsum(size)
    return np.repeat(start - ends + size, size) + np.arange(int(ends[-1]) if len(ends) else 0)


def _flat(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a binary column without nulls, and where each value ends, with 0 in front."""
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] else np.zeros(0, np.uint8)
    return data[ends[0] : ends[-1]], ends - ends[0]


def _binary(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    if int(ends[-1]) >= 1 << 31:
        raise ValueError("the texts of one batch need more than 2 GB")
    return pa.BinaryArray.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def decode(rows: DataFrame, ranks: dict[bytes, int]) -> DataFrame:
    """Adds `decoded`, the joined bytes of the pieces, to rows with ids."""
    sent = rows.sparkSession.sparkContext.broadcast(Pieces(ranks))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            data, ends = _flat(pc.fill_null(b.column("ids"), b""))
            yield pa.RecordBatch.from_arrays([*b.columns, sent.value.joined(data.view("<u4"), ends // 4)], names=[*b.schema.names, "decoded"])

    return rows.mapInArrow(run, plus(rows, decoded="binary"))


def digests(rows: DataFrame) -> DataFrame:
    """doc_id, n_tokens, ids_sha256 and decoded_sha256 of encoded and decoded rows."""
    return rows.select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
