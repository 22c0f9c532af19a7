"""Byte-level BPE: ranked merges as Spark higher-order functions.

A word is an array of one long for each of its bytes, between a start and an end mark: the id, above it the place in the word, and
above that the rank of the pair that it opens. A fold joins, in each step, the leftmost pair of the lowest rank, which is the least
number of the array, and looks up the two pairs this makes. A step calls no function for each element. Ranks are looked up in a literal map: the sparse matrix of pairs is packed into one array, each left id's row shifted by an offset so that
no two entries meet; a look-up reads one offset and one entry however large the vocabulary. The map stands in the plan as
text and becomes arrays once for every thousands of words: as an array literal its boxed numbers would be read by every task.

Words repeat, so distinct words are encoded once in a block of documents: a block ends where it has `distinct` words that are not
remembered (or 1.5 million words in all), and a document is in one block. One narrow plan does it, without a shuffle: a Python
step cuts texts and numbers the words of a block, the fold encodes the words, a second Python step puts ids in the place of
numbers, and decodes. It relies on the order of rows in a partition, which projections keep: words first, then their documents.
Words that are frequent in a sample of about `sampled` documents (at most `remembered` words, a fixed bound) are encoded before, and
broadcast. Sample and bounds decide only where a word is encoded, never how; a task's memory holds one block.
Words longer than `longest` bytes, for which a fold of quadratic cost would not do, are merged with a heap instead; the result
is the same (the tests hold one against the other).

Decoding concatenates the binary pieces of the ids.

Defined results: null is as the empty text and has no ids; every id list decodes to the text's own UTF-8 bytes. Rows are worked
on by themselves, so repeated ids are no matter, and a null id stays null. Other columns are not read. An empty table gives an
empty result. The vocabulary file is a parameter, read on the driver.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import give_back, materialise, slices, unmaterialise

NEVER = 1 << 17  # rank of a pair that is no token
PLACE, RANK = 16, 32  # bits at which the place and the rank begin; places fit 16 bits
EMPTY = -1  # as an unsigned number its left id is 65,535, which no vocabulary here has
CHUNK = 150_000  # words that one row holds for the fold
WINDOW = 4096  # offsets tried at once when the pairs are packed
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


@dataclass(frozen=True)
class Vocabulary:
    """Ranks of byte strings; rank and id are the same."""

    ranks: dict[bytes, int]

    @classmethod
    def read(cls, path: str) -> Vocabulary:
        with open(path, "rb") as lines:
            return cls({base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)})

    def pairs(self) -> Iterator[tuple[int, int, int]]:
        """Every pair of tokens whose bytes together are a token."""
        for token, rank in self.ranks.items():
            for cut in range(1, len(token)):
                left, right = self.ranks.get(token[:cut]), self.ranks.get(token[cut:])
                if left is not None and right is not None:
                    yield left, right, rank

    def packed(self) -> tuple[np.ndarray, np.ndarray]:
        """Offset of each left id's row, and the entries: at offset[left] + right stands left * 65536 + rank, as a signed 32-bit integer.

        Two more ids mark the start and the end of a word; they open and close no pair.
        """
        rows: dict[int, list[int]] = {}
        for left, right, rank in self.pairs():
            rows.setdefault(left, []).append(right << 16 | rank)
        width = max(self.ranks.values(), default=0) + 1
        if width > 65_533:
            raise ValueError("ids must fit 16 bits")
        offsets, free = np.zeros(width + 2, np.int64), np.ones(8 * width + 4 * WINDOW, bool)
        slots, hint = np.full(len(free), EMPTY, np.int32), {}

        def place(left: int, at: int) -> None:
            rights = np.array(rows[left]) >> 16
            offsets[left], free[at + rights] = at, False
            slots[at + rights] = ((left << 16) + (np.array(rows[left]) & 65_535)).astype(np.uint32).view(np.int32)

        for left in sorted((x for x in rows if len(rows[x]) > 1), key=lambda x: (-len(rows[x]), x)):
            rights = np.array(rows[left]) >> 16
            at = hint.get(len(rights), 0)  # rows of one length are placed from where the last one went
            while not (fits := np.logical_and.reduce([free[at + r : at + r + WINDOW] for r in rights])).any():
                at += WINDOW
            hint[len(rights)] = at = at + int(fits.argmax())
            place(left, at)
        holes, k = np.flatnonzero(free), 0
        for right, left in sorted((rows[x][0] >> 16, x) for x in rows if len(rows[x]) == 1):
            k += int(np.searchsorted(holes[k:], right))
            place(left, int(holes[k]) - right)
            k += 1
        return offsets, slots[: int(offsets.max()) + width + 3]

    def pieces(self) -> list[bytes]:
        found = [b""] * (max(self.ranks.values(), default=-1) + 1)
        for token, rank in self.ranks.items():
            found[rank] = token
        return found

    def merge(self, word: bytes) -> list[int]:
        """Ids of one word, in time n log n, by a heap of pairs."""
        ranks, n = self.ranks, len(word)
        after, before, ends = [*range(1, n + 1)], [*range(-1, n - 1)], [*range(1, n + 1)]
        heap = []

        def offer(i: int) -> None:
            j = after[i]
            if j < n and (rank := ranks.get(word[i : ends[j]])) is not None:
                heap.append((rank, i, ends[j])) if not started else heapq.heappush(heap, (rank, i, ends[j]))

        started = False
        for i in range(n):
            offer(i)
        heapq.heapify(heap)
        started = True
        gone = bytearray(n + 1)
        while heap:
            _, i, end = heapq.heappop(heap)
            if gone[i] or after[i] >= n or ends[after[i]] != end or ends[i] == end:
                continue
            j = after[i]
            gone[j], ends[i], after[i] = 1, end, after[j]
            if after[i] < n:
                before[after[i]] = i
            offer(i)
            if before[i] >= 0:
                offer(before[i])
        return [ranks[word[i : ends[i]]] for i in range(n) if not gone[i]]


def literal(values: np.ndarray, fresh: Column) -> Column:
    """A constant array of integers, read from its text; `fresh`, an empty text of the row, keeps it a text in the plan."""
    return F.from_json(F.concat(F.lit("[" + ",".join(map(str, values.tolist())) + "]"), fresh), "array<int>")


def let(value: Column, body) -> Column:
    """body(value), with value evaluated once.

    The end of an empty fold: an element got from a transform would have the types of the whole body worked out at each evaluation.
    """
    return F.aggregate(F.array().cast("array<int>"), value, lambda same, _: same, body)


@dataclass(frozen=True)
class Merger:
    """The packed map, for arrays of numpy and for columns."""

    bytes: np.ndarray
    offsets: np.ndarray
    entries: np.ndarray

    @classmethod
    def of(cls, vocabulary: Vocabulary) -> Merger:
        return cls(np.array([vocabulary.ranks[bytes([b])] for b in range(256)], np.int64), *vocabulary.packed())

    @property
    def marks(self) -> tuple[int, int]:
        return len(self.offsets) - 2, len(self.offsets) - 1

    def opened(self, words: list[bytes], longest: int, heap) -> pa.ListArray:
        """The arrays that the fold begins with; those of longer words, merged by heap(word), are as it would end."""
        start, end = self.marks
        done = {k: heap(w) for k, w in enumerate(words) if len(w) > longest}
        ids = [np.asarray(done[k], np.int64) if k in done else self.bytes[np.frombuffer(w, np.uint8)] for k, w in enumerate(words)] if done else None
        lengths = np.array([len(x) for x in ids or words], np.int64) + 2
        ends = np.cumsum(lengths)
        flat = np.full(int(ends[-1]) if len(ends) else 0, end, np.int64)
        flat[ends - lengths] = start
        inner = np.ones(len(flat), bool)
        inner[ends - lengths] = inner[ends - 1] = False
        flat[inner] = np.concatenate(ids) if ids else self.bytes[np.frombuffer(b"".join(words), np.uint8)]
        found = self.entries[self.offsets[flat[:-1]] + flat[1:]].astype(np.int64)
        places = (np.arange(len(flat)) - np.repeat(ends - lengths, lengths)) & 65_535  # those of words that are done may wrap
        packed = np.append((np.minimum((found ^ (flat[:-1] << 16)) & 0xFFFFFFFF, NEVER) << RANK) | flat[:-1], 0) if len(flat) else flat
        closed = ends - 1
        if done:
            closed = np.concatenate([closed, *(np.arange(ends[k] - lengths[k], ends[k]) for k in done)])
        packed[closed] = NEVER << RANK | flat[closed]
        packed |= places << PLACE
        return pa.ListArray.from_arrays(pa.array(np.append(0, ends).astype(np.int32)), pa.array(packed))

    @staticmethod
    def ids(words: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and how many each word has."""
        lengths, flat = words.value_lengths().to_numpy(), words.flatten().to_numpy()
        ends, inner = np.cumsum(lengths), np.ones(len(flat), bool)
        inner[ends - lengths] = inner[ends - 1] = False
        return (flat[inner] & 65_535).astype(np.uint32), lengths.astype(np.int64) - 2

    def fold(self, words: Column, fresh: Column) -> Column:
        """Merges every word of an array of opened words."""
        low, least = F.lit(65_535).cast("bigint"), F.lit(1 << 16 + RANK).cast("bigint")
        id_of, place_of = (lambda x: x.bitwiseAND(low)), (lambda x: x.bitwiseAND(low * (1 << PLACE)))  # the place stays where it stands

        def with_tables(t: Column) -> Column:
            def opens(left: Column, right: Column, place: Column) -> Column:
                # an entry of the same left id leaves its rank, any other at least 65,536
                found = F.get(t["entries"], F.get(t["offsets"], left) + right).bitwiseXOR(F.shiftleft(left, 16))
                rank = F.least(found.bitwiseAND(F.lit(0xFFFFFFFF).cast("bigint")), F.lit(NEVER).cast("bigint"))
                return F.shiftleft(rank, RANK).bitwiseOR(place).bitwiseOR(left)

            def step(word: Column, _: Column) -> Column:
                def joined(lowest: Column) -> Column:
                    new = F.shiftright(lowest, RANK)  # the rank, which is the new id

                    def at_place(at: Column) -> Column:
                        before = F.get(word, at - 2)
                        made = F.array(opens(id_of(before), new, place_of(before)), opens(new, id_of(F.get(word, at + 1)), place_of(lowest)))
                        return F.concat(F.slice(word, 1, at - 2), made, F.slice(word, at + 2, F.size(word)))  # flatten would ask for types at each evaluation

                    return F.when(lowest < least, let(F.array_position(word, lowest).cast("int"), at_place)).otherwise(word)

                return let(F.array_min(word), joined)

            return F.transform(words, lambda word: F.when(F.array_min(word) < least, F.aggregate(F.sequence(F.lit(4), F.size(word)), word, step)).otherwise(word))

        return let(F.struct(literal(self.offsets, fresh).alias("offsets"), literal(self.entries, fresh).alias("entries")), with_tables)


class Splitter:
    """Cuts texts into the matches of the tokenizer's pattern."""

    # fixed values: what the pattern's classes hold below U+0250
    LETTERS, NUMBERS, SPACES = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-ɏ", "0-9\xb2\xb3\xb9\xbc-\xbe", "\t-\r \x85\xa0"

    def __init__(self, pattern: str):
        self.whole = regex.compile(pattern)
        self.plain = re.compile("[\x00-ɏ]*")
        classes = {r"[^\s\p{L}\p{N}]": f"[^{self.SPACES}{self.LETTERS}{self.NUMBERS}]", r"\p{L}": f"[{self.LETTERS}]", r"\p{N}": f"[{self.NUMBERS}]", r"\s": f"[{self.SPACES}]", r"\S": f"[^{self.SPACES}]"}
        for name, chars in classes.items():
            pattern = pattern.replace(name, chars)
        self.fast = re.compile(pattern) if "\\p" not in pattern else self.whole

    def __call__(self, text: str | None) -> list[str]:
        if not text:
            return []
        return (self.fast if self.plain.fullmatch(text) else self.whole).findall(text)


def word_counts(documents: DataFrame, pattern: str, text_column: str = "text", longest: int = 64, at_once: int = 100_000) -> DataFrame:
    """word, n over all texts; longer words are left to the documents' own rows."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        split, counts = Splitter(pattern), Counter()

        def flush() -> pa.RecordBatch:
            kept = [(w, n) for w, n in counts.items() if len(w) <= longest]
            counts.clear()
            return pa.RecordBatch.from_arrays([pa.array([w for w, _ in kept], pa.string()), pa.array([n for _, n in kept], pa.int64())], names=["word", "n"])

        for batch in batches:
            for text in batch.column(0):
                counts.update(split(text.as_py()))
                if len(counts) > at_once:
                    yield flush()
        yield flush()

    return documents.select(F.col(text_column).cast("string")).mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def frequent_words(counts: DataFrame, remembered: int) -> DataFrame:
    """The most frequent words, at most so many: those above a count found from a histogram of counts."""
    level = F.floor(F.log2(F.col("n").cast("double")) * 8)
    histogram = {int(r["level"]): int(r["words"]) for r in counts.groupBy(level.alias("level")).agg(F.count("*").alias("words")).collect()}  # 512 levels at most
    least, total = max(histogram, default=0) + 1, 0
    for at in sorted(histogram, reverse=True):
        total += histogram[at]
        if total > remembered:
            break
        least = at
    return counts.where(level >= least)


class Numbers(dict):
    """The numbers of a block's words: those of remembered words are given, new words follow in the order in which they are asked for."""

    def __init__(self, remembered: dict[str, int]):
        super().__init__()
        self.remembered, self.new = remembered, []

    def __missing__(self, word: str) -> int:
        number = self.remembered.get(word)
        if number is None:
            number = len(self.remembered) + len(self.new)
            self.new.append(word)
        self[word] = number
        return number


def remember(documents: DataFrame, vocabulary: Vocabulary, merger: Merger, pattern: str, remembered: int, sampled: int, longest: int) -> tuple[list[str], np.ndarray, np.ndarray]:
    """The words, at most so many, that are frequent in a sample; all their ids, and how many each has."""
    n = documents.count() if remembered else 0
    if not n:
        return [], np.zeros(0, np.uint32), np.zeros(0, np.int64)
    counts = materialise(word_counts(documents.sample(min(1.0, sampled / n), 7), pattern), "words")
    opened = lambda words: merger.opened([w.encode() for w in words], longest, vocabulary.merge)

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = batch.column(0)
            whole = lambda column: pa.ListArray.from_arrays(pa.array([0, len(words)], pa.int32()), column)
            if len(words):
                yield pa.RecordBatch.from_arrays([whole(words), whole(opened(words.to_pylist())), pa.array([""])], names=["word", "opened", "fresh"])

    many = frequent_words(counts, remembered).select("word").mapInArrow(rows, "word array<string>, opened array<array<bigint>>, fresh string")
    found = many.select("word", merger.fold(F.col("opened"), F.col("fresh")).alias("ids")).toArrow()
    unmaterialise(counts)
    ids = [merger.ids(chunk.flatten()) for chunk in found.column(1).chunks]
    words = [w for chunk in found.column(0).chunks for w in chunk.flatten().to_pylist()]
    return words, *(np.concatenate([x[k] for x in ids]) if ids else np.zeros(0, (np.uint32, np.int64)[k]) for k in (0, 1))


def spread(flat: np.ndarray, starts: np.ndarray, lengths: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """flat[starts[i] : starts[i] + lengths[i]] for every i of `of`, end to end, and where each ends."""
    n = lengths[of]
    ends = np.cumsum(n)
    return flat[np.repeat(starts[of] - (ends - n), n) + np.arange(int(ends[-1]) if len(ends) else 0)], ends


def binaries(data: np.ndarray, ends: np.ndarray) -> pa.Array:
    """Binary values that stand end to end in data."""
    return pa.Array.from_buffers(pa.binary(), len(ends), [None, pa.py_buffer(np.append(0, ends).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data))])


def encode(documents: DataFrame, vocabulary: Vocabulary, pattern: str, remembered: int = 150_000, sampled: int = 8_000, distinct: int = 120_000, longest: int = 256, decoded: bool = False) -> DataFrame:
    """doc_id and ids (little-endian unsigned 32-bit integers as bytes) of every text, and with `decoded` the bytes that these decode to."""
    sc, merger = documents.sparkSession.sparkContext, Merger.of(vocabulary)
    words, known, lengths = remember(documents, vocabulary, merger, pattern, remembered, sampled, longest)
    before = sc.broadcast((pa.array(words, pa.string()), vocabulary, merger))
    after = sc.broadcast((known, lengths, vocabulary.pieces() if decoded else []))
    del words, known, lengths
    row = pa.schema([("doc_id", pa.int64()), ("numbers", pa.binary()), ("words", pa.list_(pa.list_(pa.int64()))), ("fresh", pa.string())])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        remembered, vocabulary, merger = before.value
        split, common = Splitter(pattern), dict(zip(remembered.to_pylist(), range(len(remembered)), strict=True))
        numbers, ids, texts, total, pack = Numbers(common), [], [], 0, zstandard.ZstdCompressor(1).compress

        def block() -> Iterator[pa.RecordBatch]:
            new = numbers.new
            for k in range(0, max(len(new), 1), CHUNK):
                opened = merger.opened([w.encode() for w in new[k : k + CHUNK]], longest, vocabulary.merge)
                words = pa.ListArray.from_arrays(pa.array([0, len(opened)], pa.int32()), opened)
                yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), words, pa.array([""])], schema=row)
            for k in range(0, len(ids), 500):
                part = ids[k : k + 500]
                yield pa.RecordBatch.from_arrays([pa.array(part, pa.int64()), pa.array(texts[k : k + 500], pa.binary()), pa.nulls(len(part), row.field(2).type), pa.nulls(len(part), pa.string())], schema=row)

        for batch in batches:
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                found = split(text.as_py())
                ids.append(doc_id)
                texts.append(pack(np.fromiter(map(numbers.__getitem__, found), "<u4", len(found))))
                total += len(found)
                if len(numbers.new) >= distinct or total >= 1_500_000:
                    yield from block()
                    numbers, ids, texts, total = Numbers(common), [], [], 0
                    give_back()
        if ids:
            yield from block()
        give_back()

    def put(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, lengths, pieces = after.value
        unpack = zstandard.ZstdDecompressor().decompress
        piece_bytes, piece_lengths = np.frombuffer(b"".join(pieces), np.uint8), np.array([len(p) for p in pieces], np.int64)
        piece_starts, parts, table = np.cumsum(piece_lengths) - piece_lengths, [(known, lengths)], None
        for batch in batches:
            opens = np.asarray(batch.column(2).is_valid())
            turns = [0, *(np.flatnonzero(opens[1:] != opens[:-1]) + 1).tolist(), len(opens)]
            for i, j in zip(turns, turns[1:], strict=False):
                if j > i and opens[i]:
                    if table is not None:
                        parts, table = [(known, lengths)], None
                    parts.append(Merger.ids(batch.column(2).slice(i, j - i).flatten()))
                    continue
                if j > i and table is None:
                    flat, each = (np.concatenate([p[k] for p in parts]) for k in (0, 1))
                    table, parts = (flat, np.cumsum(each) - each, each), []
                for k in range(i, j, 500):
                    part = batch.slice(k, min(500, j - k))
                    raw = [unpack(x.as_buffer()) for x in part.column(1)]
                    ids, ends = spread(*table, np.frombuffer(b"".join(raw), "<u4"))
                    ends = np.append(0, ends)[np.cumsum([len(x) // 4 for x in raw])]
                    columns = [part.column(0), binaries(ids.astype("<u4"), 4 * ends)]
                    if decoded:
                        texts, ends_of = spread(piece_bytes, piece_starts, piece_lengths, ids)
                        columns.append(binaries(texts, np.append(0, ends_of)[ends]))
                    yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "ids", "decoded"][: len(columns)])
            give_back()

    numbered = documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(cut, "doc_id long, numbers binary, words array<array<bigint>>, fresh string")
    folded = numbered.select("doc_id", "numbers", F.when(F.col("words").isNotNull(), merger.fold(F.col("words"), F.col("fresh"))).alias("words"))
    return folded.mapInArrow(put, "doc_id long, ids binary" + ", decoded binary" * decoded)


def decode(encoded: DataFrame, vocabulary: Vocabulary, column: str = "ids") -> DataFrame:
    """The input with `decoded` (binary) for the ids."""
    shared, at, schema = encoded.sparkSession.sparkContext.broadcast(vocabulary.pieces()), encoded.columns.index(column), T.StructType([*encoded.schema.fields, T.StructField("decoded", T.BinaryType())])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        piece = shared.value.__getitem__
        for batch in slices(batches):
            texts = [b"".join(map(piece, np.frombuffer(ids.as_buffer(), "<u4").tolist())) for ids in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.binary())], names=[*batch.schema.names, "decoded"])

    return encoded.mapInArrow(join, schema)


def round_trip(documents: DataFrame, path: str, pattern: str, **limits: int) -> DataFrame:
    """doc_id, n_tokens and the digests of ids and decoded bytes."""
    vocabulary = Vocabulary.read(path)
    return encode(documents, vocabulary, pattern, decoded=True, **limits).select("doc_id", (F.octet_length("ids") / 4).cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def digest(ids: list[int]) -> str:
    """ids_sha256 of a list."""
    return hashlib.sha256(np.asarray(ids, "<u4").tobytes()).hexdigest()
