"""Near-duplicate detection with SetSketch registers.

Each document's set of word shingles gives `bands * rows` registers: register i is floor(1 - log_base(h_i)) of the smallest of
exponentially distributed hashes h_i over the set, truncated to 0..limit. Registers of a union are the larger of the two
(`merge`), and with a base near 1 two registers agree with about the probability of the Jaccard similarity.

1. Documents with equal sets become one representative (the smallest id).
2. Each band of registers is a bucket. Within a bucket every member is compared with the bucket's first member.
3. A pair's Jaccard similarity is estimated jointly from all registers, by maximum likelihood given both set sizes; pairs far
   below the threshold (4.5 standard errors) go, the rest is verified on the full sets of shingles.
4. In a few more rounds, members outside of a bucket's largest component are compared with one drawn from it; at last with
   every member of another component in the bucket, by a join that keeps a pair only if enough of a finer sketch, one bit
   of each of `bits` minima, agrees (again 4.5 standard errors). So every pair of a bucket is either compared or already connected: nothing is capped, and a bucket of many near
   copies costs a few comparisons for each.
5. Components are found by star contractions.

Defined results: a document without words has an empty set and is linked with nothing. doc_id is the key: rows that repeat one
are one document and stay or go together; a null id has a null component and is kept. The probability that a pair at
exactly the threshold shares no band is (1 - 0.75 ** rows) ** bands, 2e-6 for the defaults.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import join_hot, materialise, slices, unmaterialise
from .components import components
from .shingles import WIDTH, mix, shingle_sets

HOT = 1000  # a set that more than this part of all documents have is hot


@dataclass(frozen=True)
class Sketch:
    """Parameters of the registers and of the links."""

    bands: int = 48
    rows: int = 5
    base: float = 1.001
    rate: float = 20.0
    limit: int = 65_534
    seed: int = 11
    width: int = WIDTH
    percent: int = 75
    bits: int = 3072

    @property
    def size(self) -> int:
        return self.bands * self.rows

    @property
    def least_estimate(self) -> float:
        t = self.percent / 100
        return t - 4.5 * (t * (1 - t) / self.size) ** 0.5

    @property
    def least_agreeing(self) -> int:
        """Bits that agree for pairs at the threshold, less 4.5 standard errors; a bit agrees with probability (1 + J) / 2."""
        p = (1 + self.percent / 100) / 2
        return int(self.bits * (p - 4.5 * (p * (1 - p) / self.bits) ** 0.5))

    def fine(self, elements: np.ndarray) -> np.ndarray:
        """One bit of each minimum, packed into 64-bit integers."""
        drawn = mix(np.arange(1, 2 * self.bits + 1, dtype=np.uint64) + np.uint64(self.seed << 40)).astype(np.uint32)
        short, parity = (elements >> np.uint64(32)).astype(np.uint32), np.empty(self.bits, np.uint8)
        for k in range(0, self.bits, 64):
            factor, shift = drawn[k : k + 64] | np.uint32(1), drawn[self.bits + k : self.bits + k + 64]
            least = np.full(64, np.iinfo(np.uint32).max, np.uint32)
            for j in range(0, len(short), 4096):
                np.minimum(least, (short[j : j + 4096, None] * factor + shift).min(axis=0), out=least)
            least = (least ^ (least >> np.uint32(15))) * np.uint32(0x85EBCA6B)
            parity[k : k + 64] = (least >> np.uint32(31)).astype(np.uint8)
        return np.packbits(parity).view(np.int64)

    def hashing(self) -> tuple[np.ndarray, np.ndarray]:
        drawn = mix(np.arange(1, 2 * self.size + 1, dtype=np.uint64) + np.uint64(self.seed << 32))
        return drawn[: self.size] | np.uint64(1), drawn[self.size :]

    def registers(self, elements: np.ndarray, hashing: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
        """Registers of a set of 64-bit elements; an empty set has zeros."""
        factor, shift = hashing or self.hashing()
        least = np.full(self.size, np.iinfo(np.uint64).max, np.uint64)
        for k in range(0, len(elements), 1024):
            np.minimum(least, (elements[k : k + 1024, None] * factor + shift).min(axis=0), out=least)
        if not len(elements):
            return np.zeros(self.size, np.uint16)
        uniform = (least.astype(np.float64) + 0.5) / 2.0**64
        exponential = np.maximum(-np.log1p(-np.minimum(uniform, 1 - 2**-53)) / self.rate, 1e-300)
        return np.clip(np.floor(1 - np.log(exponential) / np.log(self.base)), 0, self.limit + 1).astype(np.uint16)

    def likeliest(self, a: np.ndarray, b: np.ndarray, n_a: np.ndarray, n_b: np.ndarray) -> np.ndarray:
        """Jaccard similarity of pairs of sketches (rows of a and b) that makes their order most likely, given the set sizes."""
        more, less = (a > b).sum(axis=1), (a < b).sum(axis=1)
        same = a.shape[1] - more - less
        u, v = n_a / (n_a + n_b), n_b / (n_a + n_b)
        chance = lambda x: np.maximum(-np.log1p(-np.clip(x, 0, 1) * (self.base - 1) / self.base) / np.log(self.base), 1e-12)

        def value(j: np.ndarray) -> np.ndarray:
            up, down = chance(u - v * j), chance(v - u * j)
            return more * np.log(up) + less * np.log(down) + same * np.log(np.maximum(1 - up - down, 1e-12))

        low, high, ratio = np.zeros(len(u)), np.minimum(u / v, v / u), (5**0.5 - 1) / 2
        for _ in range(40):
            left, right = high - ratio * (high - low), low + ratio * (high - low)
            better = value(left) > value(right)
            low, high = np.where(better, low, left), np.where(better, right, high)
        return (low + high) / 2


def merge(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Registers of the union."""
    return np.maximum(a, b)


def sketches(documents: DataFrame, sketch: Sketch = Sketch()) -> DataFrame:
    """doc_id, n (set size), f1 and f2 (a 128-bit fingerprint of the set), registers (16-bit, as bytes)."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashing = sketch.hashing()
        for batch in slices(batches):
            n, f1, f2, registers = [], [], [], []
            for s in shingle_sets(batch.column(1).to_pylist(), sketch.width):
                n.append(len(s))
                f1.append(int(s.sum(dtype=np.uint64).view(np.int64)))
                f2.append(int(mix(s + np.uint64(sketch.seed)).sum(dtype=np.uint64).view(np.int64)))
                registers.append(sketch.registers(s, hashing).astype(">u2").tobytes() if len(s) else b"")
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.array(registers, pa.binary())], names=["doc_id", "n", "f1", "f2", "registers"])

    return documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(build, "doc_id long, n long, f1 long, f2 long, registers binary")


def full_sets(documents: DataFrame, ids: DataFrame, sketch: Sketch) -> DataFrame:
    """id, elements (sorted 64-bit hashes as bytes), fine (the finer sketch) of the documents whose ids are given."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            sets = [*shingle_sets(batch.column(1).to_pylist(), sketch.width)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([sketch.fine(s) for s in sets], pa.list_(pa.int64()))], names=["id", "elements", "fine"])

    wanted = documents.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string")).join(ids, "id", "left_semi")
    return wanted.dropDuplicates(["id"]).mapInArrow(build, "id long, elements binary, fine array<bigint>")


def likely(pairs: DataFrame, table: DataFrame, sketch: Sketch) -> DataFrame:
    """Of pairs (a, b), those whose estimate does not rule out a link."""

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            if not batch.num_rows:
                continue
            for k in range(0, batch.num_rows, 2000):
                part = batch.slice(k, 2000)
                a, b = (np.frombuffer(b"".join(part.column(c).to_pylist()), ">u2").reshape(-1, sketch.size) for c in (4, 5))
                n_a, n_b = (np.asarray(part.column(c), np.float64) for c in (2, 3))
                yield part.select([0, 1]).filter(pa.array(sketch.likeliest(a, b, n_a, n_b) >= sketch.least_estimate))

    side = lambda c: table.select(F.col("rep").alias(c), F.col("n").alias(f"n_{c}"), F.col("registers").alias(f"registers_{c}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b").where(f"100 * least(n_a, n_b) >= {sketch.percent} * greatest(n_a, n_b)")
    return both.select("a", "b", "n_a", "n_b", "registers_a", "registers_b").mapInArrow(judge, "a long, b long")


def verified(pairs: DataFrame, sets: DataFrame, sketch: Sketch) -> DataFrame:
    """Of pairs (a, b), those whose full sets reach the similarity."""

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= sketch.percent * (len(x) + len(y) - both))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

    side = lambda c: sets.select(F.col("id").alias(c), F.col("elements").alias(f"elements_{c}"))
    return pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", "elements_a", "elements_b").mapInArrow(judge, "a long, b long")


def near_duplicates(documents: DataFrame, sketch: Sketch = Sketch(), rounds: int = 1) -> DataFrame:
    """doc_id, n_shingles, component_id (smallest doc_id reachable over links) and kept, for every row."""
    table = materialise(sketches(documents, sketch), "sketches")
    sizes = table.where("n > 0 AND doc_id IS NOT NULL").groupBy("f1", "f2", "n").agg(F.min("doc_id").alias("rep"), F.count("*").alias("size"))
    groups = materialise(sizes, "groups")  # as a table it brings no partitioning by the set alone, to which joins would send a hot set's rows
    hot = groups.where(F.col("size") > max(100, table.count() // HOT)).drop("size")  # fewer than HOT sets
    reps = groups.drop("size").join(table.withColumnRenamed("doc_id", "rep"), ["f1", "f2", "n", "rep"]).dropDuplicates(["rep"]).select("rep", "n", "registers")
    hashes = F.transform(F.sequence(F.lit(0), F.lit(sketch.bands - 1)), lambda i: F.xxhash64(i, F.col("registers").substr(i * (2 * sketch.rows) + 1, F.lit(2 * sketch.rows))))
    buckets = reps.select("rep", F.explode(hashes).alias("bucket"))
    first = buckets.groupBy("bucket").agg(F.min("rep").alias("lead"), F.count("*").alias("size")).where("size > 1").drop("size")
    members = materialise(buckets.join(first, "bucket").select("bucket", "lead", "rep"), "members")
    ids = members.select(F.col("rep").alias("id")).distinct()
    sets = materialise(full_sets(documents, ids, sketch), "sets")
    known = materialise(reps.join(ids.withColumnRenamed("id", "rep"), "rep", "left_semi"), "known")
    label = None

    def compare(pairs: DataFrame, estimate: bool = True) -> DataFrame:
        """Verifies pairs, and gives the component of every member after that."""
        hopeful = materialise(likely(pairs.distinct(), known, sketch) if estimate else pairs.distinct(), "likely")
        links = materialise(verified(hopeful, sets, sketch), "links")
        unmaterialise(hopeful)
        joined = links if label is None else links.unionByName(label.select(F.col("id").alias("a"), F.col("component").alias("b")))
        found = materialise(components(joined), "labels")
        unmaterialise(links)
        if label is not None:
            unmaterialise(label)
        return found

    def placed() -> DataFrame:
        return members.drop("lead").join(label.withColumnRenamed("id", "rep"), "rep", "left").select("bucket", "rep", F.coalesce("component", "rep").alias("of"))

    ordered = (F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    label = compare(members.where("rep <> lead").select(F.col("lead").alias("a"), F.col("rep").alias("b")))
    for turn in range(rounds):
        now = placed()
        sizes = now.groupBy("bucket", "of").agg(F.count("*").alias("n"), F.min_by("rep", F.xxhash64("rep", F.lit(turn))).alias("y"))
        main = sizes.groupBy("bucket").agg(F.max(F.struct("n", "of", "y")).alias("m"), F.count("*").alias("parts")).where("parts > 1").select("bucket", F.col("m.of").alias("main"), F.col("m.y").alias("y"))
        label = compare(now.join(main, "bucket").where("of <> main").select(F.col("rep").alias("x"), "y").select(*ordered))
    now = placed()
    parts = now.groupBy("bucket").agg(F.min("of").alias("low"), F.max("of").alias("high")).where("low < high").select("bucket", F.col("low").alias("part"))
    own = sets.select(F.col("id").alias("rep"), "fine").join(known.select("rep", hashes.alias("all")), "rep")
    mixed = now.join(parts, "bucket").join(own, "rep")
    side = lambda c: mixed.select("bucket", *(F.col(name).alias(f"{name}_{c}") for name in ("rep", "of", "fine", "all")))
    one, other = side("x").withColumnRenamed("rep_x", "x"), side("y").withColumnRenamed("rep_y", "y")
    agreeing = sketch.bits - F.aggregate(F.zip_with("fine_x", "fine_y", lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda total, v: total + v)
    near = one.join(other, (one["bucket"] == other["bucket"]) & (F.col("x") < F.col("y")) & (F.col("of_x") != F.col("of_y")) & (agreeing >= sketch.least_agreeing) & (F.get(F.array_intersect("all_x", "all_y"), F.lit(0)) == one["bucket"]))  # a pair comes from the first bucket it shares
    label = compare(near.select(*ordered), estimate=False)
    for done in (members, sets, known):
        unmaterialise(done)
    linked = join_hot(table.drop("registers"), groups.drop("size"), ["f1", "f2", "n"], hot, F.col("doc_id")).join(label.select(F.col("id").alias("rep"), "component"), "rep", "left")
    component = F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.coalesce("component", "rep"))
    out = linked.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), component).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def without_copies(documents: DataFrame, sketch: Sketch = Sketch()) -> DataFrame:
    """The documents, all columns, of which one of each component stays."""
    found = near_duplicates(documents, sketch)
    gone = materialise(found.where(~F.col("kept")).select(F.col("doc_id").alias("__gone")), "gone")
    unmaterialise(found)
    return documents.join(gone, documents["doc_id"] == F.col("__gone"), "left_anti")
