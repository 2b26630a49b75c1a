"""Shared helpers of the text operators: column picking, joins that spread hot keys, hashing of words and bounded Bloom filters."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..scratch import cut as cut  # tables in the folder that driver and executors share
from ..scratch import scratch_path as scratch_path

DOC_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def pick(df: DataFrame, *names: str) -> DataFrame:
    """Selects columns by exact name, whatever other columns (also ones that differ in case only) stand beside them.

    If no column has the exact name, a single column equal up to case is taken; of several with the same name the first."""
    plain = df.toDF(*[f"__c{i}" for i in range(len(df.columns))])
    chosen = []
    for name in names:
        at = [i for i, c in enumerate(df.columns) if c == name] or [i for i, c in enumerate(df.columns) if c.lower() == name.lower()]
        if not at:
            raise ValueError(f"no column {name!r} among {df.columns}")
        chosen.append(F.col(f"__c{at[0]}").alias(name))
    return plain.select(*chosen)


#: A key with more than 1 / SHARES of all rows is hot; there are fewer than SHARES of them.
SHARES = 1000


def spread_join(rows: DataFrame, groups: DataFrame, key: str, spread: str, how: str = "inner", count: str = "n") -> DataFrame:
    """rows joined to groups by key, where groups has one row a key and says how many rows have it (count, which goes).

    Hot keys are split: their rows go by a hash of column spread to as many parts as they hold thousandths of all rows, and their group to each of these. Only
    the hot keys, fewer than SHARES, are broadcast. how: inner or left."""
    total = groups.agg(F.coalesce(F.sum(count), F.lit(0)).alias("t")).first().t
    hot = groups.where(F.col(count) * SHARES > int(total)).select(F.col(key).alias("__key"), F.ceil(F.col(count) * SHARES / max(1, int(total))).cast("int").alias("__parts"))
    parts = F.coalesce(F.col("__parts"), F.lit(1))

    def dealt(df: DataFrame) -> DataFrame:
        return df.join(F.broadcast(hot), F.col(key) == F.col("__key"), "left")

    left = dealt(rows).withColumn("__part", F.pmod(F.xxhash64(spread), parts).cast("int")).drop("__key", "__parts")
    right = dealt(groups).withColumn("__part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("__key", "__parts", count)
    return left.join(right, [key, "__part"], how).drop("__part")


def release() -> None:
    """Gives freed memory back to the system, so that a Python worker that waits for its next task holds little."""
    pa.default_memory_pool().release_unused()
    libc = ctypes.CDLL(None)
    if hasattr(libc, "malloc_trim"):
        libc.malloc_trim(0)


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """run over the batches of a task, then release()."""

    def whole(batches: Iterator) -> Iterator:
        yield from run(batches)
        release()

    return whole


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective finaliser over uint64."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


_BYTE = mix64(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))
_BYTE[65:91] = _BYTE[97:123]  # A-Z count as a-z
_SEPARATOR = np.zeros(256, dtype=bool)
_SEPARATOR[[9, 10, 11, 12, 13, 32]] = True
_STEP = 0xD6E8FEB86659FD93
_powers = np.ones(1, dtype=np.uint64)


def _power_table(n: int) -> np.ndarray:
    global _powers
    if len(_powers) < n:
        size = max(64, 2 * n)
        steps = np.full(size, _STEP, dtype=np.uint64)
        steps[0] = 1
        _powers = np.multiply.accumulate(steps)
    return _powers


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the words of some texts that lie one after another in data (UTF-8), and per text the number of words.

    A word is a run of bytes other than space and 0x09-0x0D; ASCII capitals count as small letters."""
    n = len(data)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(len(starts), np.int64)
    inside = ~_SEPARATOR[data]
    first = inside.copy()
    first[1:] &= ~inside[:-1]
    bounds = starts[starts < n]
    first[bounds] = inside[bounds]
    at = np.flatnonzero(first)
    if len(at) == 0:
        return np.zeros(0, np.uint64), np.zeros(len(starts), np.int64)
    within = np.arange(n, dtype=np.int64)
    within[at[0]:] -= np.repeat(at, np.diff(np.append(at, n)))
    within[~inside] = 0
    within[: at[0]] = 0
    value = _BYTE[data] * _power_table(int(within.max()) + 1)[within]
    value[~inside] = 0
    return mix64(np.add.reduceat(value, at)), np.searchsorted(at, ends) - np.searchsorted(at, starts)


_SPREAD = mix64(np.arange(11, 11 + 64, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95)) | np.uint64(1)


def shingle_sets(column: pa.Array, width: int = 5, chunk: int = 1 << 20) -> Iterator[np.ndarray]:
    """Per text the sorted distinct hashes of its shingles of `width` words.

    With fewer words the whole sequence is the only shingle; null and wordless texts give the empty set."""
    column = column.cast(pa.large_binary()) if not pa.types.is_large_binary(column.type) else column
    column = column.fill_null(b"")
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(column.buffers()[2], dtype=np.uint8) if column.buffers()[2] is not None and column.buffers()[2].size else np.zeros(0, np.uint8)
    i = 0
    while i < len(column):
        j = int(np.searchsorted(offsets, offsets[i] + chunk, side="left"))
        j = min(max(j, i + 1), len(column))
        data = raw[offsets[i] : offsets[j]]
        words, counts = word_hashes(data, offsets[i:j] - offsets[i], offsets[i + 1 : j + 1] - offsets[i])
        full = np.zeros(0, np.uint64)
        if len(words) >= width:
            full = words[: len(words) - width + 1] * _SPREAD[0]
            for k in range(1, width):
                full = full + words[k : len(words) - width + 1 + k] * _SPREAD[k]
            full = mix64(full)
        at = 0
        for c in counts.tolist():
            if c >= width:
                yield np.unique(full[at : at + c - width + 1])
            elif c:
                yield mix64((words[at : at + c] * _SPREAD[:c]).sum(dtype=np.uint64, keepdims=True) + _SPREAD[40 + c % 20])
            else:
                yield np.zeros(0, np.uint64)
            at += c
        i = j


BLOOM_BITS = 1 << 26


def _bloom_positions(values: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    h = mix64(values.astype(np.int64).view(np.uint64) + np.uint64(0x1234567))
    mask = np.uint64(BLOOM_BITS - 1)
    return h & mask, (h >> np.uint64(20)) & mask, (h >> np.uint64(38)) & mask


class Bloom:
    """Membership of long keys with false positives only; never over BLOOM_BITS bits, whatever it was made of. Null is a member."""

    def __init__(self, words: dict[int, int]):
        self.words = words

    @classmethod
    def of(cls, keys: DataFrame) -> Bloom:
        """keys: one long column. Executors set bits; at most BLOOM_BITS / 64 words come to the driver."""

        def bits(batches):
            for b in batches:
                values = b.column(0).drop_null().to_numpy(zero_copy_only=False)
                if len(values):
                    all_bits = np.unique(np.concatenate(_bloom_positions(values)).astype(np.int64))
                    words, at = np.unique(all_bits >> 6, return_index=True)
                    held = np.bitwise_or.reduceat(np.left_shift(np.uint64(1), (all_bits & 63).astype(np.uint64)), at)
                    yield pa.record_batch([pa.array(words), pa.array(held.view(np.int64))], names=["word", "held"])

        rows = keys.mapInArrow(bits, "word long, held long").groupBy("word").agg(F.expr("bit_or(held)").alias("held")).toArrow()
        return cls((rows.column("word").to_numpy(), rows.column("held").to_numpy()))

    def test(self) -> Bloom:
        """Unpacks itself; call once in each task."""
        self.bits = np.zeros(BLOOM_BITS // 64, dtype=np.int64)
        self.bits[self.words[0]] = self.words[1]
        return self

    def may_hold(self, column: pa.Array) -> np.ndarray:
        values = column.cast(pa.int64()).fill_null(0).to_numpy(zero_copy_only=False)
        found = np.ones(len(values), dtype=bool)
        bits = self.bits.view(np.uint64)
        for p in _bloom_positions(values):
            found &= ((bits[(p >> np.uint64(6)).astype(np.int64)] >> (p & np.uint64(63))) & np.uint64(1)).astype(bool)
        return found | column.is_null().to_numpy(zero_copy_only=False)


def components(edges: DataFrame) -> DataFrame:
    """Connected components of an undirected graph. edges: a long, b long. Returns node, label (the least node reachable) for every node with an edge.

    Alternates linking each node's larger neighbours to its least one with linking its smaller ones (two-phase star contraction),
    so each round is two aggregations; a node of any degree is pre-aggregated before the shuffle and never gathered in one task."""
    spark = edges.sparkSession
    now = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    before = None
    while True:
        both = now.select("u", "v").union(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        joined = large.join(low, "u")
        small = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v"))).distinct()
        now = cut(small)
        state = now.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if before == (state.n, state.h):
            break
        before = (state.n, state.h)
    roots = now.select(F.col("v").alias("node")).distinct().join(now.select(F.col("u").alias("node")), "node", "left_anti")
    return now.select(F.col("u").alias("node"), F.col("v").alias("label")).union(roots.select("node", F.col("node").alias("label")))
