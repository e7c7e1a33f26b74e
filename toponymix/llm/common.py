"""Shared helpers of the corpus operators: table access, shared scratch tables, byte-level text kernels."""

from __future__ import annotations

import atexit
import itertools
import re
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that the numpy kernels take at once; bounds a Python worker's memory.
CHUNK_BYTES = 1 << 20

WHITESPACE = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. Where the session names none, only a single-machine session gets one."""
    sc = spark.sparkContext
    named = sc.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not re.match(r"local(\[[^\]]*\])?$", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = f"/tmp/checkpoints/{sc.applicationId}"
        sc.setCheckpointDir(named)
    return named


def _remove(spark: SparkSession, path: str) -> None:
    """Deletes a scratch folder while the session lives; at exit after its end the folder stays."""
    if spark.sparkContext._jsc is None or spark.sparkContext._jsc.sc().isStopped():
        return
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def _written(df: DataFrame, spark: SparkSession, path: str) -> DataFrame:
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Tables made inside the open blocks of `passing`.
_PASSING: list[list[str]] = []


def materialise(df: DataFrame, spark: SparkSession) -> DataFrame:
    """Write df once as a table in the shared folder and read it back: cuts lineage, survives lost executors."""
    path = f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"
    if _PASSING:
        _PASSING[-1].append(path)
    else:
        atexit.register(_remove, spark, path)
    out = _written(df, spark, path)
    if _PASSING:
        release_shuffles(spark)
    return out


def release_shuffles(spark: SparkSession) -> None:
    """Spark deletes the shuffle files of a finished query when the driver's collector finds its plan; on a quiet driver that may take long."""
    spark.sparkContext._jvm.System.gc()


@contextmanager
def passing(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Tables of `materialise` made in the block go when it ends; one written by the yielded function stays until exit."""
    mine: list[str] = []
    _PASSING.append(mine)

    def stays(df: DataFrame) -> DataFrame:
        path = f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}"
        atexit.register(_remove, spark, path)
        return _written(df, spark, path)

    try:
        yield stays
    finally:
        _PASSING.remove(mine)
        for path in mine:
            _remove(spark, path)
        release_shuffles(spark)


def without_rows(docs: DataFrame, gone: DataFrame) -> DataFrame:
    """docs without the rows whose places (`monotonically_increasing_id`) the column `_row` of `gone` lists.

    Places are dense inside a partition, so a bitmap of one bit a row is broadcast and no text is shuffled, however many rows go.
    """
    slab = lambda c: F.floor(F.col(c) / F.lit(32768)).cast("long")
    bits = gone.select("_row", slab("_row").alias("_slab")).groupBy("_slab").agg(F.expr("bitmap_construct_agg(_row % 32768)").alias("_bits"))
    at = docs.withColumn("_row", F.monotonically_increasing_id()).withColumn("_slab", slab("_row"))
    byte = F.conv(F.hex(F.expr("substring(_bits, cast((_row % 32768) div 8 as int) + 1, 1)")), 16, 10).cast("int")
    hit = byte.bitwiseAND(F.expr("shiftleft(1, cast(_row % 8 as int))")) != 0
    return at.join(F.broadcast(bits), "_slab", "left").where(F.col("_bits").isNull() | ~hit).select(*docs.columns)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Tables like those of `materialise` that go when the block ends; what leaves the block must not read them."""
    folder, n = f"{shared_dir(spark)}/scratch-{uuid.uuid4().hex}", itertools.count()
    try:
        yield lambda df: _written(df, spark, f"{folder}/{next(n)}")
    finally:
        _remove(spark, folder)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def crc_bucket(n: int):
    """crc32 of the decimal doc_id, modulo n: the held-out rule of the contracts."""
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % n


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if pa.types.is_string(column.type):
        column = column.cast(pa.large_string())
    if column.null_count:
        column = column.fill_null("")
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[off[0] : off[-1]] if len(off) else raw[:0], off - off[0]


def row_slices(offsets: np.ndarray, most: int = CHUNK_BYTES) -> Iterator[tuple[int, int]]:
    """Runs of rows of at most `most` bytes; a longer row is a run of its own."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1)
        yield i, j
        i = j


_rng = np.random.default_rng(20240531)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_PLACE = _rng.integers(1, 2**63, 4096, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_WORD = _rng.integers(1, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_VALUE = np.where(_SPACE, np.uint64(0), _BYTE[_LOWER])


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def _word_hashes(data: np.ndarray, row_starts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(hash, first byte) of each word of data; a row start always begins a new word."""
    if not len(data):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    inside = ~_SPACE[data]
    begins = inside.copy()
    begins[1:] &= ~inside[:-1]
    at = row_starts[row_starts < len(data)]
    begins[at] = inside[at]
    starts = np.flatnonzero(begins)
    if not len(starts):
        return np.zeros(0, np.uint64), starts
    place = np.arange(len(data), dtype=np.int64)
    place[starts[0] :] -= np.repeat(starts, np.diff(np.append(starts, len(data))))
    value = _VALUE[data]
    value *= _PLACE[place & 4095]
    value[: starts[0]] = 0
    return mix(np.add.reduceat(value, starts)), starts


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of the lower-cased words of all rows, in order, and the words of each row.

    Words are runs of bytes other than ASCII white space, A-Z lower-cased. Long inputs go through in pieces cut at
    white space, so memory stays near CHUNK_BYTES times a small factor besides eight bytes a word.
    """
    hashes, firsts, pos, n = [], [], 0, len(data)
    while pos < n:
        end = min(n, pos + CHUNK_BYTES)
        if end < n:
            back = np.flatnonzero(_SPACE[data[pos:end]])
            row = offsets[np.searchsorted(offsets, end, side="right") - 1]
            cut = max(pos + int(back[-1]) + 1 if len(back) else pos, int(row))
            while cut <= pos:  # one word longer than a piece
                step = np.flatnonzero(_SPACE[data[end : end + CHUNK_BYTES]])
                after = offsets[np.searchsorted(offsets, end, side="left")]
                stop = end + int(step[0]) + 1 if len(step) else min(n, end + CHUNK_BYTES)
                cut, end = (min(stop, int(after)), stop) if len(step) or after <= stop or stop == n else (pos, stop)
            end = cut
        inner = offsets[(offsets >= pos) & (offsets < end)] - pos
        h, s = _word_hashes(data[pos:end], inner)
        hashes.append(h)
        firsts.append(s + pos)
        pos = end
    h = np.concatenate(hashes) if hashes else np.zeros(0, np.uint64)
    f = np.concatenate(firsts) if firsts else np.zeros(0, np.int64)
    return h, np.diff(np.searchsorted(f, offsets))


def shingle_sets(words: np.ndarray, counts: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingle hashes, ordered by row and hash, and the row of each.

    A row with fewer words than `width` gives its whole sequence as one shingle; a row without words gives none.
    """
    rows = np.repeat(np.arange(len(counts)), counts)
    first = np.cumsum(counts) - counts
    total = len(words)
    s = np.zeros(max(total - width + 1, 0), np.uint64)
    for j in range(width):
        s += words[j : j + len(s)] * _WORD[j]
    whole = np.arange(len(s))
    keep = whole + width <= (first + counts)[rows[: len(s)]] if len(s) else np.zeros(0, bool)
    hashes, owners = [s[keep]], [rows[: len(s)][keep]]
    for r in np.flatnonzero((counts > 0) & (counts < width)):
        w = words[first[r] : first[r] + counts[r]]
        with np.errstate(over="ignore"):
            hashes.append(np.array([(w * _WORD[: len(w)]).sum(dtype=np.uint64) + _WORD[32 + len(w)]], np.uint64))
        owners.append(np.array([r]))
    h, o = mix(np.concatenate(hashes)), np.concatenate(owners)
    order = np.lexsort((h, o))
    h, o = h[order], o[order]
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (o[1:] != o[:-1])
    return h[fresh], o[fresh]


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def dense_slots(df: DataFrame, group: str, order: str, tie: list[str], block: int = 2048) -> DataFrame:
    """Adds `slot`: the 0-based rank of each row inside its `group`, by `order` (a long) and then `tie`.

    Ranks come from counts of (group, block of the order column) and of blocks of blocks, so no task holds a group.
    """
    key = F.coalesce(F.col(order), F.lit(-1).cast("long"))
    keyed = df.withColumn("_blk", F.floor(key / F.lit(block)).cast("long")).withColumn("_g", F.coalesce(F.col(group).cast("long"), F.lit(-1)))
    counts = keyed.groupBy("_g", "_blk").agg(F.count(F.lit(1)).alias("_n")).withColumn("_sup", F.floor(F.col("_blk") / F.lit(block)).cast("long"))
    sup = counts.groupBy("_g", "_sup").agg(F.sum("_n").alias("_sn"))
    from pyspark.sql import Window as W

    w_sup = W.partitionBy("_g").orderBy("_sup").rowsBetween(W.unboundedPreceding, -1)
    w_in = W.partitionBy("_g", "_sup").orderBy("_blk").rowsBetween(W.unboundedPreceding, -1)
    zero = F.lit(0).cast("long")
    sup = sup.select("_g", "_sup", F.coalesce(F.sum("_sn").over(w_sup), zero).alias("_so"))
    offsets = counts.withColumn("_io", F.coalesce(F.sum("_n").over(w_in), zero)).join(sup, ["_g", "_sup"]).select("_g", "_blk", (F.col("_so") + F.col("_io")).alias("_off"))
    rank = F.row_number().over(W.partitionBy("_g", "_blk").orderBy(order, *tie)) - 1
    return keyed.withColumn("_r", rank).join(offsets, ["_g", "_blk"]).withColumn("slot", (F.col("_off") + F.col("_r")).cast("long")).drop("_g", "_blk", "_r", "_off")
