"""All pairs of names of a district by blocks: a task takes a block of standard names against a block of candidates.

A pair of blocks is compared by one matrix product, so a text is taken apart once a block and not once a pair. What a text
measure needs of a pair is few small integers: m of the pair, a1 and a2 of the standard name, b1 and b2 of the candidate.
`rows` gives them for every pair; `counts` sums pairs of equal integers inside the task, so pairs are never shuffled.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Names of a block; a pair of blocks is a matrix of its square.
SIZE = 1000
HASHED = 256
INTS = ("m", "a1", "a2", "b1", "b2")
_INTS = ", ".join(f"{c} bigint" for c in INTS)
Measure = Callable[[list[dict], list[dict]], tuple[np.ndarray, np.ndarray, np.ndarray]]


def shared_trigrams(left: list[dict], right: list[dict]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """m: trigrams that both names hold; a and b: distinct trigrams and length of each."""
    sets = [[{x["low"][i : i + 3] for i in range(len(x["low"]) - 2)} for x in side] for side in (left, right)]
    vocabulary = {g: k for k, g in enumerate(set().union(*sets[0]) & set().union(*sets[1]))}
    held = []
    for side in sets:
        at = [(r, vocabulary[g]) for r, s in enumerate(side) for g in s if g in vocabulary]
        m = np.zeros((len(side), len(vocabulary)), np.float32)
        if at:
            m[tuple(np.array(at).T)] = 1
        held.append(m)
    attrs = [np.array([(len(s), len(x["low"]) - 3) for s, x in zip(ss, side, strict=True)], np.int64) for ss, side in zip(sets, (left, right), strict=True)]
    return (held[0] @ held[1].T).astype(np.int64), *attrs


def hashed_products(left: list[dict], right: list[dict]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """m: inner product of both names' hashed trigram counts; a and b: the product of each with itself, and 0."""
    held = []
    for side in (left, right):
        m = np.zeros((len(side), HASHED))
        for r, x in enumerate(side):
            padded = f"  {x['name'].lower()} "
            np.add.at(m[r], [zlib.crc32(padded[i : i + 3].encode()) % HASHED for i in range(len(padded) - 2)], 1)
        held.append(m)
    attrs = [np.stack([(m * m).sum(1), np.zeros(len(m))], 1).astype(np.int64) for m in held]
    return np.rint(held[0] @ held[1].T).astype(np.int64), *attrs


def _block_pairs(standard: DataFrame, candidates: DataFrame, truth: DataFrame, size: int) -> DataFrame:
    """(city, district, l, r): every pair of blocks of a district."""
    of = truth.groupBy("city", "district", F.col("std_name").alias("name")).agg(F.collect_set("cand_name").alias("alias"))
    low = F.concat(F.lit("  "), F.lower("name"), F.lit(" ")).alias("low")
    std = standard.select("city", "district", "name").join(of, ["city", "district", "name"], "left").select("city", "district", F.struct("name", low, "alias").alias("x"))
    cand = candidates.select("city", "district", F.struct("name", low, F.lit(None).cast("array<string>").alias("alias")).alias("x"))
    return paired(std, cand, size)


def paired(std: DataFrame, cand: DataFrame, size: int) -> DataFrame:
    """(city, district, l, r): every pair of blocks of a district; sides are (city, district, x) with a field `name` in x."""
    count = lambda side, n: side.groupBy("city", "district").agg(F.ceil(F.count(F.lit(1)) / size).cast("int").alias(n))
    blocks = count(std, "nl").join(count(cand, "nr"), ["city", "district"])
    total = blocks.agg(F.coalesce(F.sum(F.col("nl") * F.col("nr")), F.lit(0))).first()[0]
    parts = int(min(total // 2 + 1, 4096))

    def packed(side: DataFrame, own: str, other: str, at: str, over: str) -> DataFrame:
        dealt = side.join(F.broadcast(blocks), ["city", "district"]).withColumn(at, F.pmod(F.xxhash64("x.name"), F.col(own)).cast("int"))
        dealt = dealt.groupBy("city", "district", at, other).agg(F.collect_list("x").alias(at + "x"))
        return dealt.withColumn(over, F.explode(F.sequence(F.lit(0), F.col(other) - 1))).drop(other).repartition(parts, "city", "district", "l", "r")

    return packed(std, "nl", "nr", "l", "r").join(packed(cand, "nr", "nl", "r", "l"), ["city", "district", "l", "r"]).select("city", "district", F.col("lx").alias("l"), F.col("rx").alias("r"))


def _matrices(batches: Iterator[pa.RecordBatch], measure: Measure):
    for batch in batches:
        for k in range(batch.num_rows):
            left, right = batch.column("l")[k].as_py(), batch.column("r")[k].as_py()
            yield batch.column("city")[k].as_py(), batch.column("district")[k].as_py(), left, right, *measure(left, right)


def counts(standard: DataFrame, candidates: DataFrame, truth: DataFrame, measure: Measure, size: int = SIZE) -> DataFrame:
    """(city, district, m, a1, a2, b1, b2, k, h): pairs of a district with these integers, and how many of them are true."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for city, district, left, right, m, a, b in _matrices(batches, measure):
            place = {x["name"]: c for c, x in enumerate(right)}
            (ua, ia), (ub, ib) = (np.unique(x, axis=0, return_inverse=True) for x in (a, b))
            top = int(m.max()) + 1
            code = (ia.reshape(-1, 1) * len(ub) + ib.reshape(1, -1)) * top + m
            true = np.zeros(code.shape, bool)
            for r, x in enumerate(left):
                for name in x["alias"] or ():
                    if name in place:
                        true[r, place[name]] = True
            codes, k = np.unique(code, return_counts=True)
            h = np.bincount(np.searchsorted(codes, code[true]), minlength=len(codes))
            pair, value = codes // top, codes % top
            at, bt = ua[pair // len(ub)], ub[pair % len(ub)]
            cols = [value, at[:, 0], at[:, 1], bt[:, 0], bt[:, 1], k, h]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(k), city), pa.int32()), pa.array(np.full(len(k), district), pa.int32()), *[pa.array(x.astype(np.int64)) for x in cols]], ["city", "district", *INTS, "k", "h"])

    out = _block_pairs(standard, candidates, truth, size).mapInArrow(run, f"city int, district int, {_INTS}, k bigint, h bigint")
    return out.groupBy("city", "district", *INTS).agg(F.sum("k").alias("k"), F.sum("h").alias("h"))


def rows(standard: DataFrame, candidates: DataFrame, truth: DataFrame, measure: Measure, size: int = SIZE) -> DataFrame:
    """(city, district, std_name, cand_name, m, a1, a2, b1, b2) of every pair."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for city, district, left, right, m, a, b in _matrices(batches, measure):
            ln, rn = (pa.array([x["name"] for x in side]) for side in (left, right))
            for i in range(0, len(left), 32):
                n = min(32, len(left) - i)
                own, other = np.repeat(np.arange(i, i + n), len(right)), np.tile(np.arange(len(right)), n)
                ints = [m[i : i + n].ravel(), a[own, 0], a[own, 1], b[other, 0], b[other, 1]]
                size_ = len(own)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(size_, city), pa.int32()), pa.array(np.full(size_, district), pa.int32()), ln.take(pa.array(own)), rn.take(pa.array(other)), *map(pa.array, ints)], ["city", "district", "std_name", "cand_name", *INTS])

    return _block_pairs(standard, candidates, truth, size).mapInArrow(run, f"city int, district int, std_name string, cand_name string, {_INTS}")
