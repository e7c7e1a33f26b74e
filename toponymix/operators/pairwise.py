"""Measures of all pairs of names of a district by blocks, and their scores counted in two passes.

A task compares a block of standard names with a block of candidates, so neither pairs nor shared cells are shuffled. A
footprint travels as one array of cells; sums over the cells that two names share are matrix products, or sums over the
shared cells themselves where these are few. `compared` gives a row per pair. `counted` gives what tuning and testing a cut
need: its first pass counts pairs by score range (`slab`), its second only takes apart the ranges in which a best cut can lie.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.geo import EARTH_M
from ..sources.tables import settle
from . import blocks

#: Names of a block as it is shuffled, columns of a matrix, and pairs that are scored at a time.
SIZE, STRIP, CHUNK = 2000, 1000, 1 << 17
#: Multiplications of a matrix product that cost as much as one shared cell.
EVENT = 250
#: Scores of blocks: (key, first row, first column, matrix); NaN where a pair has no score.
Scores = Iterator[tuple[tuple, int, int, np.ndarray]]


def named(standard: DataFrame, candidates: DataFrame, truth: DataFrame, attrs: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Both sides as (city, district, x): the name, its true aliases and the columns of `attrs` (city, name, maybe district, ...)."""
    of = truth.groupBy("city", "district", F.col("std_name").alias("name")).agg(F.collect_set("cand_name").alias("alias"))
    std = standard.select("city", "district", "name").join(of, ["city", "district", "name"], "left")
    cand = candidates.select("city", "district", "name", F.lit(None).cast("array<string>").alias("alias"))
    if attrs is not None:
        keys = [c for c in ("city", "district", "name") if c in attrs.columns]
        std, cand = (side.join(attrs, keys, "left") for side in (std, cand))
    pack = lambda side: settle(side.select("city", "district", F.struct(*[c for c in side.columns if c not in ("city", "district")]).alias("x")), release=True)
    return pack(std), pack(cand)


def _sides(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, int, pa.StructArray, pa.StructArray]]:
    for batch in batches:
        for k in range(batch.num_rows):
            yield batch.column("city")[k].as_py(), batch.column("district")[k].as_py(), batch.column("l")[k].values, batch.column("r")[k].values


def _strips(left: int, right: int) -> Iterator[tuple[int, int, int, int]]:
    for j in range(0, right, STRIP):
        width = min(STRIP, right - j)
        rows = max(1, CHUNK // width)
        for i in range(0, left, rows):
            yield i, min(left, i + rows), j, j + width


# ---- Cells -----------------------------------------------------------------------------------------------------------


class Side:
    """The cells of a block of names at one resolution: entries (row, cell, n) by row and cell, and sums per name."""

    def __init__(self, names: pa.StructArray, base: int, n: int, eps: float):
        cells = names.field("cells")
        lengths = pc.fill_null(pc.list_value_length(cells), 0).to_numpy(zero_copy_only=False)
        code = cells.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
        at = (code // base * n // base) * n + code % base * n // base
        key, k = np.unique(np.repeat(np.arange(len(lengths)), lengths) * (n * n) + at, return_counts=True)
        self.size, self.grid, self.eps = len(lengths), float(n) * n, eps
        self.row, self.cell, self.n = key // (n * n), key % (n * n), k.astype(np.float64)
        self.total = lengths.astype(np.float64)  # of the district; `whole` that of the city, which shares divide by
        self.whole = pc.fill_null(names.field("total"), 0).to_numpy(zero_copy_only=False).astype(np.float64)
        self.held = self.sums(np.ones(len(k)))
        self.starts = np.searchsorted(self.row, np.arange(self.size + 1))

    def sums(self, values: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, values, self.size)

    def lift(self) -> np.ndarray:
        return np.log((self.n + self.eps) / self.eps)

    @cached_property
    def plogp(self) -> np.ndarray:
        p = self.n / self.whole[self.row]
        return self.sums(p * np.log(p))

    @cached_property
    def lifted(self) -> np.ndarray:
        return self.sums((self.n + self.eps) * self.lift())

    @cached_property
    def rim(self) -> np.ndarray:
        return self.sums(self.eps * self.lift())

    def values(self, kind: str) -> np.ndarray:
        if kind == "1":
            return np.ones(len(self.n))
        return {"n": lambda: self.n, "ln": lambda: np.log(self.n), "nln": lambda: self.n * np.log(self.n), "smooth": lambda: np.log(self.n + self.eps), "lift": self.lift}[kind]()


#: Sums over shared cells: what each of both names gives.
SUMS = {"k": ("1", "1"), "sn": ("n", "1"), "cn": ("1", "n"), "lnq": ("n", "smooth"), "ss": ("nln", "1"), "sc": ("n", "ln"), "cc": ("1", "nln"), "cs": ("ln", "n"), "std_by_cand": ("n", "lift"), "cand_by_std": ("lift", "n")}
_KL = {"smooth": ("lnq",), "strict": ("ss", "sc"), "skip": ("ss", "sc"), "reverse": ("cc", "cs"), "smooth_both": ("std_by_cand",), "symmetric": ("std_by_cand", "cand_by_std")}


def shared(s: Side, c: Side, wanted: list[str]) -> Iterator[tuple[int, int, int, int, dict[str, np.ndarray]]]:
    """Sums over shared cells of every pair, by parts of the matrix of pairs."""
    used = np.intersect1d(s.cell, c.cell)
    place = np.searchsorted(used, s.cell)
    own = used[np.minimum(place, max(len(used) - 1, 0))] == s.cell if len(used) else np.zeros(len(s.cell), bool)
    place_c = np.searchsorted(used, c.cell)
    own_c = used[np.minimum(place_c, max(len(used) - 1, 0))] == c.cell if len(used) else np.zeros(len(c.cell), bool)
    events = (np.bincount(place[own], minlength=len(used)) * np.bincount(place_c[own_c], minlength=len(used))).sum()
    run = _products if events * EVENT > len(used) * s.size * c.size else _events
    for j in range(0, c.size, STRIP):
        width = min(STRIP, c.size - j)
        mine = own_c & (c.row >= j) & (c.row < j + width)
        right = (c.row[mine] - j, place_c[mine], {b: c.values(b)[mine] for b in {SUMS[w][1] for w in wanted}})
        for i, k, sums in run(s, own, place, right, width, len(used), wanted):
            yield i, k, j, j + width, sums


def _products(s: Side, own, place, right, width, n_cells, wanted):
    """By matrix products. Sums of counts are whole numbers, exact in single precision below 2^24."""
    row, cell, values = right
    small = max(s.total.max(initial=0), values["n"].sum() if "n" in values else 0) < 1 << 24
    kind = lambda w: np.float32 if small and set(SUMS[w]) <= {"1", "n"} else np.float64
    dense = {}
    for w in wanted:
        if (b := (SUMS[w][1], kind(w))) not in dense:
            dense[b] = np.zeros((n_cells, width), b[1])
            dense[b][cell, row] = values[b[0]]
    mine = {a: s.values(a) for a in {SUMS[w][0] for w in wanted}}
    rows = max(1, CHUNK // width)
    for i in range(0, s.size, rows):
        k = min(s.size, i + rows)
        part = slice(s.starts[i], s.starts[k])
        ok = own[part]
        at = (s.row[part][ok] - i, place[part][ok])
        held, sums = {}, {}
        for w in wanted:
            if (a := (SUMS[w][0], kind(w))) not in held:
                held[a] = np.zeros((k - i, n_cells), a[1])
                held[a][at] = mine[a[0]][part][ok]
            sums[w] = (held[a] @ dense[SUMS[w][1], kind(w)]).astype(np.float64)
        yield i, k, sums


def _events(s: Side, own, place, right, width, n_cells, wanted):
    """By the shared cells themselves: every entry of a standard name meets the entries of its cell."""
    row, cell, values = right
    order = np.argsort(cell, kind="stable")
    row, values = row[order], {b: v[order] for b, v in values.items()}
    starts = np.searchsorted(cell[order], np.arange(n_cells + 1))
    length = np.zeros(len(own), np.int64)
    length[own] = starts[place[own] + 1] - starts[place[own]]
    before = np.append(0, np.cumsum(length))
    mine = {a: s.values(a) for a in {SUMS[w][0] for w in wanted}}
    i = 0
    while i < s.size:
        # As many rows as a part may have, fewer where they share very many cells; one row goes even so.
        k = min(s.size, i + max(1, CHUNK // width))
        k = max(i + 1, min(k, int(np.searchsorted(before[s.starts], before[s.starts[i]] + (CHUNK << 2), side="right")) - 1))
        part = np.arange(s.starts[i], s.starts[k])
        part = part[length[part] > 0]
        n = length[part]
        left = np.repeat(part, n)
        other = np.arange(n.sum()) + np.repeat(starts[place[part]] - (np.cumsum(n) - n), n)
        target = (s.row[left] - i) * width + row[other]
        sums = {}
        for w in wanted:
            a, b = SUMS[w]
            weight = None if a == b == "1" else mine[a][left] if b == "1" else values[b][other] if a == "1" else mine[a][left] * values[b][other]
            sums[w] = np.bincount(target, weight, (k - i) * width).astype(np.float64).reshape(k - i, width)
        yield i, k, sums
        i = k


def divergence(s: Side, c: Side, i: int, k: int, j: int, m: int, x: dict[str, np.ndarray], policy: str) -> np.ndarray:
    """KL of a part of the pairs under a policy of `divergence.compare`; anything where a footprint is empty."""
    col = lambda v: v[i:k, None]
    row = lambda v: v[None, j:m]
    ts, tc, ws, wc = col(s.total), row(c.total), col(s.whole), row(c.whole)
    with np.errstate(all="ignore"):
        if policy == "smooth":
            mass = x["sn"] / ws
            q = x["lnq"] / ws - mass * np.log(wc + s.eps * s.grid)
            missing = np.where(x["sn"] == ts, 0.0, 1 - mass)
            return col(s.plogp) - q - missing * np.log(s.eps / (tc + s.eps * s.grid))
        if policy in ("strict", "skip"):
            skip = (x["ss"] - x["sc"] + x["sn"] * (np.log(wc) - np.log(ws))) / ws
            return np.where(x["sn"] < ts, np.inf, skip) if policy == "strict" else np.where(x["k"] == 0, 0.0, skip)
        if policy == "reverse":
            return np.where(x["k"] == 0, 0.0, (x["cc"] - x["cs"] + x["cn"] * (np.log(ws) - np.log(wc))) / wc)
        a, b = ts + s.eps * s.grid, tc + s.eps * s.grid
        there = np.log(b / a) + (col(s.lifted) - row(c.rim) - x["std_by_cand"]) / a
        if policy == "smooth_both":
            return there
        return (there + np.log(a / b) + (row(c.lifted) - col(s.rim) - x["cand_by_std"]) / b) / 2


#: Columns of a compared pair and their types.
COLUMNS = {"n_shared_cells": "bigint", "shared_std_n": "bigint", "shared_cand_n": "bigint", "total_std": "bigint", "total_cand": "bigint", "cells_std": "bigint", "cells_cand": "bigint", "overlap": "double", "kl": "double", "inverse": "double", "jaccard": "double", "is_inf": "boolean"}


def _wanted(columns: list[str], policy: str) -> list[str]:
    kl = ("sn", "cn", "k", *_KL[policy]) if policy not in ("smooth", "smooth_both", "symmetric") else ("sn", *_KL[policy])
    need = {"n_shared_cells": ("k",), "shared_std_n": ("sn",), "shared_cand_n": ("cn",), "overlap": ("sn", "cn"), "is_inf": ("sn",), "kl": kl, "inverse": kl, "jaccard": ("k",)}
    out = [w for c in columns for w in need.get(c, ())]
    return [w for w in SUMS if w in out]


def _overlap(s: Side, c: Side, i: int, k: int, j: int, m: int, x: dict[str, np.ndarray]) -> np.ndarray:
    with np.errstate(all="ignore"):
        return (x["sn"] / s.total[i:k, None] + x["cn"] / c.total[None, j:m]) / 2


def _inverse(x: np.ndarray) -> np.ndarray:
    with np.errstate(all="ignore"):
        return np.where(x <= 0, np.inf, 1 / x)


def compared(std: DataFrame, cand: DataFrame, columns: list[str], base: int, n: int, eps: float, policy: str = "smooth", size: int = SIZE, places: dict[str, int] | None = None) -> DataFrame:
    """One row per pair with some of COLUMNS, as `divergence.compare` has them; sides come from `named` with total and cells.

    inverse is 1 / kl, infinite at or below zero; jaccard the likeness of both sets of cells. `places` rounds doubles here, by
    whole arrays: a decimal for each of many rows costs more than their comparison.
    """
    wanted = _wanted(columns, policy)
    kinds = {"bigint": pa.int64(), "double": pa.float64(), "boolean": pa.bool_()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for city, district, left, right in _sides(batches):
            s, c = Side(left, base, n, eps), Side(right, base, n, eps)
            for i, k, j, m, x in shared(s, c, wanted):
                shape = (k - i, m - j)
                ts, tc = np.broadcast_to(s.total[i:k, None], shape), np.broadcast_to(c.total[None, j:m], shape)
                none = (ts == 0) | (tc == 0)
                if "kl" in columns or "inverse" in columns:
                    kl = divergence(s, c, i, k, j, m, x, policy)
                make = {
                    "n_shared_cells": lambda: (x["k"], None), "shared_std_n": lambda: (x["sn"], None), "shared_cand_n": lambda: (x["cn"], None),
                    "total_std": lambda: (ts, ts == 0), "total_cand": lambda: (tc, tc == 0),
                    "cells_std": lambda: (np.broadcast_to(s.held[i:k, None], shape), ts == 0), "cells_cand": lambda: (np.broadcast_to(c.held[None, j:m], shape), tc == 0),
                    "overlap": lambda: (_overlap(s, c, i, k, j, m, x), none), "kl": lambda: (kl, none), "inverse": lambda: (_inverse(kl), none),
                    "jaccard": lambda: (x["k"] / np.maximum(s.held[i:k, None] + c.held[None, j:m] - x["k"], 1), none), "is_inf": lambda: (x["sn"] < ts, none),
                }
                out = []
                for name in columns:
                    v, mask = make[name]()
                    v = v.astype(np.int64) if COLUMNS[name] == "bigint" else rounded(v, places[name]) if name in (places or {}) else v
                    out.append(pa.array(v.ravel(), kinds[COLUMNS[name]], mask=None if mask is None else mask.ravel()))
                own, other = np.repeat(np.arange(i, k), m - j), np.tile(np.arange(j, m), k - i)
                yield from _cut(city, district, left.field("name").take(pa.array(own)), right.field("name").take(pa.array(other)), out, columns)

    types = ", ".join(f"{c} {COLUMNS[c]}" for c in columns)
    return blocks.paired(std, cand, size).mapInArrow(run, f"city int, district int, std_name string, cand_name string, {types}")


def _cut(city: int, district: int, l: pa.Array, r: pa.Array, out: list[pa.Array], columns: list[str], rows: int = 1 << 15) -> Iterator[pa.RecordBatch]:  # noqa: E741
    for at in range(0, len(l), rows):
        n = min(rows, len(l) - at)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(n, city), pa.int32()), pa.array(np.full(n, district), pa.int32()), *[x.slice(at, n) for x in (l, r, *out)]], ["city", "district", "std_name", "cand_name", *columns])


def missing(std: DataFrame, cand: DataFrame, base: int, sizes: list[int], eps: float, size: int = SIZE) -> DataFrame:
    """(n_grid, pairs, missing): pairs of two footprints, and those whose standard name has mass where the candidate has none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, left, right in _sides(batches):
            got = []
            for n in sizes:
                s, c = Side(left, base, n, eps), Side(right, base, n, eps)
                inf = sum(int(((x["sn"] < s.total[i:k, None]) & (s.total[i:k, None] > 0) & (c.total[None, j:m] > 0)).sum()) for i, k, j, m, x in shared(s, c, ["sn"]))
                got.append((n, int((s.total > 0).sum()) * int((c.total > 0).sum()), inf))
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*got, strict=True), (pa.int32(), pa.int64(), pa.int64()), strict=True)], ["n_grid", "pairs", "missing"])

    out = blocks.paired(std, cand, size).mapInArrow(run, "n_grid int, pairs bigint, missing bigint")
    return out.groupBy("n_grid").agg(F.sum("pairs").alias("pairs"), F.sum("missing").alias("missing"))


# ---- Scores ----------------------------------------------------------------------------------------------------------


def rounded(x: np.ndarray, places: int) -> np.ndarray:
    """Half away from zero; never minus zero."""
    with np.errstate(invalid="ignore"):
        p = 10.0**places
        a = np.abs(x) * p
        whole = np.trunc(a)
        return np.copysign((whole + (a - whole >= 0.5)) / p, x) + 0.0


def raster_scores(base: int, sizes: list[int], methods: list[str], eps: float) -> Callable[[pa.StructArray, pa.StructArray], Scores]:
    """Scores of M3 and M4 at several resolutions; the key is (method, n)."""
    wanted = _wanted([c for m, c in (("M3", "kl"), ("M4", "overlap")) if m in methods], "smooth")

    def run(left: pa.StructArray, right: pa.StructArray) -> Scores:
        for n in sizes:
            s, c = Side(left, base, n, eps), Side(right, base, n, eps)
            for i, k, j, m, x in shared(s, c, wanted):
                none = (s.total[i:k, None] == 0) | (c.total[None, j:m] == 0)
                for method in methods:
                    v = -rounded(divergence(s, c, i, k, j, m, x, "smooth"), 6) if method == "M3" else _overlap(s, c, i, k, j, m, x)
                    yield (method, n), i, j, np.where(none, np.nan, v)

    return run


def distance_scores(method: str) -> Callable[[pa.StructArray, pa.StructArray], Scores]:
    """Negated metres between anchors (lat, lon in degrees), in millimetres."""

    def run(left: pa.StructArray, right: pa.StructArray) -> Scores:
        at = lambda side, c: np.radians(side.field(c).to_numpy(zero_copy_only=False).astype(np.float64))
        a, o, b, p = at(left, "lat"), at(left, "lon"), at(right, "lat"), at(right, "lon")
        for i, k, j, m in _strips(len(left), len(right)):
            dy, dx = np.sin((b[None, j:m] - a[i:k, None]) / 2), np.sin((p[None, j:m] - o[i:k, None]) / 2)
            h = np.sqrt(dy * dy + np.cos(a[i:k, None]) * np.cos(b[None, j:m]) * dx * dx)
            yield (method, 0), i, j, -rounded(2 * EARTH_M * np.arcsin(np.minimum(h, 1.0)), 3)

    return run


def _codes(names: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of names, filled up with -1, and their lengths."""
    n = np.array([len(x) for x in names])
    out = np.full((len(names), int(n.max(initial=0))), -1, np.int64)
    out[np.arange(out.shape[1])[None, :] < n[:, None]] = np.frombuffer("".join(names).encode("utf-32-le", "surrogatepass"), np.uint32)
    return out, n


def edits(left: list[str], right: list[str]) -> np.ndarray:
    """Levenshtein distances of all pairs. Names of at most 32 or 64 characters keep a column of the table in the bits of a word."""
    (lc, ln), (rc, rn) = _codes(left), _codes(right)
    out = np.empty((len(left), len(right)), np.int64)
    out[ln == 0] = rn
    alphabet, inverse = np.unique(np.append(-1, rc.ravel()), return_inverse=True)
    text = inverse[1:].reshape(rc.shape)
    by = np.argsort(-rn, kind="stable")
    text, active = text[by], (rn[None, :] > np.arange(rc.shape[1])[:, None]).sum(1)
    for word, floor in ((np.uint32, 0), (np.uint64, 32)):
        bits = np.iinfo(word).bits
        short = np.flatnonzero((ln > floor) & (ln <= bits))
        step = max(1, (1 << 17) // (bits // 8) // max(1, len(right)))
        for at in range(0, len(short), step):
            rows = short[at : at + step]
            peq = np.zeros((len(rows), len(alphabet)), word)
            for c in range(int(ln[rows].max())):
                has = np.flatnonzero(ln[rows] > c)
                code = np.minimum(np.searchsorted(alphabet, lc[rows[has], c]), len(alphabet) - 1)
                same = alphabet[code] == lc[rows[has], c]
                peq[has[same], code[same]] |= word(1 << c)
            shape, one = (len(rows), len(right)), word(1)
            pv, mv = np.full(shape, ~word(0)), np.zeros(shape, word)
            for c, n in enumerate(active):
                eq, p, q = np.take(peq, text[:n, c], axis=1), pv[:, :n], mv[:, :n]
                xv = eq | q
                xh = eq & p
                xh += p
                xh ^= p
                xh |= eq
                ph = ~(xh | p)
                ph |= q
                xh &= p  # the negative steps between columns from here on
                ph <<= one
                ph |= one
                xh <<= one
                q[:] = ph & xv
                xv |= ph
                np.invert(xv, out=p)
                p |= xh
            # The last column's steps add up to the distance: no cell of the table is followed on the way.
            own = (~word(0) >> (bits - ln[rows]).astype(word))[:, None]
            out[rows[:, None], by[None, :]] = np.bitwise_count(pv & own).astype(np.int64) - np.bitwise_count(mv & own) + rn[by]
    for i in np.flatnonzero(ln > 64):  # the table row by row, all candidates at once
        prev = np.repeat(np.arange(ln[i] + 1)[:, None], len(right), 1)
        final = np.full(len(right), ln[i])
        for c in range(rc.shape[1]):
            cur = np.empty_like(prev)
            cur[0] = c + 1
            for r in range(1, ln[i] + 1):
                cur[r] = np.minimum(np.minimum(prev[r], cur[r - 1]) + 1, prev[r - 1] + (rc[:, c] != lc[i, r - 1]))
            prev = cur
            final = np.where(rn == c + 1, prev[-1], final)
        out[i] = final
    return out


def edit_scores(left: pa.StructArray, right: pa.StructArray) -> Scores:
    """Negated edits between both names."""
    l, r = left.field("name").to_pylist(), right.field("name").to_pylist()  # noqa: E741
    for i, k, j, m in _strips(len(l), len(r)):
        yield ("T1", 0), i, j, -edits(l[i:k], r[j:m]).astype(np.float64) + 0.0


# ---- Counting --------------------------------------------------------------------------------------------------------


def slab(score: np.ndarray) -> np.ndarray:
    """The range of a score: its sign, exponent and first eight binary digits. Never falls as the score grows."""
    return np.sign(score).astype(np.int64) * (np.abs(score).view(np.int64) >> 44)


def _hits(left: pa.StructArray, right: pa.StructArray) -> tuple[np.ndarray, np.ndarray]:
    """Rows and columns of true pairs."""
    place = {x: c for c, x in enumerate(right.field("name").to_pylist())}
    at = [(r, place[x]) for r, names in enumerate(left.field("alias").to_pylist()) for x in names or () if x in place]
    return tuple(np.array(at, np.int64).reshape(-1, 2).T)


def _parts(batches: Iterator[pa.RecordBatch], scores: Callable, labelled: bool):
    """(city, district, key -> parts of (sorted scores, sorted scores of true pairs)) of each pair of blocks, one key at a time."""
    for city, district, left, right in _sides(batches):
        rows, cols = _hits(left, right)
        keep = np.array([bool(x) for x in left.field("alias").to_pylist()])
        for key, i, j, v in scores(left, right):
            if labelled:
                v = np.where(keep[i : i + len(v), None], v, np.nan)
            mine = (rows >= i) & (rows < i + v.shape[0]) & (cols >= j) & (cols < j + v.shape[1])
            true = v[rows[mine] - i, cols[mine] - j]
            yield city, district, key, v.ravel()[~np.isnan(v.ravel())], true[~np.isnan(true)]
        yield city, district, None, None, None


def _summed(key: np.ndarray, k: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    order = np.argsort(key, kind="stable")
    first = np.flatnonzero(np.append(True, np.diff(key[order]) != 0)) if len(key) else np.zeros(0, np.int64)
    add = lambda x: np.add.reduceat(x[order], first) if len(first) else x
    return order, first, key[order][first], add(k), add(h)


def _histogram(std: DataFrame, cand: DataFrame, scores: Callable, labelled: bool, size: int) -> DataFrame:
    """(method, n_grid, city, district, slab, k, h, top, low)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}
        for city, district, key, v, true in _parts(batches, scores, labelled):
            if key is not None:
                v = np.sort(v)
                at = slab(v)
                first = np.flatnonzero(np.append(True, np.diff(at) != 0)) if len(at) else np.zeros(0, np.int64)
                last = np.append(first[1:], len(at))[: len(first)]
                h = np.bincount(np.searchsorted(at[first], slab(true)), minlength=len(first))
                held.setdefault(key, []).append((at[first], last - first, h, v[last - 1] if len(first) else v, v[first]))
                continue
            for (method, n), parts in held.items():
                s, k, h, top, low = (np.concatenate(x) for x in zip(*parts, strict=True))
                if len(s):
                    order, first, s, k, h = _summed(s, k, h)
                    top, low = np.maximum.reduceat(top[order], first), np.minimum.reduceat(low[order], first)
                    fixed = [pa.array([method] * len(s)), *[pa.array(np.full(len(s), x), pa.int32()) for x in (n, city, district)]]
                    yield pa.RecordBatch.from_arrays([*fixed, *map(pa.array, (s, k, h, top, low))], ["method", "n_grid", "city", "district", "slab", "k", "h", "top", "low"])
            held = {}

    out = blocks.paired(std, cand, size).mapInArrow(run, "method string, n_grid int, city int, district int, slab bigint, k bigint, h bigint, top double, low double")
    keys = ["method", "n_grid", "city", "district", "slab"]
    return out.groupBy(*keys).agg(F.sum("k").alias("k"), F.sum("h").alias("h"), F.max("top").alias("top"), F.min("low").alias("low"))


def _details(std: DataFrame, cand: DataFrame, scores: Callable, labelled: bool, size: int, open_slabs: dict[tuple, np.ndarray]) -> DataFrame:
    """(method, n_grid, city, district, score, k, h) of the scores in open ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, list] = {}
        for city, district, key, v, true in _parts(batches, scores, labelled):
            if key is not None:
                if key in open_slabs:
                    inside = lambda x: x[np.isin(slab(x), open_slabs[key])]  # noqa: B023, E731
                    s, k = np.unique(inside(v), return_counts=True)
                    held.setdefault(key, []).append((s, k, np.bincount(np.searchsorted(s, inside(true)), minlength=len(s))))
                continue
            for (method, n), parts in held.items():
                _, _, s, k, h = _summed(*(np.concatenate(x) for x in zip(*parts, strict=True)))
                for at in range(0, len(s), 1 << 15):
                    x = slice(at, at + (1 << 15))
                    fixed = [pa.array([method] * len(s[x])), *[pa.array(np.full(len(s[x]), y), pa.int32()) for y in (n, city, district)]]
                    yield pa.RecordBatch.from_arrays([*fixed, pa.array(s[x]), pa.array(k[x]), pa.array(h[x].astype(np.int64))], ["method", "n_grid", "city", "district", "score", "k", "h"])
            held = {}

    out = blocks.paired(std, cand, size).mapInArrow(run, "method string, n_grid int, city int, district int, score double, k bigint, h bigint")
    return out.groupBy("method", "n_grid", "city", "district", "score").agg(F.sum("k").alias("k"), F.sum("h").alias("h"))


def opened(hist: pd.DataFrame, true: dict[int, int], runs: list[list[int]]) -> np.ndarray:
    """The ranges of one key that can hold the best cut of a run (a list of source districts), or the next score below one.

    Taking a whole range is a cut, so the best of these bounds F1 from below. Inside a range no cut has more hits than all of
    its true pairs and nothing else would give: where even that stays below the bound, the range can stay closed. A range of
    one score needs no second look.
    """
    out: set[int] = set()
    for districts in runs:
        mine = hist[(hist.city == 0) & hist.district.isin(districts)].groupby("slab")[["k", "h"]].sum().sort_index(ascending=False)
        k, h, s = mine.k.to_numpy(), mine.h.to_numpy(), mine.index.to_numpy()
        t = sum(true.get(d, 0) for d in districts)
        a, c = np.cumsum(k), np.cumsum(h)
        with np.errstate(all="ignore"):
            least = np.nan_to_num(2.0 * c / (a + t)).max(initial=0.0)
            most = np.nan_to_num(2.0 * c / (a - k + h + t))
        can = np.flatnonzero(most >= least * (1 - 1e-9))
        out.update(s[can].tolist(), s[np.minimum(can + 1, len(s) - 1)].tolist())
    several = hist.groupby("slab").agg(top=("top", "max"), low=("low", "min"))
    several = set(several.index[several.top > several.low].tolist())
    return np.array(sorted(out & several), np.int64)


def counted(std: DataFrame, cand: DataFrame, truth: DataFrame, scores: Callable, folds: list[list[int]], labelled: bool = False, size: int = SIZE) -> DataFrame:
    """(method, n_grid, city, district, score, k, h): whole where a cut of `folds` or of the source city is decided.

    A closed range of scores is one row of each district, at its highest score there: no best cut and no next lower
    score lies in it, so on either side of any cut its pairs stay together.
    """
    hist = settle(_histogram(std, cand, scores, labelled, size))
    true = {r.district: r.n for r in truth.where("city = 0").groupBy("district").agg(F.count(F.lit(1)).alias("n")).collect()}
    table = hist.toArrow().to_pandas()
    every = sorted({*true, *table[table.city == 0].district.tolist()})
    open_slabs = {key: opened(g, true, [every, *folds]) for key, g in table.groupby(["method", "n_grid"])}
    open_slabs = {k: v for k, v in open_slabs.items() if len(v)}
    closed = hist.select("method", "n_grid", "city", "district", F.col("top").alias("score"), "k", "h", "slab")
    if not open_slabs:
        return closed.drop("slab")
    rows = [(m, int(n), int(s)) for (m, n), ss in open_slabs.items() for s in ss]
    gone = F.broadcast(std.sparkSession.createDataFrame(rows, "method string, n_grid int, slab bigint"))
    closed = closed.join(gone, ["method", "n_grid", "slab"], "left_anti").drop("slab")
    return settle(closed.unionByName(_details(std, cand, scores, labelled, size, open_slabs)))
