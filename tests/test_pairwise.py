"""All pairs by blocks: the same values as the plain forms, no pair shuffled, and counts that decide cuts as single pairs do."""

from __future__ import annotations

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from toponymix.operators import divergence, evaluate, pairwise, raster, score, textbase
from toponymix.plans import discover as D
from toponymix.plans import workloads
from toponymix.sources.fixtures import Tables

AT = "city int, district int, name string"
PAIR = ["city", "district", "std_name", "cand_name"]


def toy(spark, n, seed=3, per=6):
    """Names of three districts, one standard name and one candidate of them without pings; authors, pings on an n x n grid, true pairs."""
    rng = random.Random(seed)
    std = [(0 if d < 2 else 1, d, f"s{d}-{k}") for d in (0, 1, 10) for k in range(per)]
    cand = [(0 if d < 2 else 1, d, f"c{d}-{k}") for d in (0, 1, 10) for k in range(per + 1)]
    auth = [(*x, u) for k, x in enumerate(std + cand) if k not in (0, len(std)) for u in rng.sample(range(30), 3)]
    pings = [(u, rng.randrange(n), rng.randrange(n)) for u in range(30) for _ in range(rng.randint(1, 9))]
    true = [(*s, c[2]) for s in std for c in cand if s[:2] == c[:2] and rng.random() < 0.2]
    make = spark.createDataFrame
    return make(std, AT), make(cand, AT), make(auth, "city int, district int, place_name string, user_id bigint"), make(pings, "user_id bigint, r int, c int"), make(true, "city int, district int, std_name string, cand_name string")


@pytest.mark.parametrize("event", (0, 10**9))
@pytest.mark.parametrize("policy", ("smooth", "strict", "skip", "reverse", "smooth_both", "symmetric"))
def test_block_comparison_equals_the_join_of_cells(spark, monkeypatch, event, policy):
    """Every column of every policy, by matrix products and by shared cells, in blocks of a few names."""
    monkeypatch.setattr(pairwise, "EVENT", event)
    monkeypatch.setattr(pairwise, "STRIP", 2)
    std, cand, auth, pings, truth = toy(spark, 4)
    columns = list(D.COMPARED)
    sides = pairwise.named(std, cand, truth, raster.packed(auth, pings, 4))
    got = {tuple(r[:4]): tuple(r[4:]) for r in pairwise.compared(*sides, columns, 4, 4, 1e-3, policy, size=4).collect()}
    shares = raster.share(raster.density(auth, pings))
    plain = divergence.compare(shares, score.within_district(std, cand), std, cand, 1e-3, 4, zero_policy=policy)
    want = {tuple(r[:4]): tuple(r[4:]) for r in plain.select(*PAIR, *columns).collect()}
    assert got.keys() == want.keys() and any(v[5] is None for v in want.values())
    for key, row in want.items():
        assert got[key] == pytest.approx(row, abs=1e-9)


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["f_map_overlap", "sql_m4", "m3_kl_smooth", "m3_kl_symmetric", "m3_score", "x_cell_jaccard"])
def test_pairs_are_never_shuffled(spark, sf_dir, name):
    """Rows of pairs come out of the blocks' task: above it the plan has neither join nor exchange."""
    above, found, _ = plan_of(workloads.queries()[name](spark, sf_dir)).partition("MapInArrow")
    assert found and "Exchange" not in above.replace("AdaptiveSparkPlan", "") and "Join" not in above


def test_edits_equal_the_plain_distance(spark):
    """Names up to and beyond 64 characters, empty ones and such outside ASCII."""
    rng = random.Random(4)
    word = lambda n: "".join(rng.choice("abÜ 𝒳") for _ in range(n))
    left, right = ([word(n) for n in (0, 1, 5, 30, 63, 64, 65, 80)] + [word(rng.randint(2, 40)) for _ in range(6)] for _ in range(2))
    pairs = spark.createDataFrame([(a, b) for a in left for b in right], "std_name string, cand_name string")
    want = {(r.std_name, r.cand_name): r.edits for r in textbase.edit(pairs).collect()}
    got = pairwise.edits(left, right)
    assert {(a, b): got[i, j] for i, a in enumerate(left) for j, b in enumerate(right)} == want


@pytest.mark.parametrize("scheme", ("disjoint", "all_pairs"))
def test_counts_of_two_passes_decide_as_single_pairs_do(spark, monkeypatch, scheme):
    """Folds, cuts and transfer from counted scores equal those from one row per pair, though closed ranges come as one row."""
    monkeypatch.setattr(pairwise, "slab", lambda s: np.floor(s * 4).astype(np.int64))  # wide ranges of many scores
    std, cand, auth, pings, truth = toy(spark, 5, per=16)
    sides = pairwise.named(std, cand, truth, raster.packed(auth, pings, 5))
    rows = pairwise.compared(*sides, ["overlap"], 5, 5, 1e-3, size=5).select(F.lit("M4").alias("method"), *PAIR, F.col("overlap").alias("score")).cache()
    training: dict[int, list[int]] = {}
    for f, d, role in evaluate.folds(scheme=scheme):
        if role == "train":
            training.setdefault(f, []).append(d)
    counts = pairwise.counted(*sides, truth, pairwise.raster_scores(5, [5], ["M4"], 1e-3), list(training.values()), size=5).drop("n_grid")
    assert counts.agg(F.sum("k")).first()[0] == rows.where("score IS NOT NULL").count() and counts.count() < rows.select("city", "district", "score").distinct().count()
    plain = lambda df: sorted(tuple(round(x, 9) if isinstance(x, float) else x for x in r) for r in df.collect())
    assert plain(evaluate.cross_validate(counts, truth, ["method"], scheme)) == plain(evaluate.cross_validate(rows, truth, ["method"], scheme))
    assert plain(evaluate.transfer(counts, truth, ["method"])) == plain(evaluate.transfer(rows, truth, ["method"]))
    assert plain(evaluate.best_cut(counts, truth, ["method"])) == plain(evaluate.best_cut(rows, truth, ["method"]))


def test_evaluations_read_counted_scores(spark, sf_dir, monkeypatch):
    """No evaluation in the findings forms a row per pair."""
    monkeypatch.setattr(D, "scored", lambda *a, **k: pytest.fail("a row per pair"))
    monkeypatch.setattr(evaluate, "label", lambda *a, **k: pytest.fail("pairs are labelled by a join"))
    t = Tables(spark, sf_dir)
    for m in ("M2", "M3"):
        assert workloads._tr(t, [m]).count() == 1
    assert D.missing_mass(t, [20, 50]).count() == 2


@pytest.mark.parametrize("name", ["m3_kl_smooth", "m3_kl_symmetric", "m3_score", "x_cell_jaccard"])
def test_pairs_are_rounded_in_their_block(spark, sf_dir, name):
    """No decimal is made for each of many rows above the blocks' task."""
    above, found, _ = plan_of(workloads.queries()[name](spark, sf_dir)).partition("MapInArrow")
    assert found and "round(" not in above


def test_rounding_goes_half_away_from_zero():
    """As SQL rounds: ties, the double just below one half, infinities; never minus zero."""
    x = np.array([0.5, -0.5, 0.49999999999999994, -0.49999999999999994, 2.5, np.inf, -np.inf])
    assert pairwise.rounded(x, 0).tolist() == [1, -1, 0, 0, 3, np.inf, -np.inf]
    assert not np.signbit(pairwise.rounded(np.array([-0.0, -1e-9]), 6)).any()


def test_inverse_and_jaccard_equal_their_plain_forms(spark):
    """M3's score and the likeness of cell sets, of every pair, rounded and not; empty footprints stay null."""
    std, cand, auth, pings, truth = toy(spark, 4)
    sides = pairwise.named(std, cand, truth, raster.packed(auth, pings, 4))
    columns = ["kl", "inverse", "jaccard", "n_shared_cells", "cells_std", "cells_cand"]
    rows = pairwise.compared(*sides, columns, 4, 4, 1e-3, size=4).collect()
    want = {tuple(r[:4]): r.score for r in score.distribution(pairwise.compared(*sides, ["kl"], 4, 4, 1e-3, size=4), "M3").collect()}
    near = {tuple(r[:4]): (r.inverse, r.jaccard) for r in pairwise.compared(*sides, columns[1:3], 4, 4, 1e-3, size=4, places={"inverse": 4, "jaccard": 6}).collect()}
    assert len(rows) == len(want) == len(near) and any(r.inverse is None for r in rows)
    for r in rows:
        inverse, jaccard = near[tuple(r[:4])]
        assert r.inverse == want[tuple(r[:4])] and (r.jaccard is None) == (r.kl is None) == (jaccard is None)
        if r.jaccard is not None:
            assert r.jaccard == r.n_shared_cells / (r.cells_std + r.cells_cand - r.n_shared_cells)
            assert jaccard == pytest.approx(r.jaccard, abs=5.1e-7) and (inverse == r.inverse or inverse == pytest.approx(r.inverse, abs=5.1e-5))


def test_edits_follow_no_cell_of_the_table(spark, monkeypatch):
    """Distances come from the last column's steps; names around 32 and 64 characters, where the words change."""
    counted = []
    monkeypatch.setattr(np, "bitwise_count", lambda x, f=np.bitwise_count: counted.append(x.dtype) or f(x))
    rng = random.Random(8)
    left, right = (["".join(rng.choice("abc é") for _ in range(n)) for n in (1, 31, 32, 33, 63, 64, 65, 0)] for _ in range(2))
    pairs = spark.createDataFrame([(a, b) for a in left for b in right], "std_name string, cand_name string")
    want = {(r.std_name, r.cand_name): r.edits for r in textbase.edit(pairs).collect()}
    got = pairwise.edits(left, right)
    assert {(a, b): got[i, j] for i, a in enumerate(left) for j, b in enumerate(right)} == want
    assert {np.dtype(np.uint32), np.dtype(np.uint64)} == set(counted)
