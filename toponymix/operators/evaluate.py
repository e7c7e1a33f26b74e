"""Precision, recall, F1; cuts; cross-validation by district; transfer to another city.

All functions take `scored` (..., district, std_name, cand_name, score) and `truth` (city, district, std_name,
cand_name); tuning, cross-validation and transfer also take scores `counted` by district. Folds are rows, not loops. `by` lists columns that separate evaluations run in one plan.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.tables import settle

#: A cut below every score: everything that has a score is accepted.
ALL = -1.7976931348623157e308


def f1(correct: Column, accepted: Column, true: Column) -> Column:
    return F.when(accepted + true > 0, 2.0 * correct / (accepted + true)).otherwise(0.0)


def measures(correct: Column, accepted: Column, true: Column) -> list[Column]:
    ratio = lambda a, b: F.coalesce(F.try_divide(a.cast("double"), b), F.lit(0.0))
    return [ratio(correct, accepted).alias("precision"), ratio(correct, true).alias("recall"), f1(correct, accepted, true).alias("f1")]


def label(scored: DataFrame, truth: DataFrame, universe: str = "all_pairs") -> DataFrame:
    """Adds hit (0/1). `labelled_standard` keeps pairs whose standard name has a label."""
    keys = ["city", "district", "std_name", "cand_name"]
    if universe == "labelled_standard":
        scored = scored.join(truth.select(*keys[:3]).distinct(), keys[:3], "left_semi")
    return scored.join(truth.select(*keys, F.lit(1).alias("hit")), keys, "left").withColumn("hit", F.coalesce("hit", F.lit(0)))


def counted(scored: DataFrame, truth: DataFrame, by: list[str], universe: str = "all_pairs") -> DataFrame:
    """(by, city, district, score, k, h): pairs of a district with one score, and how many of them are true.

    Folds, cuts and tests need no more of a pair, so each pair is labelled and shuffled once, whatever the number of rounds.
    Scores that come counted already stay as they are.
    """
    if "k" in scored.columns:
        return scored
    keys = [*by, *(["fold"] if "fold" in scored.columns else []), "city", "district", "score"]
    return label(scored, truth, universe).groupBy(*keys).agg(F.count(F.lit(1)).alias("k"), F.sum("hit").alias("h"))


def gathered(counts: DataFrame) -> DataFrame:
    """Counted rows with one row per score."""
    return counts.groupBy(*[c for c in counts.columns if c not in ("k", "h")]).agg(F.sum("k").alias("k"), F.sum("h").alias("h"))


def confusion(decided: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """n_accepted, n_correct, n_true and the measures, in all or per `by` (for instance district)."""
    by = by or []
    d = label(decided, truth).groupBy(*by).agg(F.sum(F.col("is_alias").cast("int")).alias("n_accepted"), F.sum((F.col("is_alias") & (F.col("hit") == 1)).cast("int")).alias("n_correct"))
    t = truth.groupBy(*by).agg(F.count(F.lit(1)).alias("n_true"))
    both = (d.join(t, by, "full") if by else d.crossJoin(t)).fillna(0, ["n_accepted", "n_correct", "n_true"])
    return both.select(*by, "n_accepted", "n_correct", "n_true", *measures(F.col("n_correct"), F.col("n_accepted"), F.col("n_true")))


def slab(score: Column) -> Column:
    """The range of a score: a step function of it that never falls, about 256 steps a factor of e beyond 1e-6."""
    return F.floor(F.signum(score) * F.log1p(F.abs(score) * 1e6) * 256)


def pr_curve(labelled: DataFrame, n_true: DataFrame, by: list[str]) -> DataFrame:
    """One row per distinct score: what accepting that score and all above gives. Ties enter together.

    Running counts come in two levels, inside score ranges (`slab`) and over range totals, so no task sorts all scores of
    a run. The slab never falls as the score grows, through zero and over both signs, so ranges don't interleave.
    """
    k, h = (F.sum("k"), F.sum("h")) if "k" in labelled.columns else (F.count(F.lit(1)), F.sum("hit"))
    ties = labelled.where(F.col("score").isNotNull() & ~F.isnan("score")).groupBy(*by, "score").agg(k.alias("k"), h.alias("h"))
    ties = settle(ties.withColumn("slab", slab(F.col("score"))))
    inner = W.partitionBy(*by, "slab").orderBy(F.desc("score")).rowsBetween(W.unboundedPreceding, 0)
    outer = W.partitionBy(*by).orderBy(F.desc("top")).rowsBetween(W.unboundedPreceding, -1)
    slabs = ties.groupBy(*by, "slab").agg(F.max("score").alias("top"), F.sum("k").alias("k"), F.sum("h").alias("h"))
    zero = F.lit(0).cast("bigint")
    base = slabs.select(*by, "slab", F.coalesce(F.sum("k").over(outer), zero).alias("bk"), F.coalesce(F.sum("h").over(outer), zero).alias("bh"))
    run = ties.select(*by, "slab", "score", F.sum("k").over(inner).alias("k"), F.sum("h").over(inner).alias("h")).join(base, [*by, "slab"])
    run = run.select(*by, "score", (F.col("k") + F.col("bk")).alias("n_accepted"), (F.col("h") + F.col("bh")).alias("n_correct"))
    run = run.join(n_true, by) if by else run.crossJoin(n_true)
    return run.select(*by, "score", "n_accepted", "n_correct", "n_true", *measures(F.col("n_correct"), F.col("n_accepted"), F.col("n_true")))


def tune(curve: DataFrame, by: list[str]) -> DataFrame:
    """The cut of best F1 per run (ties: fewer accepted): the next lower score, so that `score > cut` keeps the group."""
    best = curve.groupBy(*by).agg(F.max(F.struct("f1", (-F.col("n_accepted")).alias("few"), "score")).alias("b")).select(*by, F.col("b.f1").alias("train_f1"), F.col("b.score").alias("at_least"))
    joined = curve.select(*by, "score").join(best, by) if by else curve.select("score").crossJoin(best)
    low = joined.groupBy(*by, "train_f1", "at_least").agg(F.max(F.when(F.col("score") < F.col("at_least"), F.col("score"))).alias("lower"))
    return low.select(*by, "train_f1", "at_least", F.coalesce("lower", F.lit(ALL)).alias("cut"))


def folds(truth_districts: int = 10, scheme: str = "disjoint"):
    """Rows (fold, district, role) of eight training and two test districts: five disjoint rounds or all 45 pairs."""
    pairs = [(2 * k, 2 * k + 1) for k in range(truth_districts // 2)]
    if scheme == "all_pairs":
        pairs = [(a, b) for a in range(truth_districts) for b in range(a + 1, truth_districts)]
    return [(f, d, "test" if d in p else "train") for f, p in enumerate(pairs) for d in range(truth_districts)]


def fold_table(scored: DataFrame, scheme: str = "disjoint") -> DataFrame:
    rows = folds(scheme=scheme)
    return scored.sparkSession.createDataFrame(rows, "fold int, district int, role string")


def cross_validate(scored: DataFrame, truth: DataFrame, by: list[str] | None = None, scheme: str = "disjoint", universe: str = "all_pairs") -> DataFrame:
    """Source city: per fold, and micro (-1, pooled counts) and macro (-2, mean of rounds) rows.

    Where `scored` has a column `fold`, its scores come from models trained in that fold and are used in it alone.
    """
    by = by or []
    table = F.broadcast(fold_table(scored, scheme))
    lab = settle(counted(scored.where("city = 0"), truth, by, universe)).join(table, ["district", "fold"] if "fold" in scored.columns else ["district"])
    t = truth.where("city = 0").join(table, "district")
    runs = [*by, "fold"]
    seen = lab.select(*by).distinct() if by else None
    n_true = t.where("role = 'train'").groupBy("fold").agg(F.count(F.lit(1)).alias("n_true"))
    n_true = n_true.crossJoin(seen) if by else n_true
    cuts = settle(tune(settle(pr_curve(lab.where("role = 'train'"), n_true, runs)), runs))
    test = accept_rows(lab.where("role = 'test'").join(cuts.select(*runs, "cut"), runs))
    got = test.groupBy(*runs).agg(F.sum("acc").alias("n_accepted"), F.sum("ok").alias("n_correct"))
    want = t.where("role = 'test'").groupBy("fold").agg(F.count(F.lit(1)).alias("n_true"))
    per = settle(got.join(want, "fold", "left").fillna(0, ["n_true"]))
    per = per.select(*runs, "n_accepted", "n_correct", "n_true", *measures(F.col("n_correct"), F.col("n_accepted"), F.col("n_true")))
    sums = per.groupBy(*by).agg(*[F.sum(c).alias(c) for c in ("n_accepted", "n_correct", "n_true")], *[F.avg(c).alias("m_" + c) for c in ("precision", "recall", "f1")])
    micro = sums.select(*by, F.lit(-1).alias("fold"), "n_accepted", "n_correct", "n_true", *measures(F.col("n_correct"), F.col("n_accepted"), F.col("n_true")))
    macro = sums.select(*by, F.lit(-2).alias("fold"), "n_accepted", "n_correct", "n_true", *[F.col("m_" + c).alias(c) for c in ("precision", "recall", "f1")])
    return per.unionByName(micro).unionByName(macro)


def accept_rows(rows: DataFrame) -> DataFrame:
    """Counted rows with the pairs above the cut and the true ones of these."""
    yes = F.coalesce((F.col("score") > F.col("cut")).cast("int"), F.lit(0))
    return rows.withColumns({"acc": yes * F.col("k"), "ok": yes * F.col("h")})


def best_cut(scored: DataFrame, truth: DataFrame, by: list[str] | None = None, city: int = 0) -> DataFrame:
    """The cut tuned on one whole city."""
    by = by or []
    lab = settle(counted(scored.where(F.col("city") == city), truth, by))
    n_true = truth.where(F.col("city") == city).agg(F.count(F.lit(1)).alias("n_true"))
    n_true = n_true.crossJoin(lab.select(*by).distinct()) if by else n_true
    return settle(tune(settle(pr_curve(lab, n_true, by)), by))


def transfer(scored: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The source city's cut applied unchanged to the target city."""
    by = by or []
    cuts = best_cut(scored, truth, by)
    lab = counted(scored.where("city = 1"), truth, by)
    test = accept_rows(lab.join(F.broadcast(cuts), by) if by else lab.crossJoin(F.broadcast(cuts)))
    got = test.groupBy(*by, "cut").agg(F.sum("acc").alias("n_accepted"), F.sum("ok").alias("n_correct"))
    n_true = truth.where("city = 1").agg(F.count(F.lit(1)).alias("n_true"))
    return got.crossJoin(n_true).select(*by, "cut", "n_accepted", "n_correct", "n_true", *measures(F.col("n_correct"), F.col("n_accepted"), F.col("n_true")))


def drop(cv: DataFrame, moved: DataFrame, by: list[str]) -> DataFrame:
    """Relative loss of F1 from cross-validation (micro) to transfer."""
    a = cv.where("fold = -1").select(*by, F.col("f1").alias("cv_f1"))
    b = moved.select(*by, F.col("f1").alias("tr_f1"))
    return a.join(b, by).withColumn("f1_drop", F.try_divide(F.col("cv_f1") - F.col("tr_f1"), F.col("cv_f1")))
