r"""Personal data by weak supervision, native plans only.

Base kinds come from fixed patterns with a validity test (value range, checksum, digit count). Further credential-like
spans come from one broad candidate pattern; regex, gazetteer and context labelers vote on each candidate, expectation-
maximisation over the vote patterns estimates their reliabilities without labels, and a logistic span classifier
trained on the posteriors decides. Vote and feature patterns are few (at most 3^5 * 2^6), so only their counts reach
the driver. Base spans are always kept.

Patterns are written so that each start is tried once per run of its first class: a run that fails at its start fails
at every later start too, and `\G` allows a start right after the previous match. Matches equal those of the plain forms.

Edge cases: null and empty texts give zero counts and empty digests; positions are code points; repeated rows and
equal ids each give a row; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialise

#: The patterns of the base kinds, in their order.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: A cheap test that must hold for a pattern to match at all.
NEEDS = {"email": "@", "ip": ".", "phone": "+"}
CANDIDATE = r"(?<![A-Za-z0-9_=.@-])(?=[A-Za-z_=-]*+[0-9])(?=[0-9_=-]*+[A-Za-z])[A-Za-z0-9_=-]{9,}+(?![@.][A-Za-z0-9])"
KINDS = [*PATTERNS, "secret"]
_OCTET = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
GAZETTEER = r"(?i)passw|secret|token|api[_-]?key|credential|iban|passport|licen[cs]e no"


def _digits(c: Column) -> Column:
    return F.regexp_replace(c, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    def add(total: Column, i: Column) -> Column:
        d = F.substr(digits, F.length(digits) - i + 1, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return total + F.when(i % 2 == 0, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), add) % 10 == 0


def valid(kind: str, c: Column) -> Column:
    if kind == "ip":
        return c.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$")
    if kind == "card":
        d = _digits(c)
        return F.when(F.length(d).between(14, 19), luhn(d)).otherwise(False)
    if kind == "phone":
        return F.length(_digits(c)).between(10, 15)
    return F.lit(True)


def segments(text: Column, kind: str) -> Column:
    """array<struct<gap, m>>: the text before each match and the match; the last entry has no match."""
    pattern = PATTERNS.get(kind, CANDIDATE)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    cut = F.zip_with(F.split(text, pattern, -1), found, lambda g, m: F.struct(g.alias("gap"), m.alias("m")))
    possible = F.contains(text, F.lit(NEEDS[kind])) if kind in NEEDS else text.rlike("[0-9]")
    return F.when(possible, cut).otherwise(F.array(F.struct(text.alias("gap"), F.lit(None).cast("string").alias("m"))))


def votes(span: Column, before: Column) -> list[Column]:
    """Labelers: 1 private, 0 not, -1 abstain."""
    yes, no, none = F.lit(1), F.lit(0), F.lit(-1)
    shape = F.when(span.rlike(r"^[A-Z]{4}[A-Z0-9]{16}$|^[0-9a-f]{32,64}$|^[A-Z]{2}[0-9]{2}[A-Z0-9]{10,30}$|^gh[ps]_|^sk-"), yes)
    words = F.when(F.concat(before, span).rlike(GAZETTEER), yes)
    context = F.when(before.rlike("[\"'=:]\\s?$") | span.contains("="), yes).when(before.rlike(r"[a-z]\s$"), no)
    mixed = F.regexp_count(span, F.lit("[A-Za-z][0-9]|[0-9][A-Za-z]"))
    entropy = F.when(mixed >= 4, yes).when(mixed <= 1, no)
    size = F.when(F.length(span) >= 18, yes).when(F.length(span) <= 11, no)
    return [v.otherwise(none) for v in (shape, words, context, entropy, size)]


def features(span: Column, before: Column) -> list[Column]:
    """Binary inputs of the final classifier."""
    return [
        span.rlike("^[A-Z0-9]+$"),
        span.rlike("^[0-9a-f]+$"),
        span.contains("="),
        F.length(span) >= 16,
        F.regexp_count(span, F.lit("[0-9]")) * 3 >= F.length(span),
        before.rlike("[\"'=:(]\\s?$"),
    ]


def fit_label_model(patterns: list[tuple[tuple[int, ...], int]], rounds: int = 50) -> dict[tuple[int, ...], float]:
    """Posterior of `private` for each vote pattern, by expectation-maximisation over pattern counts.

    Each labeler has its own chance of each vote in either class; the start is the majority of the votes.
    """
    if not patterns:
        return {}
    v = np.array([p for p, _ in patterns])
    n = np.array([c for _, c in patterns], float)
    q = np.clip(0.5 + 0.2 * ((v == 1).sum(1) - (v == 0).sum(1)), 0.05, 0.95)
    for _ in range(rounds):
        prior = np.clip((n * q).sum() / n.sum(), 0.01, 0.99)
        log = np.tile(np.log([1 - prior, prior]), (len(v), 1))
        for j in range(v.shape[1]):
            for y, w in ((0, n * (1 - q)), (1, n * q)):
                chance = np.array([(w * (v[:, j] == s)).sum() + 0.5 for s in (-1, 0, 1)])
                log[:, y] += np.log(chance / chance.sum())[v[:, j] + 1]
        q = 1 / (1 + np.exp(np.clip(log[:, 0] - log[:, 1], -50, 50)))
    return {tuple(int(x) for x in p): float(x) for p, x in zip(v, q)}


def fit_classifier(x: np.ndarray, y: np.ndarray, n: np.ndarray, rounds: int = 400) -> np.ndarray:
    """Weighted logistic regression on grouped rows; the last weight is the bias."""
    x = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(x.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-x @ w))
        w += 2.0 * (x.T @ (n * (y - p)) / n.sum() - 1e-4 * w)
    return w


def secret_score(cand: DataFrame) -> Callable[[list[Column]], Column]:
    """The span classifier, fitted on the votes v0.. and features f0.. of all candidates: features to score."""
    names = [c for c in cand.columns if c[0] in "vf" and c[1:].isdigit()]
    nv = sum(c[0] == "v" for c in names)
    nf = len(names) - nv
    grouped = cand.groupBy(*names).agg(F.count(F.lit(1)).alias("n")).collect()
    if not grouped:
        return lambda of: F.lit(-1.0)
    per_votes: dict[tuple[int, ...], int] = {}
    for r in grouped:
        per_votes[tuple(r[:nv])] = per_votes.get(tuple(r[:nv]), 0) + r.n
    posterior = fit_label_model(sorted(per_votes.items()))
    x = np.array([r[nv : nv + nf] for r in grouped], float)
    weights = fit_classifier(x, np.array([posterior[tuple(r[:nv])] for r in grouped]), np.array([float(r.n) for r in grouped]))
    return lambda of: reduce(lambda a, j: a + of[j] * float(weights[j]), range(nf), F.lit(float(weights[-1])))


def _near(gap: Column) -> Column:
    """The 24 characters before a span."""
    return F.substr(gap, F.greatest(F.length(gap) - 23, F.lit(1)), F.lit(24))


def spans(spark: SparkSession, docs: DataFrame, text: str = "text") -> DataFrame:
    """(row, doc_id, kind, start, end, keep): every base span and candidate; each row has one entry of null kind."""
    whole = F.coalesce(F.col(text), F.lit(""))
    base = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", whole.alias("x"))

    def part(k: int, kind: str) -> Column:
        def one(s: Column, i: Column) -> Column:
            gap, m = s["gap"], s["m"]
            near = _near(gap) if kind == "secret" else F.lit("")
            return F.struct(
                F.lit(k).alias("k"),
                i.alias("i"),
                F.length(gap).alias("g"),
                F.length(m).alias("n"),
                (F.lit(False) if kind == "secret" else valid(kind, m)).alias("ok"),
                (m if kind == "secret" else F.lit(None).cast("string")).alias("m"),
                near.alias("b"),
            )

        return F.transform(F.filter(segments(F.col("x"), kind), lambda s: s["m"].isNotNull()), one)

    parts = [part(k, kind) for k, kind in enumerate(KINDS)]
    found = base.select("row", "doc_id", F.explode(F.concat(F.array(F.lit(None)), *parts)).alias("s")).select("row", "doc_id", "s.*")
    w = W.partitionBy("row", "k").orderBy("i").rowsBetween(W.unboundedPreceding, 0)
    end = F.sum(F.col("g") + F.col("n")).over(w)
    placed = found.withColumn("end", end).withColumn("start", F.col("end") - F.col("n"))
    secret = F.col("k") == len(PATTERNS)
    vs = [F.when(secret, v).alias(f"v{j}") for j, v in enumerate(votes(F.col("m"), F.col("b")))]
    fs = [F.when(secret, f.cast("int")).alias(f"f{j}") for j, f in enumerate(features(F.col("m"), F.col("b")))]
    cand = materialise(placed.where(F.col("k").isNull() | secret | F.col("ok")).select("row", "doc_id", "k", "start", "end", *vs, *fs), spark)

    score = secret_score(cand.where(secret))([F.col(f"f{j}") for j in range(len(fs))])
    keep = F.when(F.col("k").isNull(), False).when(secret, score > 0).otherwise(True)
    return cand.select("row", "doc_id", "k", "start", "end", keep.alias("keep"))


def report(spark: SparkSession, docs: DataFrame, text: str = "text") -> DataFrame:
    """Per row: counts of the base kinds, digest of the base spans, all spans."""
    found = spans(spark, docs, text)
    base = F.col("k") < len(PATTERNS)
    name = F.get(F.array(*[F.lit(k) for k in KINDS]), F.col("k"))
    entry = F.struct("start", "k", F.concat_ws(":", name, F.col("start"), F.col("end")).alias("s"), base.alias("base"))
    per = found.groupBy("row", "doc_id").agg(
        *[F.count(F.when(F.col("k") == i, 1)).alias(f"n_{kind}") for i, kind in enumerate(PATTERNS)],
        F.array_sort(F.collect_list(F.when(F.col("keep"), entry))).alias("all"),
    )
    joined = lambda a: F.array_join(F.transform(a, lambda s: s["s"]), ",")
    return per.select("doc_id", *[f"n_{k}" for k in PATTERNS], F.sha2(joined(F.filter("all", lambda s: s["base"])), 256).alias("base_sha256"), joined(F.col("all")).alias("spans"))


def mask(spark: SparkSession, docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with every found span replaced by its kind in angle brackets; counts of characters follow where given.

    The classifier is fitted in one pass over the candidates; a second one finds the spans of each text and rebuilds it from
    code-point positions in place, so no text is shuffled or written in between. Overlapping spans are replaced as one, by
    the kind of the earliest, longest of them.
    """
    whole = F.coalesce(F.col(text), F.lit(""))
    matches = lambda kind: F.filter(segments(whole, kind), lambda s: s["m"].isNotNull())
    found = docs.select(F.explode(F.transform(matches("secret"), lambda s: F.struct(s["m"].alias("m"), _near(s["gap"]).alias("b")))).alias("s")).select("s.*")
    vs = [v.alias(f"v{j}") for j, v in enumerate(votes(F.col("m"), F.col("b")))]
    fs = [f.cast("int").alias(f"f{j}") for j, f in enumerate(features(F.col("m"), F.col("b")))]
    weighed = secret_score(found.select(*vs, *fs))

    def private(kind: str, s: Column) -> Column:
        if kind != "secret":
            return valid(kind, s["m"])
        return weighed([f.cast("int") for f in features(s["m"], _near(s["gap"]))]) > 0

    def placed(kind: str) -> Column:
        none = F.array().cast("array<struct<start:bigint,e:bigint,tag:string>>")

        def step(a: Column, s: Column) -> Column:
            start = a["at"] + F.length(s["gap"])
            end = start + F.length(s["m"])
            one = F.array(F.struct(start.alias("start"), (-end).alias("e"), F.lit(f"<{kind.upper()}>").alias("tag")))
            return F.struct(end.alias("at"), F.when(private(kind, s), F.concat(a["out"], one)).otherwise(a["out"]).alias("out"))

        return F.aggregate(matches(kind), F.struct(F.lit(0).cast("long").alias("at"), none.alias("out")), step, lambda a: a["out"])

    def step(a: Column, s: Column) -> Column:
        fresh = s["start"] >= a["at"]
        more = F.concat(a["out"], F.substr(text, (a["at"] + 1).cast("int"), (s["start"] - a["at"]).cast("int")), s["tag"])
        return F.struct(F.when(fresh, more).otherwise(a["out"]).alias("out"), F.greatest(-s["e"], a["at"]).alias("at"))

    start = F.struct(F.lit("").alias("out"), F.lit(0).cast("long").alias("at"))
    rebuilt = F.aggregate("_s", start, step, lambda a: F.concat(a["out"], F.substr(text, (a["at"] + 1).cast("int"), F.length(text))))
    some = F.size("_s") > 0
    out = docs.withColumn("_s", F.array_sort(F.concat(*[placed(kind) for kind in KINDS])))
    if "n_chars" in docs.columns:
        out = out.withColumn("_masked", F.when(some, rebuilt).otherwise(F.col(text)))
        out = out.withColumn("n_chars", F.when(some, F.length("_masked").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars"))).withColumn(text, F.col("_masked"))
    else:
        out = out.withColumn(text, F.when(some, rebuilt).otherwise(F.col(text)))
    return out.select(*docs.columns)
