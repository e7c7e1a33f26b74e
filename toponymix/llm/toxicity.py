r"""Toxicity by weak supervision: voters, a generative label model with correlations, a linear classifier.

1. A bounded sample of labelled training rows (`most_labelled`, by hash order) gives lexicon entries: words and word
   stems (prefixes of 4 to 7 letters, by times of occurrence) far more frequent in toxic texts. Counts are summed on the cluster.
2. Entries that share a stem form a lexicon voter; pattern voters look at shouting, masked words and repeated marks, and one
   voter speaks for clean texts. No text's own label enters its posterior.
3. A generative model of the votes, fitted by expectation-maximisation, holds the accuracy of each voter in either class and the
   strongest correlations between voters as a tree learned from class-conditional mutual information. One figure comes from the
   labelled sample: the share of all lexicon votes that clean texts cast, which bounds what the model may blame on them.
4. A logistic classifier on entry and pattern features is trained on the model's posterior labels and scores every text.

The model is bounded: `most_entries` entries, the strongest by evidence over all units counted, and one voter for each of the
`most_voters` commonest stems of entries with four for the rest. The driver holds the entries and the sampled rows' entry ids.

Edge cases: null and empty texts score as texts without any feature; long texts are read whole, in pieces; repeated
rows score alike; without labels or toxic examples every score is the (low) prior; an empty table gives an empty
result; extra columns are ignored by the query and kept by the filter.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, materialise

STEMS = (4, 5, 6, 7)
#: A stem is an entry of its own for each of these numbers of occurrences: 'lowe*', 'lowe**', and so on.
TIMES = (1, 2, 3, 5)
#: Strength of the pull of the classifier's weights to zero, in rows.
RIDGE = 0.02
#: Words whose entries a scorer remembers.
MEMO = 400_000
PATTERNS = (re.compile(r"[A-Z]{5,}\s+[A-Z]{5,}"), re.compile(r"\b\w+[*@#$]{2,}\w+\b"), re.compile(r"!{3,}|\?!"))
_WORD = re.compile(r"[^\W\d_]+")
PIECE = 1 << 20


def pieces(text: str) -> Iterator[str]:
    """The text in pieces cut at white space."""
    at = 0
    while len(text) - at > PIECE:
        cut = max(text.rfind(" ", at, at + PIECE), text.rfind("\n", at, at + PIECE))
        cut = at + PIECE if cut <= at else cut
        yield text[at:cut]
        at = cut
    yield text[at:]


def word_counts(text: str) -> Counter:
    out: Counter = Counter()
    for p in pieces(text):
        out.update(_WORD.findall(p.lower()))
    return out


def units(text: str) -> set[str]:
    """Distinct words and stems of a text, a stem with as many stars as it is met at least."""
    words = word_counts(text)
    stems: Counter = Counter()
    for w, c in words.items():
        for k in STEMS:
            if len(w) >= k:
                stems[w[:k]] += c
    return {*words, *(s + "*" * t for s, c in stems.items() for t in TIMES if t <= c)}


@dataclass
class Model:
    entries: dict[str, int]
    weights: np.ndarray  # entries, then patterns, then bias
    accuracies: np.ndarray = field(default_factory=lambda: np.zeros((0, 2)))
    correlations: list[tuple[int, int, float]] = field(default_factory=list)

    def feature_ids(self, text: str) -> tuple[list[int], int]:
        """Ids of the entries and patterns in a text, and its number of words."""
        hits: set[int] = set()
        stems: Counter = Counter()
        total = 0
        memo = self.memo
        for p in pieces(text):
            found = _WORD.findall(p.lower())
            total += len(found)
            for w in set(found):
                got = memo.get(w)
                if got is None:
                    if len(memo) > MEMO:
                        memo.clear()
                    own = self.entries.get(w)
                    memo[w] = got = (own, tuple(w[:k] for k in STEMS if len(w) >= k and w[:k] in self.tracked)) if own is not None or w[: STEMS[0]] in self.heads else ()
                if got:
                    if got[0] is not None:
                        hits.add(got[0])
                    if got[1]:
                        c = found.count(w)
                        for s in got[1]:
                            stems[s] += c
        for s, c in stems.items():
            for t in TIMES:
                if t <= c and s + "*" * t in self.entries:
                    hits.add(self.entries[s + "*" * t])
        hits.update(len(self.entries) + k for k, r in enumerate(PATTERNS) if r.search(text))
        return sorted(hits), total

    @cached_property
    def memo(self) -> dict[str, tuple]:
        return {}

    @cached_property
    def heads(self) -> set[str]:
        return {s[: STEMS[0]] for s in self.tracked}

    @cached_property
    def tracked(self) -> set[str]:
        return {e.rstrip("*") for e in self.entries if e.endswith("*")}

    def scores(self, texts) -> np.ndarray:
        ids = [self.feature_ids(t)[0] for t in texts]
        of = np.repeat(np.arange(len(ids)), [len(x) for x in ids])
        z = self.weights[-1] + np.bincount(of, self.weights[np.concatenate([np.array(x, np.int64) for x in ids] or [np.zeros(0, np.int64)])], len(ids))
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def evidence(pos: int, neg: int) -> tuple:
    """(share, evidence) columns: the toxic share of a unit, and the log likelihood ratio of it against the overall one."""
    base = (pos + 1) / (pos + neg + 2)
    share = (F.col("p") + 0.25) / (F.col("p") + F.col("neg") + 0.5)
    return share, F.col("p") * F.log(share / base) + F.col("neg") * F.log((1 - share) / (1 - base))


def families(entries: list[str], most: int) -> np.ndarray:
    """Voter of each entry: entries that share their first four letters vote together; rare families share voters."""
    stems = [e.rstrip("*")[:4] for e in entries]
    big = [s for s, _ in Counter(stems).most_common(most)]
    first = {s: i for i, s in enumerate(big)}
    return np.array([first.get(s, most + sum(map(ord, s)) % 4) for s in stems], np.int64)


@dataclass
class LabelModel:
    """P(y) and P(vote_j | y, vote_parent(j)) over binary votes, fitted without labels."""

    prior: float
    parent: np.ndarray
    chance: np.ndarray  # [voter, y, parent vote] -> P(vote = 1)

    def log_joint(self, v: np.ndarray) -> np.ndarray:
        above = np.where(self.parent >= 0, v[:, np.maximum(self.parent, 0)], 0)
        j = np.arange(v.shape[1])
        out = np.empty((len(v), 2))
        for y in (0, 1):
            c = self.chance[j, y, above]
            out[:, y] = np.log(np.where(v == 1, c, 1 - c)).sum(1) + np.log((1 - self.prior, self.prior)[y])
        return out

    def posterior(self, v: np.ndarray) -> np.ndarray:
        s = self.log_joint(v)
        return 1 / (1 + np.exp(np.clip(s[:, 0] - s[:, 1], -50, 50)))


def correlation_tree(v: np.ndarray, n: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(parent of each voter, class-conditional mutual information): the maximum spanning tree from voter 0."""
    m = v.shape[1]
    info = np.zeros((m, m))
    for w in (n * (1 - q), n * q):
        total = w.sum() + 1
        one = (w @ v + 0.5) / total
        both = (v.T * w) @ v / total
        for a in (0, 1):
            for b in (0, 1):
                pa_, pb = (one if a else 1 - one)[:, None], (one if b else 1 - one)[None, :]
                joint = both if a and b else one[:, None] - both if a else one[None, :] - both if b else 1 - one[:, None] - one[None, :] + both
                joint = np.clip(joint, 1e-9, 1)
                info += total / (n.sum() + 2) * joint * np.log(joint / (pa_ * pb))
    np.fill_diagonal(info, 0)
    parent = np.full(m, -1)
    inside, gain, via = np.zeros(m, bool), np.full(m, -1.0), np.full(m, -1)
    at = 0
    for _ in range(m):
        inside[at] = True
        better = (info[at] > gain) & ~inside
        gain[better], via[better] = info[at][better], at
        gain[at] = -2
        if inside.all():
            break
        at = int(np.argmax(np.where(inside, -3, gain)))
        parent[at] = via[at] if gain[at] > 1e-4 else -1
    return parent, info


def fit_label_model(v: np.ndarray, n: np.ndarray, toxic_votes: np.ndarray, false_share: float = 0.01, rounds: int = 40) -> tuple[LabelModel, np.ndarray]:
    """v: distinct vote rows (0/1), n: their counts, toxic_votes: the lexicon voters, which start as speaking for the toxic class.

    false_share: the share of a lexicon voter's votes that clean texts may cast while its parent is silent. Other voters
    start neutral between the classes and end where the votes put them.
    """
    base = np.where(toxic_votes, [[0.002], [0.2]], [[0.2], [0.2]])
    fired = v[:, toxic_votes].sum(1)
    q = np.where(fired >= 2, 0.95, np.where(fired == 1, 0.7, 0.03))
    model, info = LabelModel(0.1, np.full(v.shape[1], -1), np.zeros((v.shape[1], 2, 2))), np.zeros((v.shape[1],) * 2)
    for step in range(rounds):
        if step % 8 == 0:
            model.parent, info = correlation_tree(v, n, q)
        model.prior = float(np.clip((n * q).sum() / n.sum(), 1e-3, 0.6))
        above = np.where(model.parent >= 0, v[:, np.maximum(model.parent, 0)], 0)
        for y, w in ((0, n * (1 - q)), (1, n * q)):
            for s in (0, 1):
                there = (above == s) * w[:, None]
                model.chance[:, y, s] = ((there * v).sum(0) + 2 * base[y]) / (there.sum(0) + 2)
        most = np.maximum(false_share * (n @ v) / n.sum() / (1 - model.prior), 1e-5)
        model.chance[toxic_votes, 0, 0] = np.minimum(model.chance[toxic_votes, 0, 0], most[toxic_votes])
        q = model.posterior(v)
    return model, info


def fit_linear(rows: list[list[int]], q: np.ndarray, n: np.ndarray, size: int, steps: int = 400) -> np.ndarray:
    """Logistic regression on sparse binary rows, soft labels and row counts; the last weight is the bias.

    The penalty is that of `RIDGE` rows whatever their number, so rare entries keep their weight in a large sample.
    """
    cols = np.concatenate([np.array(r, np.int64) for r in rows]) if rows else np.zeros(0, np.int64)
    of = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    w, m, s = np.zeros(size + 1), np.zeros(size + 1), np.zeros(size + 1)
    for step in range(1, steps + 1):
        z = w[-1] + np.bincount(of, w[cols], len(rows))
        d = n * (q - 1 / (1 + np.exp(-np.clip(z, -30, 30))))
        g = (np.append(np.bincount(cols, d[of], size), d.sum()) - RIDGE * np.append(w[:-1], 0)) / n.sum()
        m, s = 0.9 * m + 0.1 * g, 0.999 * s + 0.001 * g * g
        w += 0.1 * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.999**step)) + 1e-8)
    return w


def fit(spark: SparkSession, docs: DataFrame, labels: DataFrame, most_labelled: int = 20_000, most_entries: int = 2_000, most_voters: int = 32) -> Model:
    """Fit on labelled rows whose crc32(doc_id) modulo 5 is not 0; `most_labelled` bounds the sample."""
    chosen = labels.where((crc_bucket(5) != 0) & F.col("toxic").isNotNull() & F.col("doc_id").isNotNull())
    chosen = chosen.select("doc_id", F.col("toxic").cast("int").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id", "toxic").limit(most_labelled)
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(chosen), "doc_id").select("text", "toxic")

    def count(batches: Iterator[pa.RecordBatch], hold: int = 200_000) -> Iterator[pa.RecordBatch]:
        seen: tuple[Counter, Counter] = (Counter(), Counter())

        def flush() -> pa.RecordBatch:
            keys = list(seen[0].keys() | seen[1].keys())
            out = [pa.array(keys, pa.string()), *(pa.array([seen[y][k] for k in keys], pa.int64()) for y in (1, 0))]
            seen[0].clear(), seen[1].clear()
            return pa.RecordBatch.from_arrays(out, ["unit", "pos", "neg"])

        for batch in batches:
            for text, y in zip(batch.column("text").to_pylist(), batch.column("toxic").to_pylist(), strict=True):
                seen[y > 0].update(units(text))
                seen[y > 0][""] += 1
                if len(seen[0]) + len(seen[1]) > hold:
                    yield flush()
        yield flush()

    summed = rows.mapInArrow(count, "unit string, pos long, neg long").groupBy("unit").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    summed = materialise(summed, spark)
    # The empty unit carries the numbers of rows; of the others only those often seen in toxic rows can be entries.
    whole = summed.where(F.col("unit") == "").first()
    pos, neg = (whole.pos, whole.neg) if whole else (0, 0)
    strong = summed.where((F.col("unit") != "") & (F.col("pos") >= 4) & (F.col("pos") > F.col("neg") / 2)).withColumn("p", F.col("pos"))
    units_tried = strong.count()
    strong = strong.orderBy(evidence(pos, neg)[1].desc(), "unit").limit(8 * most_entries)
    tried = {r.unit for r in strong.select("unit").collect()}

    def settings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """(unit, word before it) in toxic rows: copies of a text share these, so they count once."""
        seen: set[tuple[str, str]] = set()

        def flush() -> pa.RecordBatch:
            out = [pa.array([k[i] for k in seen], pa.string()) for i in (0, 1)]
            seen.clear()
            return pa.RecordBatch.from_arrays(out, ["unit", "before"])

        for batch in batches:
            for text, y in zip(batch.column("text").to_pylist(), batch.column("toxic").to_pylist(), strict=True):
                for p in pieces(text) if y > 0 else ():
                    before = ""
                    for w in _WORD.findall(p.lower()):
                        stems = [w[:k] for k in STEMS if len(w) >= k]
                        seen.update([(u, before) for u in (w, *(x + "*" * k for x in stems for k in TIMES)) if u in tried])
                        before = w
                if len(seen) > 100_000:
                    yield flush()
        yield flush()

    entries: list[str] = []
    if tried:
        # Copies of a text are one setting each, so a unit counts as often in toxic rows as it has settings there.
        varied = rows.mapInArrow(settings, "unit string, before string").distinct().groupBy("unit").count()
        judged = strong.join(varied, "unit").withColumn("p", F.least("pos", "count"))
        share, proof = evidence(pos, neg)
        judged = judged.select("unit", "p", share.alias("share"), proof.alias("proof")).where((F.col("p") >= 4) & (F.col("share") > 0.93) & (F.col("proof") > np.log(units_tried) + 5))
        entries = [r.unit for r in judged.orderBy(F.desc("proof"), "unit").limit(most_entries).collect()]
    model = Model({e: i for i, e in enumerate(entries)}, np.zeros(len(entries) + len(PATTERNS) + 1))
    prior = min((pos + 0.5) / (pos + neg + 1), 0.45)
    model.weights[-1] = np.log(prior / (1 - prior))
    if not entries:
        return model

    def reduce_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [model.feature_ids(t) for t in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([g[0] for g in got], pa.list_(pa.int32())), pa.array([g[1] for g in got], pa.int64()), batch.column("toxic")], ["ids", "n", "toxic"])

    sample = rows.mapInArrow(reduce_rows, "ids array<int>, n long, toxic int").groupBy("ids", (F.col("n") >= 60).alias("long"))
    sample = sample.agg(F.count(F.lit(1)).alias("c"), F.sum((F.col("toxic") > 0).cast("int")).alias("y")).collect()
    voter = families(entries, most_voters)
    m = int(voter.max()) + 1
    votes = np.zeros((len(sample), m + len(PATTERNS) + 1), np.int64)
    for i, r in enumerate(sample):
        lexical = [voter[k] for k in r.ids if k < len(entries)]
        votes[i, lexical] = 1
        votes[i, [m + k - len(entries) for k in r.ids if k >= len(entries)]] = 1
        votes[i, -1] = int(r.long and not lexical)
    toxic_votes = np.append(np.ones(m, bool), np.zeros(len(PATTERNS) + 1, bool))
    n = np.array([float(r.c) for r in sample])
    cast = votes[:, toxic_votes].sum(1)
    false_share = ((cast * np.array([r.c - r.y for r in sample])).sum() + 1) / ((cast * n).sum() + 2)
    label_model, info = fit_label_model(votes, n, toxic_votes, float(false_share))
    q = label_model.posterior(votes)
    parent = label_model.parent
    model.correlations = [(j, int(parent[j]), float(info[j, parent[j]])) for j in range(len(parent)) if parent[j] >= 0]
    model.accuracies = np.stack([1 - label_model.chance[:, 0, 0], label_model.chance[:, 1, 0]], 1)
    model.weights = fit_linear([r.ids for r in sample], q, n, len(entries) + len(PATTERNS))
    return model


def scorer(spark: SparkSession, model: Model):
    """Column function: toxicity score of a text."""
    held = spark.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(texts: pd.Series) -> pd.Series:
        m = held.value
        return pd.Series(m.scores(texts), dtype="float64")

    return lambda c: score(F.coalesce(c, F.lit("")))


def score_documents(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    model = fit(spark, docs, labels)
    scored = docs.select("doc_id", (crc_bucket(5) == 0).alias("held_out"), scorer(spark, model)(F.col("text")).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def drop_toxic(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of docs that score below one half, with their columns."""
    model = fit(spark, docs, labels)
    return docs.where(scorer(spark, model)(F.col("text")) < 0.5)
