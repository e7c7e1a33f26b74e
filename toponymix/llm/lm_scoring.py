"""Log-bilinear language model trained in numpy with noise-contrastive estimation; exact unigram base beside it.

Word counts of all training texts are summed on the cluster; the most frequent words become the model's classes, with
one class for the end of a text and one for all other words, whose members share that class's mass by their counts. The
model predicts the next class w from the two words before it, each position with matrices of its own:
score = C1[h1] . R1[w] + b1[w] + C2[h2] . R2[w] + b2[w].

Training is noise-contrastive, position after position. The nearest is held against smoothed unigram noise. The second is
held against noise drawn from the model of the first, so the first cancels in its odds and its objective depends on the
corpus only through pair counts at distance two and the expected noise; the latter follows from the pair counts at distance
one, as all but the last of them are the contexts of a next token. Both tables are summed over all training texts: training
is exact full-batch ascent over the whole corpus with a driver footprint fixed by the number of classes. Batched products of
the factors give the scores of all contexts and, in one more product, the normaliser of every pair of contexts; tokens look
them up.

Counts of frequent words (at most `frequent`, documented bound) are broadcast; counts of all rarer words are joined by
a shuffle, so every token meets its exact count. Words are told apart by a 64-bit hash.

Edge cases: null and empty texts have one token, the end; without training texts all counts are 0 and both scores are
that of an empty model; repeated rows and equal or null ids each give a row; an empty table gives an empty result.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_bucket, materialise, mix, row_slices, signed, text_bytes, word_hashes

END = -1  # hash value that stands for the end token
OTHER, STOP = 0, 1


@dataclass
class Vocabulary:
    """Frequent words by ascending hash, their counts and class ids (OTHER for words without a class)."""

    keys: np.ndarray
    counts: np.ndarray
    ids: np.ndarray

    def find(self, h: np.ndarray) -> np.ndarray:
        """Position of each hash among the keys, -1 where it is not one."""
        if not len(self.keys):
            return np.full(len(h), -1)
        at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
        return np.where(self.keys[at] == h, at, -1)


def _slices(batch: pa.RecordBatch) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    data, off = text_bytes(batch.column("text"))
    for i, j in row_slices(off):
        words, counts = word_hashes(data[off[i] : off[j]], off[i : j + 1] - off[i])
        yield i, j, signed(words), counts


def token_counts(docs: DataFrame, hold: int = 1_500_000) -> DataFrame:
    """(h, c): the count of each token, end tokens included; tasks add up before the shuffle, within `hold` entries."""

    def merge(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
        h, inv = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
        return h, np.bincount(inv, np.concatenate([p[1] for p in parts]), len(h)).astype(np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        for batch in batches:
            for i, j, words, _ in _slices(batch):
                parts.append(np.unique(words, return_counts=True))
                parts.append((np.array([END]), np.array([j - i])))
                if sum(len(p[0]) for p in parts) > hold:
                    parts = [merge(parts)]
                    if len(parts[0][0]) > hold // 2:
                        yield pa.RecordBatch.from_arrays([pa.array(x) for x in parts.pop()], ["h", "c"])
        if parts:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in merge(parts)], ["h", "c"])

    return docs.select("text").mapInArrow(run, "h long, c long").groupBy("h").agg(F.sum("c").alias("c"))


def classes_of(vocab: Vocabulary, words: np.ndarray, counts: np.ndarray, n_classes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(class before, class before that, class, row, position in the vocabulary) of every token, each row closed by its end token."""
    at = vocab.find(words)
    own = np.where(at >= 0, vocab.ids[at] if len(vocab.ids) else OTHER, OTHER)
    rows = np.arange(len(counts))
    ends = np.cumsum(counts + 1) - 1
    total = int((counts + 1).sum())
    is_end = np.zeros(total, bool)
    is_end[ends] = True
    cls, pos = np.full(total, STOP), np.full(total, -1)
    cls[~is_end], pos[~is_end] = own, at
    before = np.empty(total, np.int64)
    before[1:] = cls[:-1]
    second = np.empty(total, np.int64)
    second[2:] = cls[:-2]
    # The start of a text is a context of its own.
    before[ends - counts] = n_classes
    second[ends - counts] = n_classes
    second[(ends - counts + 1)[counts > 0]] = n_classes
    return before, second, cls, np.repeat(rows, counts + 1), pos


def pair_counts(docs: DataFrame, vocab, n_classes: int) -> DataFrame:
    """(pair, c): how often each class follows each context class, over all texts; then the same at distance two."""
    cells = (n_classes + 1) * n_classes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(2 * cells, np.int64)
        for batch in batches:
            for _, _, words, counts in _slices(batch):
                before, second, cls, _, _ = classes_of(vocab.value, words, counts, n_classes)
                for at, context in enumerate((before, second)):
                    total[at * cells : (at + 1) * cells] += np.bincount(context * n_classes + cls, minlength=cells)
        there = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(there), pa.array(total[there])], ["pair", "c"])

    return docs.select("text").mapInArrow(run, "pair long, c long").groupBy("pair").agg(F.sum("c").alias("c"))


@dataclass
class Position:
    context: np.ndarray
    target: np.ndarray
    bias: np.ndarray

    def scores(self) -> np.ndarray:
        """Rows are contexts, columns classes."""
        return self.context @ self.target.T + self.bias


@dataclass
class LogBilinear:
    near: Position
    far: Position

    def tables(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(near, far, norm) in base 10: a class w after h1, with h2 before that, has near[h1, w] + far[h2, w] - norm[h1, h2]."""
        near, far = self.near.scores(), self.far.scores()
        near -= near.max(1, keepdims=True)
        far -= far.max(1, keepdims=True)
        norm = np.exp(near) @ np.exp(far).T
        np.log10(np.maximum(norm, 1e-37, out=norm), out=norm)
        near /= np.float32(math.log(10))
        far /= np.float32(math.log(10))
        return near, far, norm


#: The tables of the last model that this process has worked out, by its broadcast.
_WORKED_OUT: dict[int, tuple[LogBilinear, tuple[np.ndarray, np.ndarray, np.ndarray]]] = {}


def _tables(model) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    key = id(model.value)
    if key not in _WORKED_OUT:
        _WORKED_OUT.clear()
        _WORKED_OUT[key] = (model.value, model.value.tables())
    return _WORKED_OUT[key][1]


def ascend(data: np.ndarray, drawn: np.ndarray, offset: np.ndarray | float, bias: np.ndarray, decay: float, dims: int, steps: int, rate: float, seed: int) -> Position:
    """Ascent with Adam on the expected noise-contrastive objective of one position.

    data and drawn are the shares of true and of noise tokens by context and class, offset is the log density of the noise that
    the scores are held against. The noise's expectation is taken in closed form instead of by sampling. decay draws the factors
    to zero, as a normal prior does. `drawn` is overwritten.
    """
    rng = np.random.default_rng(seed)
    contexts, classes = data.shape
    # Two tables are reused by all steps, so the driver holds four of them at a time.
    g, work = np.empty_like(data), np.empty_like(data)
    p = [rng.normal(0, 0.1, (contexts, dims)).astype(np.float32), rng.normal(0, 0.1, (classes, dims)).astype(np.float32), bias.astype(np.float32)]
    m, v = [np.zeros_like(x) for x in p], [np.zeros_like(x) for x in p]
    both = drawn
    both += data
    for step in range(1, steps + 1):
        np.matmul(p[0], p[1].T, out=g)
        g += p[2] - offset
        np.negative(g, out=g)
        np.exp(g, out=g)
        g += 1
        np.divide(both, g, out=work)
        np.subtract(data, work, out=g)
        grads = [g @ p[1] - decay * p[0], g.T @ p[0] - decay * p[1], g.sum(0)]
        lr = rate * (1 - 0.9 * step / steps)
        for k, d in enumerate(grads):
            m[k] = 0.9 * m[k] + 0.1 * d
            v[k] = 0.99 * v[k] + 0.01 * d * d
            p[k] = p[k] + lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-9)
    return Position(*p)


def train(first: np.ndarray, second: np.ndarray, dims: int = 24, noise: int = 10, prior: float = 4.0, steps: int = 250, rate: float = 0.03, seed: int = 7) -> LogBilinear:
    """Model of the pair counts (contexts by classes) at distances one and two; the last context is the start of a text.

    prior is the precision of the factors in units of one token, so its weight falls as the corpus grows.
    """
    classes, total = first.shape[1], max(first.sum(), 1)
    unigram = (first.sum(0) + 1.0) / (first.sum() + classes)
    data = np.divide(first, total, dtype=np.float32, casting="unsafe")
    drawn = np.multiply(data.sum(1, keepdims=True) * noise, unigram, dtype=np.float32, casting="unsafe")
    near = ascend(data, drawn, np.log(noise * unigram).astype(np.float32), np.log(unigram), float(prior / total), dims, steps, rate, seed)
    del drawn
    p = near.scores()
    p -= p.max(1, keepdims=True)
    np.exp(p, out=p)
    p /= p.sum(1, keepdims=True)
    # Share of tokens by context at distance two and one: a pair at distance one, unless it ends its text, is followed by one token.
    contexts = np.zeros((classes + 1, classes + 1), np.float32)
    contexts[:, :classes] = data
    contexts[:, STOP] = 0
    contexts[-1, -1] = data[:, STOP].sum()
    drawn = contexts @ p
    drawn *= noise
    del contexts, p
    np.divide(second, total, out=data, casting="unsafe")
    far = ascend(data, drawn, np.float32(math.log(noise)), np.zeros(classes), float(prior / total), dims, steps, rate, seed + 1)
    return LogBilinear(near, far)


def _frequent(counts: DataFrame, most: int):
    """Words whose count is at least some cut, at most `most` of them; the cut comes from a histogram of fixed size."""
    step = F.floor(F.log2(F.col("c").cast("double")) * 16).cast("int")
    kept, cut = 0, None
    for r in sorted(counts.groupBy(step.alias("s")).agg(F.count(F.lit(1)).alias("n")).collect(), reverse=True):
        if kept + r.n > most:
            break
        kept, cut = kept + r.n, r.s
    frequent = step >= (cut if cut is not None else 1 << 30)
    return counts.where(frequent), counts.where(~frequent)


def score_texts(spark: SparkSession, docs: DataFrame, held_out=None, n_classes: int = 2048, frequent: int = 1 << 19) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row of docs (doc_id, text)."""
    rule = (crc_bucket(7) == 2) if held_out is None else held_out
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    train_docs = docs.where(~rule)
    counts = materialise(token_counts(train_docs), spark)
    total, distinct = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    common, rare = _frequent(counts, frequent)
    table = common.select("h", "c").toArrow()
    keys, c = (table.column(x).to_numpy().astype(np.int64) for x in ("h", "c"))
    by = np.argsort(keys)
    keys, c = keys[by], c[by]
    order = np.lexsort((keys, -c))
    ranked = order[keys[order] != END][: n_classes - 2]
    ids = np.full(len(keys), OTHER, np.int32)
    ids[ranked] = np.arange(2, 2 + len(ranked))
    ids[keys == END] = STOP
    classed = int(c[ids != OTHER].sum())
    n_other, v_other = total - classed, distinct - int((ids != OTHER).sum())
    end_count = int(c[keys == END].sum()) or int(counts.where(F.col("h") == END).agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0])

    vocab = spark.sparkContext.broadcast(Vocabulary(keys, c, ids))
    pairs = np.zeros((2, n_classes + 1, n_classes), np.int64)
    for batch in pair_counts(train_docs, vocab, n_classes).toArrow().to_batches():
        pairs.reshape(-1)[batch.column("pair").to_numpy()] = batch.column("c").to_numpy()
    # The factors are sent, not the tables of all contexts; each Python worker works these out once.
    model = spark.sparkContext.broadcast(train(*pairs))
    del pairs

    schema = "rid long, h long, tf long, doc_id long, n_tokens long, known long, lg double, lp double, n_other long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        voc, (near, far, norm) = vocab.value, _tables(model)
        next_row = TaskContext.get().partitionId() << 36
        lg_of = np.append(np.log10(voc.counts + 1.0), 0.0)
        known_of = np.append(np.ones(len(voc.counts), np.int64), 0)
        for batch in batches:
            for i, j, words, n in _slices(batch):
                before, second, cls, row, pos = classes_of(voc, words, n, n_classes)
                rows = j - i
                other = cls == OTHER
                lp = np.bincount(row, near[before, cls] + far[second, cls] - norm[before, second], rows) + np.bincount(row[other], lg_of[pos[other]], rows)
                end = cls == STOP
                lg = np.bincount(row, np.where(end, math.log10(end_count + 1.0), lg_of[pos]), rows)
                known = np.bincount(row, known_of[pos], rows).astype(np.int64) + (end_count > 0)
                rid = np.arange(next_row, next_row + rows)
                next_row += rows
                cols = [rid, signed(mix(rid.astype(np.uint64))), np.zeros(rows, np.int64)]
                yield pa.RecordBatch.from_arrays(
                    [*map(pa.array, cols), batch.column("doc_id").slice(i, rows).cast(pa.int64()), *map(pa.array, (n + 1, known, lg, lp, np.bincount(row[other], minlength=rows)))],
                    ["rid", "h", "tf", "doc_id", "n_tokens", "known", "lg", "lp", "n_other"],
                )
                token = ~end
                gone = pos[token] < 0
                if gone.any():
                    h, r = words[gone], row[token][gone]
                    by = np.lexsort((h, r))
                    h, r = h[by], r[by]
                    first = np.flatnonzero(np.append(True, (h[1:] != h[:-1]) | (r[1:] != r[:-1])))
                    tf = np.diff(np.append(first, len(h)))
                    none = lambda t, k=len(first): pa.nulls(k, t)
                    yield pa.RecordBatch.from_arrays(
                        [pa.array(rid[r[first]]), pa.array(h[first]), pa.array(tf), none(pa.int64()), none(pa.int64()), none(pa.int64()), none(pa.float64()), none(pa.float64()), none(pa.int64())],
                        ["rid", "h", "tf", "doc_id", "n_tokens", "known", "lg", "lp", "n_other"],
                    )

    rows = docs.mapInArrow(run, schema)
    seen = rows.join(rare.withColumnRenamed("c", "rc"), "h", "left")
    rc = F.coalesce("rc", F.lit(0))
    per = seen.groupBy("rid").agg(
        *[F.max(k).alias(k) for k in ("doc_id", "n_tokens", "known", "lg", "lp", "n_other")],
        F.sum(F.when(F.col("tf") > 0, F.col("tf") * F.log10(rc + 1.0)).otherwise(0.0)).alias("rare_lg"),
        F.sum(F.when(rc > 0, F.col("tf")).otherwise(0)).alias("rare_known"),
    )
    return per.select(
        "doc_id",
        rule.alias("held_out"),
        "n_tokens",
        (F.col("known") + F.col("rare_known")).alias("n_known"),
        F.lit(int(total)).cast("long").alias("train_tokens"),
        (F.col("lg") + F.col("rare_lg") - F.col("n_tokens") * math.log10(total + distinct + 1)).alias("base_score"),
        (F.col("lp") + F.col("rare_lg") - F.col("n_other") * math.log10(n_other + v_other + 1)).alias("score"),
    )
