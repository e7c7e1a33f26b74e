"""Optimal length buckets: dynamic programming over the global length histogram, then token-budget batches.

The histogram is aggregated on the cluster and bounded whatever the input: lengths below `EXACT` are bins of their own,
longer ones share a bin with lengths within one part in `EXACT // 2`, so at most a few hundred thousand bins reach the
driver. The programme picks at most `buckets` upper bounds that minimise padding; batches of a bucket hold as many rows
as fit the token budget at its upper bound, at least one.

Edge cases: null and empty texts have length 1 (the end token); equal lengths share a bucket; repeated rows are kept;
a row longer than the budget forms a batch of its own; an empty table gives an empty result; extra columns are dropped.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import dense_slots, materialise

EXACT = 1 << 14


def token_length(text: Column) -> Column:
    """Words (runs of characters other than ASCII white space) plus one end token."""
    return (F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+")) + 1).cast("long")


def bin_bound(length: Column) -> Column:
    """The largest length of the bin that holds `length`."""
    step = F.pow(F.lit(2.0), F.greatest(F.lit(0.0), F.floor(F.log2(length.cast("double"))) - 13)).cast("long")
    return F.when(length < EXACT, length).otherwise((F.floor((length - 1) / step) + 1).cast("long") * step)


def optimal_bounds(histogram: list[tuple[int, int]], buckets: int) -> list[int]:
    """Upper bounds of at most `buckets` buckets with the least padded total for [(length, rows)].

    best[j] for k buckets is v_j*C_j + min over i<j of (best_{k-1}[i] - v_j*C_i): a lower envelope of lines whose
    slopes fall with i while queries v_j rise, so each layer takes linear time in exact integers.
    """
    hist = sorted(histogram)
    n = len(hist)
    if not n:
        return []
    value = [v for v, _ in hist]
    upto = [0]
    for _, c in hist:
        upto.append(upto[-1] + c)
    best = [value[j] * upto[j + 1] for j in range(n)]
    choice: list[list[int]] = [[0] * n]
    for _ in range(1, min(buckets, n)):
        nxt, pick = best[:], [-1] * n
        lines: list[tuple[int, int, int]] = []
        head = 0
        for j in range(1, n):
            m, b = -upto[j], best[j - 1]
            while len(lines) - head >= 2:
                (m1, b1, _), (m2, b2, _) = lines[-2], lines[-1]
                if (b - b1) * (m1 - m2) <= (b2 - b1) * (m1 - m):
                    lines.pop()
                else:
                    break
            lines.append((m, b, j))
            q = value[j]
            while len(lines) - head >= 2 and lines[head + 1][0] * q + lines[head + 1][1] <= lines[head][0] * q + lines[head][1]:
                head += 1
            cost = q * upto[j + 1] + lines[head][0] * q + lines[head][1]
            if cost < nxt[j]:
                nxt[j], pick[j] = cost, lines[head][2]
        choice.append(pick)
        best = nxt
    bounds, j, k = [], n - 1, len(choice) - 1
    while j >= 0:
        bounds.append(value[j])
        while k > 0 and choice[k][j] == -1:
            k -= 1
        if k == 0:
            break
        j, k = choice[k][j] - 1, k - 1
    return bounds[::-1]


def pack(spark: SparkSession, docs: DataFrame, buckets: int = 16, budget: int = 16384, text: str = "text") -> DataFrame:
    """doc_id, n_tokens, bucket, pad_to, batch, place, padding of every row."""
    lengths = materialise(docs.select("doc_id", token_length(F.col(text)).alias("n_tokens")), spark)
    hist = lengths.groupBy(bin_bound(F.col("n_tokens")).alias("v")).agg(F.count(F.lit(1)).alias("n"))
    bounds = optimal_bounds([(r.v, r.n) for r in hist.collect()], buckets)
    bucket, pad = F.lit(0), F.lit(bounds[0] if bounds else 1).cast("long")
    for k in range(1, len(bounds)):
        past = F.col("n_tokens") > bounds[k - 1]
        bucket, pad = F.when(past, F.lit(k)).otherwise(bucket), F.when(past, F.lit(bounds[k]).cast("long")).otherwise(pad)
    placed = lengths.select("doc_id", "n_tokens", bucket.alias("bucket"), pad.alias("pad_to"))
    room = F.greatest(F.lit(1).cast("long"), F.floor(F.lit(budget) / F.col("pad_to")).cast("long"))
    out = dense_slots(placed, "bucket", "doc_id", ["n_tokens"])
    return out.select(
        "doc_id",
        "n_tokens",
        "bucket",
        "pad_to",
        F.floor(F.col("slot") / room).cast("long").alias("batch"),
        (F.col("slot") % room).alias("place"),
        (F.col("pad_to") - F.col("n_tokens")).alias("padding"),
    )
