"""Jump consistent hashing: stable keys go to shards without a ring table.

A key is mixed once and then walks the jump sequence: from a bucket b the next bucket is a pseudo-random one beyond b,
and the last bucket below the shard count wins. Appending a shard moves only rows whose walk now lands on it.

Edge cases: a null key is a key of its own (mixed from 0 with a flag); null or empty texts have size 1 and checksum 0;
repeated rows share a shard and get slots of their own; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import dense_slots

#: The generator of the published jump hash and the additive constant of the 64-bit mixer.
JUMP_MULTIPLIER = 2862933555777941757
MIX_INCREMENT = 0x9E3779B97F4A7C15


def jump_buckets(keys: np.ndarray, shards: int) -> np.ndarray:
    """The bucket of each 64-bit key among `shards` buckets; all keys walk together, finished ones drop out."""
    if shards < 1:
        raise ValueError("shards must be positive")
    x = keys.astype(np.int64).view(np.uint64) + np.uint64(MIX_INCREMENT)
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    state = x ^ (x >> np.uint64(31))
    bucket = np.zeros(len(state), np.int64)
    walking = np.arange(len(state))
    at = np.zeros(len(state), np.int64)
    while len(walking):
        bucket[walking] = at
        state[walking] = state[walking] * np.uint64(JUMP_MULTIPLIER) + np.uint64(1)
        span = (state[walking] >> np.uint64(33)).astype(np.float64) + 1.0
        at = np.floor((at + 1) * (2147483648.0 / span)).astype(np.int64)
        on = at < shards
        walking, at = walking[on], at[on]
    return bucket


def jump_shard(key: Column, shards: int) -> Column:
    """Arrow-batched column form of `jump_buckets` for a long key."""

    @F.pandas_udf("int")
    def place(k: pd.Series) -> pd.Series:
        return pd.Series(jump_buckets(k.to_numpy(dtype=np.int64), shards).astype(np.int32))

    return place(F.coalesce(key.cast("long"), F.lit(-1).cast("long")))


def shard_documents(docs: DataFrame, shards: int = 16, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard of every row.

    Texts are reduced to size and checksum inside the scan; only these few numbers are shuffled.
    """
    whole = F.coalesce(F.col(text), F.lit(""))
    rows = docs.select(
        F.col(key).alias("doc_id"),
        (F.octet_length(whole).cast("long") + 1).alias("size"),
        F.crc32(whole.cast("binary")).cast("long").alias("text_crc32"),
        F.lit("key").alias("law"),
        jump_shard(F.col(key), shards).alias("shard"),
        jump_shard(F.col(key), shards + 1).alias("grown_shard"),
    )
    out = dense_slots(rows, "shard", "doc_id", ["text_crc32", "size"])
    return out.select("doc_id", "size", "text_crc32", "law", "shard", "slot", "grown_shard")

