"""Registry, plan shapes and streams."""

from __future__ import annotations

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from toponymix.plans import discover as D
from toponymix.plans import workloads
from toponymix.sources.fixtures import BASE, Tables
from toponymix.sources.tables import ALIAS_LIST, load_alias_list, read_table, save_bucketed, write_partitioned
from toponymix.streaming import footprints as streams


def norm(rows):
    return sorted(tuple(round(x, 6) if isinstance(x, float) else str(x) for x in r) for r in rows)


@pytest.mark.parametrize("name", ["w_authors", "w_alias_volume", "m1_score", "m3_kl_smooth", "m4_overlap", "e_cv_m4", "e_resolution", "j_near", "s_session", "s_state", "s_late"])
def test_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in BASE:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf_dir}/{t}.parquet'")
    df = workloads.queries()[name](spark, sf_dir)
    cols = sorted(df.columns)
    got = con.execute(workloads.oracle_sql()[name])
    at = [[d[0] for d in got.description].index(c) for c in cols]
    want = [[r[i] for i in at] for r in got.fetchall()]
    assert norm(df.select(*cols).collect()) == norm(want)


def test_registry_and_entry(spark):
    assert set(workloads.oracle_sql()) <= set(workloads.queries())
    assert entry.entry(spark).count() > 0
    assert len(entry.queries()) > 100


@pytest.mark.parametrize("method", ["M1", "M3", "M4"])
def test_no_nested_loops(spark, sf_dir, method):
    plan = D.scored(Tables(spark, sf_dir), method)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoop" not in plan.split("Scan")[0]


def test_overlap_ranks_best_and_printed_form_inverts(spark):
    t = {r.method: r for r in workloads.table_one(Tables(spark, "/root/testdata/sf0.01"), ["T1", "M1", "M4"]).collect()}
    assert t["M4"].cv_f1 > t["M1"].cv_f1 and t["M4"].cv_f1 > t["T1"].cv_f1


def test_streams_equal_their_batch_twins(spark, sf_dir, tmp_path):
    spark.read.parquet(f"{sf_dir}/events.parquet").repartitionByRange(3, "event_id").write.parquet(str(tmp_path / "in"))
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    src = streams.source(spark, str(tmp_path / "in"), schema, 10)  # one batch: files of a range may come in any order
    batch = streams.zoned(spark.read.parquet(f"{sf_dir}/events.parquet"))
    q = streams.start(streams.deduplicated(src).groupBy("event_type").agg(F.count(F.lit(1)).alias("n")), "dedupe", str(tmp_path / "c1"), "complete")
    q.awaitTermination(60)
    assert norm(spark.table("dedupe").collect()) == norm(batch.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).collect())
    target = str(tmp_path / "sums")
    auth = D.author_sets(Tables(spark, sf_dir))
    q = streams.by_place(streams.source(spark, str(tmp_path / "in"), schema), auth).writeStream.foreachBatch(streams.upsert_sums(target)).option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start()
    q.awaitTermination(60)
    assert norm(streams.read_sums(spark, target).collect()) == norm(streams.by_place(batch, auth).groupBy("place_name").agg(F.count(F.lit(1)).alias("n")).collect())


def test_state_is_kept_across_batches_and_late_rows_are_counted(spark, tmp_path):
    schema = "event_id bigint, place_name string, ts timestamp, lat_u bigint, lon_u bigint"
    batches = [[(k, "ab"[k % 2], f"2024-01-{day:02d} 00:00:0{k % 10}", 10 * k, k) for k in range(20 * b, 20 * b + 20)] for b, day in enumerate((10, 20, 21))]
    rows = [spark.createDataFrame(b, "event_id bigint, place_name string, ts string, lat_u bigint, lon_u bigint").withColumn("ts", F.col("ts").cast("timestamp")) for b in batches]
    old = rows[0].withColumn("ts", F.expr("timestamp'2023-01-01'"))

    def feed(df):
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))

    (tmp_path / "in").mkdir()
    pings = spark.readStream.schema(schema).parquet(str(tmp_path / "in"))
    seen = []
    for k, df in enumerate(rows):
        feed(df)
        # A fresh query on the same checkpoint: state survives the restart.
        out = streams.running_sums(pings, slots=4).writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True)
        out.foreachBatch(lambda b, i: seen.extend(b.collect())).start().awaitTermination(60)
    whole = rows[0].unionAll(rows[1]).unionAll(rows[2])
    got = streams.latest_sums(spark.createDataFrame(seen, streams.SUMS))
    assert norm(got.collect()) == norm(whole.groupBy("place_name").agg(F.count(F.lit(1)).alias("n"), F.sum("lat_u"), F.sum("lon_u")).collect())
    out = pings.withColumn("event_type", F.lit("x")).transform(streams.windowed_counts)
    target = out.writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "w")).trigger(availableNow=True).foreachBatch(lambda b, i: b.count())
    target.start().awaitTermination(60)
    feed(old)
    q = target.start()
    q.awaitTermination(60)
    assert streams.late_rows(q.recentProgress) > 0


def test_forgotten_keys_start_again_and_totals_stay_whole(spark, tmp_path):
    schema = "event_id bigint, place_name string, ts timestamp, lat_u bigint, lon_u bigint"
    (tmp_path / "in").mkdir()
    pings, seen = spark.readStream.schema(schema).parquet(str(tmp_path / "in")), []
    out = streams.running_sums(pings, slots=1).writeStream.outputMode("update").option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True)
    out = out.foreachBatch(lambda b, i: seen.extend(b.collect()))
    # "a" is silent for longer than the 30 days after which a key is forgotten; "b" moves the watermark on.
    for rows in ([(1, "a", "2024-01-01"), (2, "a", "2024-01-01")], [(3, "b", "2024-03-01")], [(4, "b", "2024-03-02")], [(5, "a", "2024-03-03")]):
        df = spark.createDataFrame([(*r, 10, 1) for r in rows], "event_id bigint, place_name string, ts string, lat_u bigint, lon_u bigint")
        df.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        out.start().awaitTermination(60)
    assert [r.n for r in seen if r.place_name == "a"] == [2, 1]
    assert [r.n for r in seen if r.place_name == "b"] == [1, 2]
    assert norm(streams.latest_sums(spark.createDataFrame(seen, streams.SUMS)).collect()) == [("a", "3", "30", "3"), ("b", "2", "20", "2")]


def test_sinks_prune_and_join_without_shuffle(spark, tmp_path):
    df = spark.createDataFrame([(c, d, u, u * 10) for c in (0, 1) for d in (0, 1, 2) for u in range(20)], "city int, district int, user_id bigint, v bigint")
    write_partitioned(df, str(tmp_path / "p"))
    back = spark.read.parquet(str(tmp_path / "p"))
    assert norm(back.select(df.columns).collect()) == norm(df.collect())
    plan = back.where("city = 1 AND district = 2")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(city" in plan and back.where("city = 1 AND district = 2").count() == 20
    try:
        for name in ("left_side", "right_side"):
            save_bucketed(df, name, 4)
        joined = spark.table("left_side").hint("merge").join(spark.table("right_side"), "user_id")
        assert "Exchange hashpartitioning" not in joined._jdf.queryExecution().executedPlan().toString()
        assert joined.count() == 20 * 36
    finally:
        for name in ("left_side", "right_side"):
            spark.sql(f"DROP TABLE IF EXISTS {name}")


def test_alias_list_formats(spark, tmp_path):
    df = spark.createDataFrame([(0, 1, "a", "b")], ALIAS_LIST)
    for fmt in ("json", "orc", "parquet"):
        df.write.format(fmt).save(str(tmp_path / fmt))
        assert read_table(spark, str(tmp_path / fmt), fmt, ALIAS_LIST).collect() == df.collect()
    df.write.option("header", "true").csv(str(tmp_path / "csv"))
    assert load_alias_list(spark, str(tmp_path / "csv")).collect() == df.collect()


def test_text_baselines_are_trained_inside_each_fold(spark):
    """All seven methods have a row, and the labels of the test districts never reach the fold's model."""
    t = Tables(spark, "/root/testdata/sf0.001")
    rows = {r.method for r in workloads.table_one(t, ("T1", "T2", "T3", "M4")).collect()}
    assert rows == {"T1", "T2", "T3", "M4"} and len(D.ALL_METHODS) == 7
    assert {"e_table1_all", "e_cv_t2", "e_cv_t3", "e_transfer_t2", "e_transfer_t3"} <= set(workloads.queries())
    whole = {(r.district, r.std_name, r.cand_name): r.score for r in D.fold_scored(t).where("fold = 0").collect()}
    t.truth = t.truth.where("district not in (0, 1)")
    assert {(r.district, r.std_name, r.cand_name): r.score for r in D.fold_scored(t).where("fold = 0").collect()} == whole


def test_corpus_registry_may_be_missing(monkeypatch):
    """An empty corpus folder, or none, leaves the other queries."""
    import sys

    monkeypatch.setitem(sys.modules, "toponymix.llm", None)
    names = set(entry.queries())
    assert not any(n.startswith("op") for n in names) and set(entry.oracle_sql()) <= names


@pytest.mark.parametrize("size", (3, 1000))
def test_blocks_equal_plain_pairs_and_shuffle_none(spark, size):
    """Counts and rows of all pairs equal plain loops, in one block or many; no pair is shuffled or labelled by a join."""
    import random

    from toponymix.operators import blocks, evaluate, textbase

    rng = random.Random(5)
    name = lambda: " ".join(rng.choice(["Red", "blue", "gear", "bolt", "Ünit", "x"]) for _ in range(rng.randint(1, 4)))
    std = sorted({(0 if d < 2 else 1, d, name()) for d in (0, 1, 10) for _ in range(9)})
    cand = sorted({(0 if d < 2 else 1, d, name() + "s") for d in (0, 1, 10, 11) for _ in range(8)})
    truth = [(*s[:2], s[2], c[2]) for s in std for c in cand if s[:2] == c[:2] and rng.random() < 0.2]
    at = "city int, district int, name string"
    s, c, t = spark.createDataFrame(std, at), spark.createDataFrame(cand, at), spark.createDataFrame(truth, "city int, district int, std_name string, cand_name string")
    grams = lambda x: {f"  {x.lower()} "[i : i + 3] for i in range(len(x) + 1)}
    want: dict[tuple, list[int]] = {}
    for a in std:
        for b in cand:
            if a[:2] == b[:2]:
                ga, gb = grams(a[2]), grams(b[2])
                e = want.setdefault((*a[:2], len(ga & gb), len(ga), len(a[2]), len(gb), len(b[2])), [0, 0])
                e[0] += 1
                e[1] += (*a, b[2]) in truth
    got = blocks.counts(s, c, t, blocks.shared_trigrams, size)
    assert {tuple(r)[:7]: [r.k, r.h] for r in got.collect()} == want
    rows = blocks.rows(s, c, t, blocks.hashed_products, size).withColumn("score", textbase.product_cosine())
    plain = {(*a, b[2]): (np.array(textbase.hashed_trigrams(pd.Series([a[2]]))[0]) * textbase.hashed_trigrams(pd.Series([b[2]]))[0]).sum() for a in std for b in cand if a[:2] == b[:2]}
    assert {(r.city, r.district, r.std_name, r.cand_name): r.score for r in rows.collect()} == pytest.approx(plain)
    keyed = evaluate.gathered(got.select("city", "district", (textbase.product_cosine()).alias("score"), "k", "h"))
    pairs = blocks.rows(s, c, t, blocks.shared_trigrams, size).withColumn("score", textbase.product_cosine())
    assert evaluate.best_cut(keyed, t).first() == evaluate.best_cut(pairs.select("city", "district", "std_name", "cand_name", "score"), t).first()


def test_sweep_of_sides_joins_nothing_at_the_end(spark):
    """Each side of `m2_d_sweep` is written by itself: the final plan holds no join and no broadcast."""
    plan = workloads.queries()["m2_d_sweep"](spark, "/root/testdata/sf0.001")._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Broadcast" not in plan
