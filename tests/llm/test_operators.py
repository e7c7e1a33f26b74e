"""Corpus operators against plain versions, with nulls, empty texts, repeats, empty tables and extra columns."""

from __future__ import annotations

import glob
import hashlib
import itertools
import os
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from toponymix.llm import chat, common, decontaminate, lm_scoring, ngram_join, packing, pii, queries, sharding, suffix_dedup, topk_search, toxicity
from toponymix.llm.common import text_bytes, word_hashes

DOC = "doc_id bigint, text string, lang string, source string, n_chars bigint, p string, slab string, k string"


def docs(spark, texts, ids=None):
    """Documents with extra columns whose names the operators use inside."""
    ids = range(len(texts)) if ids is None else ids
    return spark.createDataFrame([(i, x, "en", "s", len(x or ""), "p", "slab", "k") for i, x in zip(ids, texts, strict=True)], DOC)


def words(rng, n, vocab=400):
    return " ".join(f"w{rng.randrange(vocab)}" for _ in range(n))


def edited(rng, text, edits):
    ws = text.split()
    for _ in range(edits):
        ws[rng.randrange(len(ws))] = f"e{rng.randrange(10**6)}"
    return " ".join(ws)


def test_word_hashes_split_like_python():
    import pyarrow as pa

    rng = random.Random(3)
    for _ in range(100):
        xs = ["".join(rng.choice("aB \n\té") for _ in range(rng.randint(0, 12))) for _ in range(5)] + [None]
        _, counts = word_hashes(*text_bytes(pa.array(xs)))
        assert counts.tolist() == [len((x or "").encode().split()) for x in xs]


def test_sharding_moves_only_to_the_new_shard(spark):
    rows = sharding.shard_documents(docs(spark, ["a", None, "", "é", "a", "a"] + ["x"] * 2000, [0, 1, 2, 3, 4, 4, *range(10, 2010)])).collect()
    assert len(rows) == 2006
    assert all(r.grown_shard in (r.shard, 16) for r in rows)
    by = {}
    for r in rows:
        by.setdefault(r.shard, []).append(r.slot)
    assert all(sorted(s) == list(range(len(s))) for s in by.values()) and len(by) == 16
    one = {r.doc_id: r for r in rows}
    assert (one[1].size, one[1].text_crc32) == (1, 0) and one[3].text_crc32 == zlib.crc32("é".encode())
    assert sharding.shard_documents(docs(spark, [])).count() == 0
    assert np.bincount(sharding.jump_buckets(np.arange(16000), 16)).min() > 850


def test_optimal_bounds_are_optimal():
    rng = random.Random(5)
    for _ in range(40):
        hist = sorted({rng.randint(1, 60): rng.randint(1, 9) for _ in range(rng.randint(1, 9))}.items())
        for k in (1, 2, 3, 4):
            cost = lambda bounds: sum(c * (min(b for b in bounds if b >= v) - v) for v, c in hist)
            values = [v for v, _ in hist]
            best = min(cost(set(c) | {values[-1]}) for r in range(k) for c in itertools.combinations(values, r))
            got = packing.optimal_bounds(hist, k)
            assert len(got) <= k and cost(got) == best


def test_packing_fills_batches(spark):
    rng = random.Random(1)
    rows = packing.pack(spark, docs(spark, [words(rng, rng.randint(0, 60)) for _ in range(300)] + [None, ""]), 4, 100).collect()
    assert len(rows) == 302 and all(r.padding >= 0 for r in rows)
    for _, g in itertools.groupby(sorted(rows, key=lambda r: (r.bucket, r.batch, r.place)), key=lambda r: (r.bucket, r.batch)):
        g = list(g)
        assert [r.place for r in g] == list(range(len(g))) and (len(g) * g[0].pad_to <= 100 or len(g) == 1)
    assert packing.pack(spark, docs(spark, [])).count() == 0


def test_chat_round_trip(spark):
    texts = ["</s>[INST] ok [/INST]", "[\\INST] <\\s>\\", None, "<", "s>", "a</s"]
    rows = [(1, i, "user" if i % 2 == 0 else "assistant", x) for i, x in enumerate(texts)] + [(2, 0, "system", "only"), (3, None, None, None), (4, 1, "assistant", "x"), (4, 1, "assistant", "x")]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")
    got = {r.conv_id: r for r in chat.digest(chat.format_conversations(df)).collect()}
    want = "".join(f"{'user' if i % 2 == 0 else 'assistant'}\n{x or ''}\n" for i, x in enumerate(texts))
    assert got[1].turns_sha256 == hashlib.sha256(want.encode()).hexdigest() and got[1].n_turns == 6
    assert got[1].loss_sha256 == hashlib.sha256("".join(x or "" for x in texts[1::2]).encode()).hexdigest()
    assert (got[2].n_turns, got[2].loss_chars, got[3].n_turns, got[4].n_turns, got[4].loss_chars) == (1, 0, 1, 2, 2)
    assert chat.digest(chat.format_conversations(df.limit(0))).count() == 0


def test_top_k_equals_brute_force(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(700, 12))
    x[300:] = x[:400] + rng.normal(scale=0.05, size=(400, 12))
    x[500:560] = x[0]
    rows = [(i, v.tolist(), 0) for i, v in enumerate(x)] + [(9000, None, 0), (9100, [1.0, None], 0), (9200, [float("nan")] * 12, 0), (9300, [1.0, 2.0], 0), (9301, [2.0, 1.0], 0), (9400, [], 0)]
    df = spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, label int")
    got = {(r.query_id, r.rank): (r.vec_id, r.score) for r in topk_search.top_k(spark, df).collect()}
    v = np.floor(1024 * x).astype(np.int64)
    for q in range(0, 700, 100):
        s = v @ v[q]
        order = [i for i in sorted(range(700), key=lambda i: (-s[i], i)) if i != q][:10]
        assert [got[(q, k + 1)] for k in range(10)] == [(i, int(s[i])) for i in order]
    assert got[(9300, 1)][0] == 9301 and (9300, 2) not in got and not any(q in (9000, 9100, 9200, 9400) for q, _ in got)
    assert topk_search.top_k(spark, df.limit(0)).count() == 0


def test_top_k_drops_pairs_of_blocks_on_clustered_vectors(spark, monkeypatch):
    """Bounds of whole trees rule out most pairs where vectors cluster, a crowded centre is split, and answers stay exact."""
    monkeypatch.setattr(topk_search, "GROUP", 40)
    monkeypatch.setattr(topk_search, "BLOCK", 150)
    rng = np.random.default_rng(12)
    middle = rng.normal(size=(20, 16))
    x = middle[rng.integers(0, 20, 3000)] + rng.normal(scale=0.02, size=(3000, 16))
    x[1000:2000] = x[0]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, embedding array<double>").repartition(4)
    pairs, asked, trees = topk_search._pairs(spark, df, 10, 50, 1024.0, 4096)
    assert trees.count() > 20 and pairs.count() < 0.5 * asked.count() * trees.count()
    v = np.floor(1024 * x).astype(np.int64)
    want = {}
    for q in range(0, 3000, 50):
        s = v @ v[q]
        s[q] = -(2**62)
        want |= {(q, k + 1): (int(i), int(s[i])) for k, i in enumerate(np.lexsort((np.arange(3000), -s))[:10])}
    assert {(r.query_id, r.rank): (r.vec_id, r.score) for r in topk_search.top_k(spark, df, every=50).collect()} == want


def test_top_k_counts_repeated_rows_like_the_sql(spark):
    """One id fills the top k by its copies; query ids repeat, with equal and other vectors; many queries share a vector."""
    rng = np.random.default_rng(8)
    vec = rng.normal(size=(60, 4)).astype(np.float32)
    rows = [(i, vec[i].tolist()) for i in range(60)] + [(7, vec[7].tolist())] * 40 + [(0, vec[0].tolist())] * 3 + [(0, vec[1].tolist())] + [(100, vec[7].tolist())] * 15
    rows += [(100 * j, vec[9].tolist()) for j in range(2, 90)]
    want: dict[int, list] = {}
    whole = [(i, np.floor(1024 * np.array(v, np.float64))) for i, v in rows]
    for q, x in whole:
        if q % 100 == 0:
            want.setdefault(q, []).extend((-int(x @ y), c) for c, y in whole if c != q)
    got: dict[int, list] = {}
    for r in topk_search.top_k(spark, spark.createDataFrame(rows, "vec_id bigint, embedding array<float>").repartition(3)).collect():
        got.setdefault(r.query_id, []).append((r.rank, -r.score, r.vec_id))
    assert {q: sorted(v) for q, v in got.items()} == {q: [(k + 1, *p) for k, p in enumerate(sorted(v)[:10])] for q, v in want.items()}


def test_repeated_starts_equal_brute_force():
    rng = random.Random(1)
    for length, trial in itertools.product((60, 75, 120), range(40)):
        letters = b"ab" if trial % 2 else b"abcdefgh"
        base = [bytes(rng.choice(letters) for _ in range(rng.randint(1, 200))) for _ in range(3)]
        pieces = []
        for _ in range(rng.randint(1, 7)):
            b = bytearray(rng.choice(base) + rng.choice(base))
            for _ in range(rng.randint(0, 3)):
                b[rng.randrange(len(b))] = rng.choice(letters)
            pieces.append(bytes(b))
        count: dict[bytes, int] = {}
        for p in pieces:
            for i in range(len(p) - length + 1):
                count[p[i : i + length]] = count.get(p[i : i + length], 0) + 1
        want = np.concatenate([[i + length <= len(p) and count[p[i : i + length]] > 1 for i in range(len(p))] for p in pieces])
        off = np.append(0, np.cumsum([len(p) for p in pieces]))
        assert (suffix_dedup.repeated_starts(np.frombuffer(b"".join(pieces), np.uint8), off, length) == want).all()


@pytest.mark.parametrize("most", [960_000, 1600])
def test_suffix_dedup_equals_brute_force(spark, monkeypatch, most):
    monkeypatch.setattr(suffix_dedup, "GROUP_SYMBOLS", most)
    rng = random.Random(7)
    long = words(rng, 300)
    texts = [long, edited(rng, long, 2), edited(rng, long, 6), words(rng, 50) + long[200:900] + words(rng, 40), "é" * 700, None, "", "short", long, words(rng, 200)]
    ids = [*range(9), 8]
    got = suffix_dedup.dedup(spark, docs(spark, texts, ids)).collect()
    raw = [(x or "").encode() for x in texts]
    count: dict[bytes, int] = {}
    for b in raw:
        for i in range(len(b) - 399):
            count[b[i : i + 400]] = count.get(b[i : i + 400], 0) + 1
    want = []
    for i, b in zip(ids, raw, strict=True):
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - 399):
            if count[b[k : k + 400]] > 1:
                gone[k : k + 400] = True
        want.append((i, len(b), int(gone.sum()), len(suffix_dedup.runs(gone)[0]), hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()))
    assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == sorted(want)
    assert suffix_dedup.dedup(spark, docs(spark, [])).count() == 0


@pytest.mark.parametrize("most", [960_000, 100])
def test_passages_of_fifty_words_repeat_across_documents(spark, monkeypatch, most):
    """Words in 50-word runs that another document holds; a document's own repeats, short runs and other cases don't count."""
    monkeypatch.setattr(suffix_dedup, "GROUP_SYMBOLS", most)
    rng = random.Random(17)
    short = lambda n: " ".join(rng.choice("abcdefghij") + str(rng.randrange(10)) for _ in range(n))
    p, q, r, s = short(51), short(80), short(49), short(60)
    texts = [f"{short(30)} {p} {short(20)}", f"{p.upper()}\n{short(9)}", f"{s} x {s}", f"{short(40)} {q}", f"{q} {r}", f"{r} {short(70)} {p} y {p}", None, "", f"{q} {short(5)}", edited(rng, short(200), 0)]
    got = {x.doc_id: x.n_passage_words for x in suffix_dedup.dedup(spark, docs(spark, texts)).collect()}
    words_of = [(x or "").lower().split() for x in texts]
    held: dict[tuple, set] = {}
    for i, ws in enumerate(words_of):
        for k in range(len(ws) - 49):
            held.setdefault(tuple(ws[k : k + 50]), set()).add(i)
    for i, ws in enumerate(words_of):
        inside = {k + d for k in range(len(ws) - 49) if len(held[tuple(ws[k : k + 50])]) > 1 for d in range(50)}
        assert got[i] == len(inside)
    assert [got[i] > 0 for i in range(10)] == [True, True, False, True, True, True, False, False, True, False]


def brute_components(texts, ids, t):
    sets = []
    for x in texts:
        w = (x or "").encode().lower().split()
        sets.append({tuple(w[i : i + t.width]) for i in range(max(len(w) - t.width + 1, 1))} if w else set())
    label = list(range(len(texts)))
    for a, b in itertools.combinations(range(len(texts)), 2):
        i = len(sets[a] & sets[b])
        if sets[a] and sets[b] and t.den * i >= t.num * (len(sets[a]) + len(sets[b]) - i):
            x, y = label[a], label[b]
            label = [x if v == y else v for v in label]
    least = {v: min(ids[i] for i in range(len(ids)) if label[i] == v) for v in set(label)}
    return sorted((ids[i], len(sets[i]), least[label[i]]) for i in range(len(ids)))


@pytest.mark.parametrize("t", [ngram_join.Threshold(), ngram_join.Threshold(80, 100, 5)])
def test_ngram_join_equals_brute_force(spark, t):
    rng = random.Random(11)
    cloud = words(rng, 120)
    texts = [edited(rng, cloud, rng.randint(0, 9)) for _ in range(60)] + [cloud] * 5
    for n in (3, 5, 9, 14, 22, 40):
        base = words(rng, n)
        texts += [base, base.upper(), edited(rng, base, 1), base + " tail"]
    texts += [None, "", "  ", "one", "One", words(rng, 2000)]
    ids = list(range(len(texts)))
    got = sorted(tuple(r) for r in ngram_join.similar_components(spark, docs(spark, texts), t).collect())
    assert got == brute_components(texts, ids, t)
    assert ngram_join.similar_components(spark, docs(spark, []), t).count() == 0


def test_representatives_are_rows_not_ids(spark):
    """Null ids, ids with several texts and repeated rows: of each component one row stays, and nothing else goes."""
    rng = random.Random(12)
    one, two, three, four = (words(rng, 60, 5000) for _ in range(4))
    rows = [(5, one), (None, two), (None, three), (5, two + " x"), (3, edited(rng, one, 1)), (7, four), (7, four), (None, one), (None, three), (None, None), (None, ""), (9, ""), (9, "")]
    kept = ngram_join.keep_representatives(spark, docs(spark, [x for _, x in rows], [i for i, _ in rows])).collect()
    want = [(3, rows[4][1]), (5, two + " x"), (7, four), (None, three), (None, None), (None, ""), (9, "")]
    assert sorted(map(str, want)) == sorted(str((r.doc_id, r.text)) for r in kept)


def test_signatures_meet_for_all_similar_sets():
    rng = np.random.default_rng(4)
    t = ngram_join.Threshold()
    edges = ngram_join.band_edges()[:20]
    for population in (10, 10**9):
        bands = [ngram_join.allocate(t, a, b - 1, population) for a, b in zip(edges, edges[1:])]
        for n in (7, 9, 12, 13, 20, 50, 120, 300):
            for _ in range(20):
                s = rng.integers(0, 2**63, n, dtype=np.uint64)
                lost = int(t.differences(2 * n)) // 2
                r = np.sort(np.append(s[lost:], rng.integers(0, 2**63, lost, dtype=np.uint64)))
                if lost == 0 and t.differences(2 * n - 1) >= 1:
                    r = np.sort(s[1:])
                got = [set(ngram_join.signatures(t, bands, np.sort(x), np.zeros(len(x), np.int64), np.array([len(x)]), np.array([1]))[0].tolist()) for x in (s, r)]
                assert got[0] & got[1] or not lost


def test_containment_equals_sets(spark):
    rng = random.Random(2)
    items = [words(rng, n, 50) for n in (4, 8, 30, 60)] + [None, ""]
    texts = [words(rng, 400), words(rng, 50) + " " + items[2] + " " + words(rng, 900), " ".join(items[:4]), edited(rng, items[3], 1), items[0], None, "", " ".join([*items[:4], *(words(rng, 300, 50) for _ in range(3))])]
    it = spark.createDataFrame([*enumerate(items), (2, items[2])], "item_id bigint, text string")
    got = {(r.doc_id, r.item_id): r.containment for r in decontaminate.contained_items(spark, docs(spark, texts), it).collect()}
    want = {}
    for d, i in itertools.product(range(len(texts)), range(4)):
        w = min(5, len(items[i].split()))
        sh = lambda x, w=w: {tuple(x.split()[k : k + w]) for k in range(len(x.split()) - w + 1)}
        q = sh(items[i])
        c = len(q & sh(texts[d] or "")) / len(q)
        if c >= 0.8:
            want[(d, i)] = c
    assert got == pytest.approx(want)
    assert decontaminate.contained_items(spark, docs(spark, []), it).count() == 0
    assert decontaminate.contained_items(spark, docs(spark, texts), it.limit(0)).count() == 0


PLAIN = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def plain_valid(kind, m):
    d = re.sub("[^0-9]", "", m)
    if kind == "ip":
        return all(int(x) <= 255 for x in m.split("."))
    if kind == "card":
        return 14 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
    return 10 <= len(d) <= 15 if kind == "phone" else True


def test_private_spans_equal_plain_patterns(spark):
    rng = random.Random(9)
    parts = ["a@b.c_d@e.f", "x.y+z@m-1.example.com.", "1.2.3.4.5.6.7.8", "300.1.1.1", "000255.0.0.1", "4111 1111 1111 1111", "4111-1111-1111-1112", "+1 (988) 555-2485", "+12", "é", "@@a@b.c", "password=e9b9ed9cc9999999d9", "\U0001f600 10.0.0.1", "99999999999999999999999", ".", " "]
    texts = ["".join(rng.choice(parts) + rng.choice(["", " "]) for _ in range(12)) for _ in range(150)] + [None, "", "a" * 50000 + "@" + "b" * 50000]
    rows = {r.doc_id: r for r in pii.report(spark, docs(spark, texts)).collect()}
    for i, x in enumerate(texts):
        spans = sorted((m.start(), k, f"{kind}:{m.start()}:{m.end()}") for k, (kind, p) in enumerate(PLAIN.items()) for m in re.finditer(p, x or "") if plain_valid(kind, m.group()))
        assert rows[i].base_sha256 == hashlib.sha256(",".join(s[2] for s in spans).encode()).hexdigest()
        assert {s[2] for s in spans} <= set(rows[i].spans.split(",")) or not spans
    out = {r.doc_id: r.text for r in pii.mask(spark, docs(spark, ["mail a@b.cd now", None, "", "ip 10.0.0.1."])).collect()}
    assert out == {0: "mail <EMAIL> now", 1: None, 2: "", 3: "ip <IP>."}
    assert pii.report(spark, docs(spark, [])).count() == 0


def test_mask_takes_the_union_of_overlapping_spans(spark):
    got = pii.mask(spark, docs(spark, ["ip 10.0.0.4 111 1111 1111 1111 end", "card 4111 1111 1111 1111, ip 10.0.0.1"])).orderBy("doc_id").collect()
    assert [(r.text, r.n_chars) for r in got] == [("ip <IP> end", 11), ("card <CARD>, ip <IP>", 20)]


def test_mask_equals_the_spans_and_moves_no_text(spark, sf_dir):
    """The masked texts are those that the spans give, without an exchange of rows."""
    d = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "n_chars")
    extra = [(90_000_001, "token=abcd1234efgh5678 x@y.zz 10.1.2.3", 38), (90_000_002, None, 0), (90_000_003, "card 4111 1111 1111 1111 \U0001f600 +1 (555) 123-4567", 1)]
    d = d.unionByName(spark.createDataFrame(extra, d.schema)).coalesce(2)
    found: dict[int, list] = {}
    for r in pii.spans(spark, d).where("keep").collect():
        found.setdefault(r.doc_id, []).append((r.start, -r.end, r.k))
    masked = pii.mask(spark, d)
    assert "Exchange" not in masked._jdf.queryExecution().executedPlan().toString()
    plain = {r.doc_id: r for r in d.collect()}
    for r in masked.collect():
        text, at, out = plain[r.doc_id].text, 0, ""
        for start, end, k in sorted(found.get(r.doc_id, [])):
            if start >= at:
                out += text[at:start] + f"<{pii.KINDS[k].upper()}>"
            at = max(at, -end)
        want = out + text[at:] if r.doc_id in found else text
        assert r.text == want and r.n_chars == (len(want) if r.doc_id in found else plain[r.doc_id].n_chars)
    assert len(found) > 2


def test_representatives_leave_one_table_and_turns_lose_nothing(spark, sf_dir):
    """Of the stage's tables only the list of rows that go stays; verification in many turns keeps the same rows."""
    d = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(400).repartition(3).localCheckpoint()
    d = d.unionByName(d.limit(40))
    tables = lambda: {x for x in glob.glob(common.shared_dir(spark).removeprefix("file:") + "/*") if os.path.exists(f"{x}/_SUCCESS")}
    before = tables()
    kept = ngram_join.keep_representatives(spark, d)
    assert len(tables() - before) == 1
    once = sorted(r.doc_id for r in kept.collect())
    assert once == sorted(r.doc_id for r in ngram_join.keep_representatives(spark, d, turn=5).collect())
    assert "Exchange hashpartitioning(" not in kept._jdf.queryExecution().executedPlan().toString().split("BroadcastExchange")[0]


def test_label_model_finds_the_good_voters():
    rng = np.random.default_rng(0)
    y = rng.random(4000) < 0.2
    v = np.stack([np.where(y, rng.random(4000) < a, rng.random(4000) < 0.001) for a in (0.7, 0.5, 0.6)] + [~y & (rng.random(4000) < 0.6)], 1).astype(int)
    rows, n = np.unique(v, axis=0, return_counts=True)
    model, _ = toxicity.fit_label_model(rows, n.astype(float), np.array([True, True, True, False]))
    q = model.posterior(v)
    assert np.mean((q > 0.5) == y) > 0.96


def test_posterior_equals_enumeration():
    """The posterior of each vote row is the joint of either class over their sum, by a product over voters and parents."""
    rng = np.random.default_rng(5)
    rows, n = np.unique(rng.integers(0, 2, (300, 4)), axis=0, return_counts=True)
    model, _ = toxicity.fit_label_model(rows, n.astype(float), np.array([True, True, False, False]))
    for r, got in zip(rows, model.posterior(rows), strict=True):
        joint = []
        for y, prior in ((0, 1 - model.prior), (1, model.prior)):
            for j, p in enumerate(model.parent):
                c = model.chance[j, y, r[p] if p >= 0 else 0]
                prior *= c if r[j] else 1 - c
            joint.append(prior)
        assert got == pytest.approx(joint[1] / sum(joint))


def test_toxicity_learns_and_keeps_clean_texts(spark):
    rng = random.Random(4)
    bad = ["wretch", "vermin", "sleaze"]
    texts, labels = [], []
    for _ in range(900):
        y = rng.random() < 0.2
        ws = words(rng, 60).translate(str.maketrans("0123456789", "abcdefghij")).split()
        for _ in range(3 if y else 0):
            ws.insert(rng.randrange(60), rng.choice(bad))
        texts.append(" ".join(ws))
        labels.append(int(y))
    lab = spark.createDataFrame(list(enumerate(labels)), "doc_id bigint, toxic int")
    rows = toxicity.score_documents(spark, docs(spark, [*texts, None, ""]), lab).collect()
    assert len(rows) == 902 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in rows)
    held = [r for r in rows if r.held_out and r.doc_id < 900]
    assert np.mean([labels[r.doc_id] == r.predicted for r in held]) > 0.97
    none = toxicity.score_documents(spark, docs(spark, texts[:3]), lab.limit(0)).collect()
    assert [r.predicted for r in none] == [0, 0, 0]
    assert toxicity.score_documents(spark, docs(spark, []), lab).count() == 0


def test_language_model_normalises_and_base_is_exact(spark):
    rng = random.Random(6)
    texts = [" ".join(itertools.chain.from_iterable((f"a{k}", f"b{k}") for k in (rng.randrange(8) for _ in range(40)))) for _ in range(120)] + [None, "", f"rare{1}"]
    rows = {r.doc_id: r for r in lm_scoring.score_texts(spark, docs(spark, texts).select("doc_id", "text"), n_classes=24, frequent=10).collect()}
    train: dict[str, int] = {}
    for i, x in enumerate(texts):
        if zlib.crc32(str(i).encode()) % 7 != 2:
            for w in [*(x or "").split(), "END"]:
                train[w] = train.get(w, 0) + 1
    total = sum(train.values())
    for i, x in enumerate(texts):
        ws = [*(x or "").split(), "END"]
        assert rows[i].base_score == pytest.approx(sum(np.log10((train.get(w, 0) + 1) / (total + len(train) + 1)) for w in ws))
        assert (rows[i].n_tokens, rows[i].n_known, rows[i].train_tokens) == (len(ws), sum(w in train for w in ws), total)
    assert sum(r.score for r in rows.values()) > 0.8 * sum(r.base_score for r in rows.values())
    near, far, norm = lm_scoring.train(*np.random.default_rng(1).integers(0, 9, (2, 5, 4)).astype(float)).tables()
    assert (10 ** (near[:, None, :] + far[None] - norm[:, :, None])).sum(2) == pytest.approx(1, abs=1e-5)
    assert lm_scoring.score_texts(spark, docs(spark, []).select("doc_id", "text")).count() == 0


def test_language_model_learns_from_both_words_before():
    """A word that depends on the word two before it alone is foretold by the second position only."""
    rng, n = np.random.default_rng(4), 6
    texts = []
    for _ in range(400):
        t = [int(x) for x in rng.integers(2, n, 2)]
        while len(t) < 30:
            t.append(t[-2] if rng.random() < 0.8 else int(rng.integers(2, n)))
        texts.append([*t, lm_scoring.STOP])
    first, second = np.zeros((n + 1, n)), np.zeros((n + 1, n))
    tokens = [(a, b, c) for t in texts for a, b, c in zip([n, n, *t], [n, *t], t)]
    for two, one, w in tokens:
        first[one, w] += 1
        second[two, w] += 1
    near, far, norm = lm_scoring.train(first, second).tables()
    both = np.mean([near[one, w] + far[two, w] - norm[one, two] for two, one, w in tokens])
    alone = np.mean([near[one, w] - np.log10((10 ** near[one]).sum()) for _, one, w in tokens])
    entropy = -np.mean([np.log10(second[two, w] / second[two].sum()) for two, _, w in tokens])
    assert both > alone + 0.1 and -both < entropy + 0.01


def test_training_holds_few_tables_on_the_driver():
    """Peak of numpy's memory in training, beside the two given tables: no more than six tables of single floats."""
    import pickle
    import tracemalloc

    n = 512
    first, second = np.random.default_rng(2).integers(0, 9, (2, n + 1, n))
    tracemalloc.start()
    model = lm_scoring.train(first, second, steps=3)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 6.5 * 4 * n * (n + 1)
    assert len(pickle.dumps(model)) < 4 * n * 4 * 2 * 26


def test_scores_are_sums_of_the_models_own_probabilities(spark, monkeypatch):
    """Every row's score is a plain sum over its tokens, and the probabilities of all tokens after a context add to one."""
    made = []
    train = lm_scoring.train
    monkeypatch.setattr(lm_scoring, "train", lambda *pairs: made.append(train(*pairs)) or made[-1])
    rng = random.Random(16)
    texts = [" ".join(f"w{min(rng.randrange(40), rng.randrange(40))}" for _ in range(rng.randrange(30))) for _ in range(80)] + [None, "", "never seen"]
    rows = {r.doc_id: r.score for r in lm_scoring.score_texts(spark, docs(spark, texts).select("doc_id", "text"), n_classes=12, frequent=10**6).collect()}
    count: dict[str, int] = {}
    for i, x in enumerate(texts):
        if zlib.crc32(str(i).encode()) % 7 != 2:
            for w in [*(x or "").split(), None]:
                count[w] = count.get(w, 0) + 1
    hashed = {w: int(word_hashes(np.frombuffer(w.encode(), np.uint8), np.array([0, len(w)]))[0].view(np.int64)[0]) for w in count if w}
    ranked = sorted(hashed, key=lambda w: (-count[w], hashed[w]))[:10]
    cls = {w: 2 + k for k, w in enumerate(ranked)} | {None: 1}
    other = [w for w in count if w not in cls]
    size = sum(count[w] for w in other) + len(other) + 1
    scores = [side.scores().astype(float) for side in (made[0].near, made[0].far)]
    logp = scores[0][:, None] + scores[1][None]
    logp = (logp - np.log(np.exp(logp).sum(2, keepdims=True))) / np.log(10)
    inside = lambda w: np.log10((count.get(w, 0) + 1) / size) if w not in cls else 0.0
    for i, x in enumerate(texts):
        before, want = (12, 12), 0.0
        for w in [*(x or "").split(), None]:
            want += logp[*before, cls.get(w, 0)] + inside(w)
            before = (cls.get(w, 0), before[0])
        assert rows[i] == pytest.approx(want, abs=1e-4)
    for before in itertools.product(range(13), range(13)):
        total = sum(10 ** (logp[*before, cls.get(w, 0)] + inside(w)) for w in [*count, "unseen"])
        assert total == pytest.approx(1, abs=1e-5)


def test_shards_equal_a_plain_walk():
    """The published jump rule, one step at a time, on keys through the 64-bit mixer."""
    top = 2**64

    def walk(key: int, n: int) -> int:
        key = (key + sharding.MIX_INCREMENT) % top
        key = (key ^ key >> 30) * 0xBF58476D1CE4E5B9 % top
        key = (key ^ key >> 27) * 0x94D049BB133111EB % top
        key, b, j = key ^ key >> 31, -1, 0
        while j < n:
            b, key = j, (key * sharding.JUMP_MULTIPLIER + 1) % top
            j = int((b + 1) * (float(1 << 31) / ((key >> 33) + 1)))
        return b

    keys = [0, 1, 2, 17, 10**6, 2**62, -5]
    assert [int(x) for x in sharding.jump_buckets(np.array(keys), 16)] == [walk(k % top, 16) for k in keys]


@pytest.mark.parametrize("name", ["op1", "op2", "op3", "op4", "op6", "op7", "op9", "op10"])
def test_null_and_repeated_ids_and_long_texts(spark, name):
    """Two-megabyte texts, null ids, equal ids on different texts, repeated rows and clashing columns: a row for each row."""
    rng = random.Random(41)
    long = words(rng, 400_000, 10**6)
    rows = [(1, "a b c d e f"), (1, "g h i j k l"), (None, "a b c d e f"), (None, None), (2, long), (2, long), (3, "")]
    df = docs(spark, [x for _, x in rows], [i for i, _ in rows])
    lab = spark.createDataFrame([(1, 0), (2, 1), (None, 1), (3, None)], "doc_id bigint, toxic int")
    run = {
        "op1": lambda: toxicity.score_documents(spark, df, lab),
        "op2": lambda: packing.pack(spark, df),
        "op3": lambda: suffix_dedup.dedup(spark, df),
        "op4": lambda: decontaminate.contained_items(spark, df, spark.createDataFrame([(1, "a b c d e f"), (2, "zz")], "item_id bigint, text string")),
        "op6": lambda: pii.report(spark, df),
        "op7": lambda: ngram_join.similar_components(spark, df),
        "op9": lambda: sharding.shard_documents(df),
        "op10": lambda: lm_scoring.score_texts(spark, df),
    }
    got = run[name]().collect()
    if name == "op4":
        assert [(r.doc_id, r.item_id) for r in got] == [(1, 1)]
    else:
        assert sorted(str(r.doc_id) for r in got) == sorted(str(i) for i, _ in rows)
    if name == "op3":
        assert sorted(r.n_removed for r in got)[-2:] == [len(long)] * 2


def test_pipeline_stages_keep_columns_and_take_effect(spark, sf_dir):
    import corpus_pipeline

    d = spark.read.parquet(f"{sf_dir}/documents.parquet")
    cols = d.columns
    for name, stage in corpus_pipeline.STAGES:
        before, d = d, stage(spark, d, sf_dir)
        assert d.columns == cols or name == "packing"
        assert d.count() <= before.count()
    assert d.count() > 100
    assert corpus_pipeline.run(spark, sf_dir).count() == d.count()
    assert set(queries.oracle_sql()) <= set(queries.queries())


def test_pipeline_equals_plain_stages_with_null_ids(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(21)
    item, twin = words(rng, 20, 5000), words(rng, 60, 5000)
    rows = [(i, words(rng, 50, 5000)) for i in range(8)] + [(None, words(rng, 50, 5000)) for _ in range(3)]
    rows += [(20, twin), (None, edited(rng, twin, 1)), (None, twin), (3, words(rng, 50, 5000)), (None, f"{words(rng, 9)} {item} {words(rng, 9)}"), (21, f"{item} {words(rng, 30, 5000)}")]
    rows += [(30, "mail a@b.cd " + words(rng, 30, 5000)), (None, None), (31, "")]
    docs(spark, [x for _, x in rows], [i for i, _ in rows]).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "doc_id bigint, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")

    grams = lambda x: {tuple(ws[k : k + 5]) for ws in [(x or "").split()] for k in range(max(len(ws) - 4, min(len(ws), 1)))}
    kept: list[tuple] = []
    for i, x in sorted(rows, key=lambda r: (r[0] is None, r[0] or 0)):
        g = grams(x)
        if not any(g and 10 * len(g & grams(y)) >= 8 * len(g | grams(y)) for _, y in kept):
            kept.append((i, x))
    kept = [(i, x) for i, x in kept if 10 * len(grams(x) & grams(item)) < 8 * len(grams(item))]
    kept = [(i, x and x.replace("a@b.cd", "<EMAIL>")) for i, x in kept]
    d = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        d = stage(spark, d, str(tmp_path))
        d = corpus_pipeline.materialise(d, spark)
    assert sorted(str((r.doc_id, r.text)) for r in d.collect()) == sorted(map(str, kept))
    packed = corpus_pipeline.run(spark, str(tmp_path))
    assert sorted(str(r.doc_id) for r in packed.collect()) == sorted(str(i) for i, _ in kept)


def test_null_ids_link_their_neighbours(spark):
    """A text without an id joins two others that are not alike themselves; a component without ids has no name."""
    ws = words(random.Random(32), 60, 5000).split()
    rows = [(1, " ".join(["x1", "x2", *ws])), (None, " ".join(ws)), (9, " ".join([*ws, "y1", "y2"])), (None, "p q r s t"), (None, "p q r s t"), (None, None)]
    t = ngram_join.Threshold(95, 100, 4)
    got = ngram_join.similar_components(spark, docs(spark, [x for _, x in rows], [i for i, _ in rows]), t).collect()
    assert sorted(str((r.doc_id, r.component_id)) for r in got) == sorted(map(str, [(1, 1), (None, 1), (9, 1), (None, None), (None, None), (None, None)]))


def test_components_take_each_text_of_a_repeated_id(spark):
    """Id 1 carries two unrelated texts, each the near copy of another id's text."""
    rng = random.Random(31)
    one, two = words(rng, 80, 5000), words(rng, 80, 5000)
    rows = [(1, one), (1, two), (4, edited(rng, one, 1)), (5, edited(rng, two, 1)), (6, words(rng, 80, 5000))]
    for order in (rows, rows[::-1]):
        got = ngram_join.similar_components(spark, docs(spark, [x for _, x in order], [i for i, _ in order])).collect()
        assert sorted((r.doc_id, r.component_id) for r in got) == [(1, 1), (1, 1), (4, 1), (5, 1), (6, 6)]
