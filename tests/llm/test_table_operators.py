from __future__ import annotations

import collections
import math
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from poiweave.llm import mixing, neighbours, quality, sharding
from poiweave.llm.op5 import op5_nearest
from poiweave.llm.session import table

from .helpers import awkward, brute_classes, brute_nearest, empty, words


def test_nearest_is_exact_on_small_tables(spark, sf):
    t = table(spark, sf, "embeddings").select("vec_id", "embedding").toPandas()
    want = brute_nearest(t.vec_id.to_numpy(), np.stack(t.embedding.to_list()).astype(float), 5, 50)
    got = collections.defaultdict(list)
    for r in op5_nearest(spark, sf).orderBy("query_id", "rank").collect():
        got[r.query_id].append(r.vec_id)
    assert dict(got) == want


def test_nearest_recall_when_leaves_are_skipped(spark):
    r = np.random.default_rng(0)
    x = r.normal(size=(6000, 16)) + 3 * r.normal(size=(20, 16))[r.integers(0, 20, 6000)]
    d = spark.createDataFrame([(k, [float(c) for c in row]) for k, row in enumerate(x)], "vec_id long, embedding array<double>")
    want = brute_nearest(np.arange(6000), x, 5, 50)
    got = collections.defaultdict(set)
    for row in neighbours.nearest(d, share=0.2, least=500, block=20).collect():
        got[row.query_id].add(row.vec_id)
    assert sum(len(got[q] & set(v)) for q, v in want.items()) / (5 * len(want)) >= 0.9


def test_nearest_recall_at_the_shipped_settings(spark):
    """The larger given table, which has more rows than a query visits."""
    t = table(spark, "/root/testdata/sf0.1", "embeddings").select("vec_id", "embedding").toPandas()
    x = np.stack(t.embedding.to_list()).astype(float)
    r = np.random.default_rng(0)
    # the given vectors, and as many more between random pairs of them, so that no leaf holds all
    y = x[r.integers(0, len(x), 10_000)] + x[r.integers(0, len(x), 10_000)] + 0.5 * r.normal(size=(10_000, x.shape[1])) / 8
    d = spark.createDataFrame([(k, [float(c) for c in row]) for k, row in enumerate(np.concatenate([x, y]))], "vec_id long, embedding array<double>")
    want = brute_nearest(np.arange(len(x) + len(y)), np.concatenate([x, y]), 5, 50)
    got = collections.defaultdict(set)
    for row in neighbours.nearest(d).collect():
        got[row.query_id].add(row.vec_id)
    assert sum(len(got[q] & set(v)) for q, v in want.items()) / (5 * len(want)) >= 0.9


def test_nearest_edge_cases(spark):
    v = [1.0, 0.0]
    rows = [(0, v), (0, v), (1, v), (2, v), (3, [0.0, 2.0]), (50, [5.0, 0.0]), (51, None), (52, [0.0, 0.0]), (53, [float("nan"), 1.0]), (54, [None, 1.0]), (55, [1.0]), (None, v), (56, [float("inf"), 1.0]), (57, [])]
    d = spark.createDataFrame([(i, e, "x") for i, e in rows], "vec_id long, embedding array<double>, score string")
    got = collections.defaultdict(list)
    for r in neighbours.nearest(d).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.rank, r.vec_id, r.score))
    assert [x[1] for x in got[0]] == [1, 2, 50, 3] and [x[1] for x in got[50]] == [0, 1, 2, 3]
    assert got[0][0][2] == pytest.approx(1) and got[0][3][2] == pytest.approx(0)
    assert neighbours.nearest(d.limit(0)).count() == 0
    assert neighbours.nearest(d.filter("vec_id = 0").limit(1)).count() == 0


def test_many_equal_vectors_keep_the_smallest_ids(spark):
    d = spark.createDataFrame([(k, [1.0, 2.0]) for k in range(200)] + [(500, [2.0, 1.0])], "vec_id long, embedding array<double>")
    got = neighbours.nearest(d).filter("query_id = 100").orderBy("rank").collect()
    assert [r.vec_id for r in got] == [0, 1, 2, 3, 4]


def _check_shards(p, shards, text):
    n = collections.Counter(p["shard"])
    assert set(p["shard"]) <= set(range(shards))
    for s in n:
        assert sorted(p["slot"][p["shard"] == s]) == list(range(n[s]))
    size = p.groupby("shard")["size"].sum()
    assert size.max() - size.min() <= 0.004 * size.sum() / shards + 2 * p["size"].max()
    for d, s, c in zip(p["doc_id"], p["size"], p["text_crc32"], strict=True):
        if d in text:
            b = (text[d] or "").encode()
            assert s == len(b) + 1 and c == zlib.crc32(b)


def test_shards(spark, sf):
    d = table(spark, sf, "documents")
    p = sharding.shard_digest(d).toPandas()
    assert len(p) == d.count()
    _check_shards(p, 16, {r.doc_id: r.text for r in d.select("doc_id", "text").collect()})
    again = sharding.shard_digest(d.repartition(7)).toPandas()
    assert p.sort_values("doc_id").reset_index(drop=True).equals(again.sort_values("doc_id").reset_index(drop=True))


def test_a_hot_text_is_spread_over_shards(spark):
    d = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") < 1500, F.lit("same text")).otherwise(F.concat(F.lit("text "), F.col("id").cast("string"))).alias("text"))
    p = sharding.shard_digest(d, 8).toPandas()
    _check_shards(p, 8, {})
    assert p[p["doc_id"] < 1500]["shard"].nunique() >= 3


def test_repeated_rows_are_cut_like_others(spark):
    """Rows with equal ids and texts have one key, which is cut inside by count, over several partitions."""
    same = spark.range(2000).select(F.lit(None).cast("long").alias("doc_id"), F.lit("the same words again").alias("text"))
    d = spark.range(2000).select(F.col("id").alias("doc_id"), F.concat(F.lit("text number "), F.col("id").cast("string")).alias("text")).unionByName(same).repartition(7)
    p = sharding.shard_digest(d, 16).toPandas()
    size = p.groupby("shard")["size"].sum()
    assert len(p) == 4000 and len(size) == 16 and size.max() - size.min() <= 0.01 * size.sum() / 16 + 50
    for s in range(16):
        assert sorted(p["slot"][p["shard"] == s]) == list(range((p["shard"] == s).sum()))
    assert p[p["doc_id"].isna()]["shard"].nunique() >= 7
    whole = sharding.shard_texts(d, 16).groupBy("shard").agg(F.count(F.lit(1)).alias("n"), F.max("slot").alias("top"), F.count_distinct("slot").alias("slots")).collect()
    assert sum(r.n for r in whole) == 4000 and all(r.top == r.n - 1 == r.slots - 1 for r in whole)


def test_shards_against_a_sorted_list(spark, sf):
    """All rows in the order of their keys, cut where a shard's bytes come nearest to an equal share."""
    d = table(spark, sf, "documents").select("doc_id", "text")
    keyed = d.select("doc_id", sharding.text_size(F.col("text")).alias("size"), sharding.row_key(F.col("doc_id"), F.col("text")).alias("key")).toPandas().sort_values(["key", "doc_id"]).reset_index(drop=True)
    p = sharding.shard_digest(d, 8).toPandas().sort_values(["shard", "slot"]).reset_index(drop=True)
    assert p["doc_id"].tolist() == keyed["doc_id"].tolist()
    begin = keyed["size"].cumsum().to_numpy() - keyed["size"].to_numpy()
    cuts = [int((p["shard"] < s).sum()) for s in range(1, 8)]
    total = int(keyed["size"].sum())
    for s, c in zip(range(1, 8), cuts, strict=True):
        goal = s * total / 8
        assert abs(begin[c] - goal) <= max(np.abs(begin - goal).min(), 0.002 * total / 8) + 1


def test_shard_edge_cases(spark):
    p = sharding.shard_digest(awkward(spark)).toPandas()
    assert len(p) == 15 and p[p["doc_id"] == 4]["size"].iloc[0] == 1
    _check_shards(p, 16, {})
    assert sharding.shard_digest(empty(spark)).count() == 0
    whole = sharding.shard_texts(awkward(spark))
    assert whole.count() == 15 and set(whole.columns) == set(awkward(spark).columns)


def _sizes(rows):
    return [(d, s, len(t.split()) if t else 0) for d, s, t in rows]


def _brute_targets(sizes):
    names = sorted((s for s in sizes if s is not None)) + ([None] if None in sizes else [])
    w = {s: (5, 2, 1)[k % 3] for k, s in enumerate(names)}
    total, capped = sum(sizes.values()), set()
    while True:
        free = [s for s in names if s not in capped]
        left = total - sum(3 * sizes[s] for s in capped)
        level = left / sum(w[s] for s in free) if free else 0
        over = [s for s in free if level * w[s] > 3 * sizes[s] + 1e-9]
        if not over:
            return {s: 3.0 * sizes[s] if s in capped else level * w[s] for s in names}
        capped |= set(over)


def _check_mix(got, rows, tolerance):
    sizes = collections.Counter()
    for _, s, n in rows:
        sizes[s] += n
    want, taken = _brute_targets(sizes), collections.Counter()
    source = {d: s for d, s, _ in rows}
    for r in got:
        s = source[r.doc_id]
        assert r.source_size == sizes[s] and math.isclose(r.target, want[s], rel_tol=1e-9, abs_tol=1e-6)
        assert 0 <= r.taken <= 3 * r.size and (r.size == 0 or r.taken % r.size == 0)
        taken[s] += r.taken
    for s in sizes:
        assert abs(taken[s] - want[s]) <= tolerance(s, want[s])


def test_mix_meets_targets(spark):
    sf = "/root/testdata/sf0.01"
    d = table(spark, sf, "documents")
    rows = [(r.doc_id, r.source, r.n) for r in d.select("doc_id", "source", mixing.word_count(F.col("text")).alias("n")).collect()]
    got = mixing.mix_digest(d).collect()
    assert len(got) == len(rows)
    _check_mix(got, rows, lambda s, t: 0.05 * t)
    assert sorted(got) == sorted(mixing.mix_digest(d.repartition(5)).collect())


def test_mix_with_few_sources_caps_and_zeros(spark):
    rows = [(k, "a", 10) for k in range(100)] + [(1000 + k, "b", 10) for k in range(900)] + [(5000, "c", 0), (6000, None, 3), (6001, None, 0)]
    d = spark.createDataFrame([(i, s, " ".join(["w"] * n) if n else None) for i, s, n in rows], "doc_id long, source string, text string")
    got = mixing.mix_digest(d).collect()
    _check_mix(got, rows, lambda s, t: 10)
    assert {r.taken for r in got if r.doc_id < 100} == {30}  # capped at three times its size


def test_mix_edge_cases_and_texts(spark):
    out = mixing.mix_digest(awkward(spark))
    assert out.count() == 15
    texts = mixing.mixed_texts(awkward(spark))
    assert texts.columns == awkward(spark).columns
    want = sum(r.taken for r in out.collect())
    got = sum(len(r.text.split()) if r.text else 0 for r in texts.collect())
    assert got == want and {r.target for r in texts.collect()} == {"keep"}
    assert mixing.mix_digest(empty(spark)).count() == 0 and mixing.mixed_texts(empty(spark)).count() == 0


def test_split_tree_keeps_quotas_and_spreads(spark):
    counts = spark.createDataFrame([("a", 0, 400), ("b", 1, 100), (None, 3, 7), ("z", 2, 0)], "src string, nth long, n long")
    got = mixing.split_quotas(counts, 10, 3).collect()
    by, shard = collections.Counter(), collections.Counter()
    for r in got:
        by[r.src] += r.quota
        shard[r.shard] += r.quota
    assert by == {"a": 400, "b": 100, None: 7, "z": 0}
    assert len(shard) == 10 and max(shard.values()) - min(shard.values()) <= 4
    assert 2 <= np.std([r.quota for r in got if r.src == "b"])


def test_hypergeometric_law(spark):
    u = spark.range(4000).select(((F.col("id") + 0.5) / 4000).alias("u"))
    k = u.select(mixing.hypergeometric(F.lit(50).cast("long"), F.lit(20).cast("long"), F.lit(10).cast("long"), F.col("u")).alias("k"))
    got = {r.k: r["count"] / 4000 for r in k.groupBy("k").count().collect()}
    for x in range(11):
        p = math.comb(20, x) * math.comb(30, 10 - x) / math.comb(50, 10)
        assert abs(got.get(x, 0) - p) < 1e-3
    edge = u.limit(1).select(*(mixing.hypergeometric(*(F.lit(v).cast("long") for v in a), F.col("u")) for a in ((5, 5, 3), (5, 0, 3), (5, 3, 0), (0, 0, 0), (5, 3, 5)))).first()
    assert list(edge) == [3, 0, 0, 0, 3]


def test_pipeline_stages(spark, sf):
    docs = table(spark, sf, "documents")
    kept = corpus_pipeline.quality_stage(spark, docs, sf)
    labels = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    ids = {r.doc_id for r in kept.select("doc_id").collect()}
    known = [d for d in labels if labels[d] is not None]
    assert sum((d in ids) == bool(labels[d]) for d in known) / len(known) > 0.95
    model = quality.fit_quality(docs, table(spark, sf, "labels"))
    assert ids == {r.doc_id for r in docs.collect() if model.scores([(r.text or "").encode()])[0] >= quality.CUTOFF}
    one = corpus_pipeline.near_duplicate_stage(spark, kept, sf)
    rows = [(r.doc_id, r.text) for r in kept.select("doc_id", "text").collect()]
    assert {r.doc_id for r in one.select("doc_id").collect()} == {c for c, _ in brute_classes(rows).values()}
    clean = corpus_pipeline.decontamination_stage(spark, one, sf)
    windows = set()
    for r in table(spark, sf, "benchmark").collect():
        w = words(r.text)
        windows |= {tuple(w[i : i + 10]) for i in range(max(1, len(w) - 9))} if w else set()

    def dirty(text):
        w = words(text)
        return any(tuple(w[i : i + m]) in windows for m in {len(x) for x in windows} for i in range(len(w) - m + 1))

    assert {r.doc_id for r in clean.collect()} == {r.doc_id for r in one.collect() if not dirty(r.text)}
    mixed = corpus_pipeline.mixing_stage(spark, clean, sf)
    assert mixed.columns == docs.columns and mixed.count() > 0
    own = [(r.doc_id, r.source, r.n) for r in clean.select("doc_id", "source", mixing.word_count(F.col("text")).alias("n")).collect()]
    copies = collections.Counter(r.doc_id for r in mixed.select("doc_id").collect())
    digest = {r.doc_id: r for r in mixing.mix_digest(clean).collect()}
    assert max(copies.values()) <= 3 and all(copies[i] * n == digest[i].taken for i, _, n in own)
    _check_mix(list(digest.values()), own, lambda s, t: 0.12 * t)
    sharded = corpus_pipeline.sharding_stage(spark, mixed, sf)
    rows = sharded.select("doc_id", "shard", "slot", sharding.text_size(F.col("text")).alias("size")).toPandas()
    bytes_of = rows.groupby("shard")["size"].sum().reindex(range(16), fill_value=0)
    assert (bytes_of - bytes_of.sum() / 16).abs().max() <= rows["size"].max()
    assert all(sorted(g["slot"]) == list(range(len(g))) for _, g in rows.groupby("shard"))
    assert collections.Counter(rows["doc_id"]) == copies
    assert sharded.count() == mixed.count() and {"shard", "slot"} <= set(sharded.columns)
    assert corpus_pipeline.run(spark, sf).count() == mixed.count()


def test_pipeline_survives_awkward_rows(spark, sf):
    docs = awkward(spark).select("doc_id", "text", "lang", "source", "n_chars")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() >= 0
    docs = empty(spark).select("doc_id", "text", "lang", "source", "n_chars")
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
    assert docs.count() == 0


def test_mix_targets_of_small_sources(spark, sf):
    d = table(spark, sf, "documents")
    rows = [(r.doc_id, r.source, r.n) for r in d.select("doc_id", "source", mixing.word_count(F.col("text")).alias("n")).collect()]
    _check_mix(mixing.mix_digest(d).collect(), rows, lambda s, t: 0.03 * t)


def test_mix_of_many_sources(spark):
    """More sources than one chain of draws holds: quotas add up, weights follow the order, targets are met."""
    names = [f"s{k:04d}" for k in range(700)]
    rows = [(k, names[k % 700], 3 + k % 5) for k in range(2100)]
    d = spark.createDataFrame([(i, s, " ".join(["w"] * n)) for i, s, n in rows], "doc_id long, source string, text string")
    got = mixing.mix_digest(d).collect()
    _check_mix(got, rows, lambda s, t: 5)
    quotas = mixing.split_quotas(spark.createDataFrame([(s, k, 1 + k % 3) for k, s in enumerate(names)], "src string, nth long, n long"), 5, 1).collect()
    by, shard = collections.Counter(), collections.Counter()
    for q in quotas:
        assert q.quota >= 0
        by[q.src] += q.quota
        shard[q.shard] += q.quota
    assert by == {s: 1 + k % 3 for k, s in enumerate(names)} and max(shard.values()) - min(shard.values()) <= 4


def test_mix_of_repeated_rows(spark):
    """A source of equal rows comes near its target."""
    rows = [(1, "a", 7)] * 40 + [(2, "a", 4)] * 3 + [(3, "a", 9), (4, "a", 1), (5, "b", 100), (None, "b", 2), (None, "b", 5), (None, None, 3)]
    d = spark.createDataFrame([(i, s, " ".join(["w"] * n)) for i, s, n in rows], "doc_id long, source string, text string")
    got = mixing.mix_digest(d).collect()
    assert len(got) == len(rows)
    want, taken = _brute_targets({"a": 302, "b": 107, None: 3}), collections.Counter()
    for r in got:
        assert r.taken % r.size == 0 and r.taken <= 3 * r.size
        taken[r.target] += r.taken
    for s in want:
        assert abs(taken[want[s]] - want[s]) <= max(9, 0.35 * want[s])
