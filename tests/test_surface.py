import json
import random

import numpy as np
from conftest import SF
from pyspark.sql import functions as F

from pairlens.functions import kernels as K
from pairlens.operators import baselines, scores, sieve
from pairlens.session import load
from pairlens.sources import pair_source, tables
from pairlens.sources.mappings import headline_body
from pairlens.streaming import streams


def test_common_substring_equals_brute_force():
    rng = random.Random(3)
    assert K.substring_length("", "abc") == 0 and K.substring_length("äbc", "xäby") == 2
    for _ in range(400):
        a, b = ("".join(rng.choice("abä") for _ in range(rng.randrange(14))) for _ in range(2))
        want = max((j - i for i in range(len(a)) for j in range(i, len(a) + 1) if a[i:j] in b), default=0)
        assert K.substring_length(a, b) == want, (a, b)


def test_similarity_of_null_texts_is_null(spark):
    from pairlens.functions.udfs import char_lcs_length, substring_length

    df = spark.createDataFrame([("abc", None), (None, "x"), ("", ""), ("abc", "axc")], "a string, b string")
    got = [tuple(r) for r in df.select(substring_length("a", "b"), char_lcs_length("a", "b")).collect()]
    assert got == [(None, None), (None, None), (0, 0), (1, 2)]


def test_hashed_vectors_count_every_gram():
    s = ["", "ab", "abcabc", "Abcabc", "another sentence", "abcabc another"]
    v = K.hashed_vectors(s)
    assert np.allclose(np.linalg.norm(v, axis=1), [0, 0, 1, 1, 1, 1]) and np.allclose(v[2], v[3])
    assert np.allclose(v[4], K.hashed_vectors([s[4]])[0])  # no gram spans two sentences
    assert v[2] @ v[5] > v[2] @ v[4]


def test_parameters_of_the_baselines(spark):
    p = headline_body(spark, SF)
    ratio = baselines.mean_ratio(p)
    k = {r: [x.k for x in baselines.with_k(p, ratio, r).orderBy("pair_id").collect()] for r in ("down", "half_up", "up")}
    assert all(a <= b <= c for a, b, c in zip(k["down"], k["half_up"], k["up"], strict=True)) and k["down"] != k["up"]
    first = lambda texts: np.eye(len(texts)) * 0 + (np.arange(len(texts)) < 2)[:, None]
    texts = ["one here", "two there", "three", "four"]
    assert K.central_places(texts, 2, encoder=first, damping=0.5) == [0, 1]
    assert sorted(K.central_places(texts, 4, order="rank")) == [0, 1, 2, 3]
    assert baselines.central(p.limit(20), ratio, order="rank", damping=0.5).count() == 20


def test_grams_matched_in_rows_and_by_join_agree(spark):
    rows = [(1, "a b a b a", "a b a"), (2, None, "a b"), (3, "", ""), (4, "a", "a b"), (5, "x y z", "a b c"), (6, "a b", None)]
    p = spark.createDataFrame(rows, "pair_id long, o string, t string").unionByName(headline_body(spark, SF).selectExpr("pair_id + 100 pair_id", "reference o", "summary t"))
    for n in (1, 2):
        got = lambda c: sorted(map(tuple, scores.relational_rouge(p, "o", "t", n, row_chars=c).collect()))
        assert got(20_000) == got(-1) == got(30)
    plan = scores.relational_rouge(p, "o", "t", 2, row_chars=1 << 30)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan


def test_counts_seen_while_writing(spark, tmp_path):
    p = sieve.Sieve(dedup=None).label_rows(headline_body(spark, SF))
    rows, seen = sieve.observed(p)
    rows.write.parquet(f"{tmp_path}/x")
    want = {r.verdict: r["count"] for r in p.groupBy("verdict").count().collect()}
    assert {k: v for k, v in seen.get.items() if k != "n" and v} == want and seen.get["n"] == sum(want.values())
    t = scores.timed("lead_3", baselines.lead(headline_body(spark, SF)), 0)
    assert t["outputs"] == 200 and t["per_second"] > 0


def test_pair_source(spark, tmp_path):
    pair_source.register_pairs(spark)
    headline_body(spark, SF).repartition(3).write.json(f"{tmp_path}/in")
    got = spark.read.format(pair_source.FORMAT).load(f"{tmp_path}/in")
    cols = list(pair_source.FIELDS)
    assert sorted(map(tuple, got.select(cols).collect())) == sorted(map(tuple, headline_body(spark, SF).select(cols).collect()))
    test = spark.read.format(pair_source.FORMAT).load(f"{tmp_path}/in").where("split = 'test'")
    assert test.count() == headline_body(spark, SF).where("split = 'test'").count()
    (tmp_path / "odd").mkdir()
    assert spark.read.format(pair_source.FORMAT).load(f"{tmp_path}/odd").count() == 0
    (tmp_path / "odd" / "a.json").write_text("not json\n\n[1]\n" + json.dumps({"pair_id": 1, "reference": "r s"}) + "\n")
    rows = spark.read.format(pair_source.FORMAT).load(f"{tmp_path}/odd").collect()
    assert sorted((r.pair_id, r.reference, r.broken) for r in rows if r.pair_id) == [(1, "r s", None)]
    assert sorted(r.broken for r in rows if r.broken) == ["[1]", "not json"]


def test_sql_names(spark):
    tables.register(spark, headline_body(spark, SF), "surface")
    a = spark.sql("SELECT round(rouge_f('a b c', 'a b d'), 4) AS f, compression_ratio('abcd', 'ab') AS cr").first()
    assert (a.f, a.cr) == (0.6667, 2.0)
    assert spark.sql("SELECT count(*) FROM sentence_rows(NULL)").first()[0] == 0
    assert [tuple(r) for r in spark.sql("SELECT * FROM gram_table('A b c', 2)").collect()] == [(0, "a b"), (1, "b c")]


def test_bucketed_tables_join_without_exchange(spark):
    for t in ("pairlens_b1", "pairlens_b2"):
        tables.write_bucketed(headline_body(spark, SF), t, 4)
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        j = spark.table("pairlens_b1").join(spark.table("pairlens_b2").select("pair_id", F.col("split").alias("s2")), "pair_id")
        assert "Exchange" not in j._jdf.queryExecution().executedPlan().toString() and j.count() == 200
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        for t in ("pairlens_b1", "pairlens_b2"):
            spark.sql(f"DROP TABLE IF EXISTS {t}")


def test_a_hot_key_is_split_by_adaptive_execution(spark):
    confs = {"spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.skewJoin.skewedPartitionThresholdInBytes": "20000", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "20000", "spark.sql.adaptive.skewJoin.skewedPartitionFactor": "2", "spark.sql.shuffle.partitions": "8"}
    old = {k: spark.conf.get(k) for k in confs}
    for k, v in confs.items():
        spark.conf.set(k, v)
    try:
        hot = spark.range(0, 200_000, 1, 8).select(F.when(F.col("id") % 10 < 8, 1).otherwise(F.col("id")).alias("k"), F.md5(F.col("id").cast("string")).alias("v"))
        j = hot.join(spark.range(200_000).select(F.col("id").alias("k"), F.md5(F.col("id").cast("string")).alias("w")), "k")
        assert len(j.collect()) == 200_000
        assert "skew=true" in j._jdf.queryExecution().executedPlan().toString()
    finally:
        for k, v in old.items():
            spark.conf.set(k, v)


def test_sketches_are_near_the_truth(spark):
    t = load(spark, SF.replace("0.001", "0.01"), "lineitem")
    a = t.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("b"), F.percentile_approx("l_extendedprice", 0.5, 10000).alias("p")).first()
    e = t.agg(F.count_distinct("l_partkey").alias("n"), F.percentile("l_extendedprice", F.lit(0.5)).alias("p")).first()
    assert abs(a.a / e.n - 1) < 0.06 and abs(a.b / e.n - 1) < 0.06 and abs(float(a.p) / e.p - 1) < 0.01


def _files(spark, path, rows, like):
    spark.createDataFrame(rows, like).coalesce(1).write.mode("append").parquet(path)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    import time

    like, path = "event_id long, ts timestamp, event_type string, user_id long", f"{tmp_path}/in"
    at = lambda h, m=0: __import__("datetime").datetime(2024, 1, 1, h, m)
    for batch in ([(1, at(1), "view", 1)], [(2, at(9), "view", 1)], [(6, at(9, 10), "view", 1)], [(3, at(1, 5), "view", 1), (4, at(9, 30), "view", 1)], [(5, at(20), "view", 1)]):
        _files(spark, path, batch, like)
        time.sleep(1.1)
    s = spark.readStream.schema(like).option("maxFilesPerTrigger", 1).parquet(path)
    q = streams.run_to_files(streams.windowed_counts(s), f"{tmp_path}/out", f"{tmp_path}/c")
    assert streams.dropped_late(q) == 1
    got = {(r.start.hour, r.n) for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert (1, 1) in got and (9, 3) in got


def test_first_of_each_and_restart(spark, tmp_path):
    like, path = "event_id long, ts timestamp, summary string", f"{tmp_path}/in"
    at = lambda m: __import__("datetime").datetime(2024, 1, 1, 1, m)
    run = lambda: streams.run_to_files(streams.first_of_each(spark.readStream.schema(like).parquet(path), "ts"), f"{tmp_path}/out", f"{tmp_path}/c")
    _files(spark, path, [(1, at(0), "a"), (2, at(1), "b")], like)
    run()
    _files(spark, path, [(3, at(2), "a"), (4, at(3), "c")], like)
    run()  # the state of the first run is still there
    run()  # nothing new
    assert sorted(r.event_id for r in spark.read.parquet(f"{tmp_path}/out").collect()) == [1, 2, 4]


def test_stream_against_static_limits(spark, tmp_path):
    p = headline_body(spark, SF)
    p.write.parquet(f"{tmp_path}/in")
    limits = spark.createDataFrame([("src0", 10**9, 0), ("src1", 0, 0)], "origin string, min_ref int, min_summ int")
    out = streams.run_to_end(streams.with_limits(streams.stream_table(spark, f"{tmp_path}/in", p), limits), "limited", f"{tmp_path}/c")
    want = p.groupBy().agg(F.count_if(F.col("origin") == "src0")).first()[0]
    assert out.where("verdict = 'ref_short'").count() == want > 0 and out.count() == p.count()
