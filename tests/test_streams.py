from conftest import SF

from pairlens.operators import dedup
from pairlens.operators.sieve import Sieve
from pairlens.session import load
from pairlens.sources.mappings import headline_body
from pairlens.streaming import streams


def test_stream_labels_equal_batch(spark, tmp_path):
    p = headline_body(spark, SF)
    p.repartition(3).write.parquet(f"{tmp_path}/in")
    out = streams.run_to_end(streams.label_stream(streams.stream_table(spark, f"{tmp_path}/in", p)), "labelled", f"{tmp_path}/c")
    assert {(r.pair_id, r.verdict) for r in out.collect()} == {(r.pair_id, r.verdict) for r in Sieve(dedup=None).label(p).collect()}


def test_additive_stream_equals_batch(spark, tmp_path):
    p = headline_body(spark, SF).withColumn("split", streams.F.lit("train")).orderBy("seq")
    n = p.count()
    for i in range(3):
        p.where(streams.F.col("seq").between(i * n // 3, (i + 1) * n // 3 - 1)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    streams.additive_stream(streams.stream_table(spark, f"{tmp_path}/in", p), f"{tmp_path}/out", f"{tmp_path}/c").awaitTermination()
    assert {r.pair_id for r in spark.read.parquet(f"{tmp_path}/out/kept").collect()} == {r.pair_id for r in dedup.keep(p).collect()}


def test_windows_sessions_joins_and_state(spark, tmp_path):
    e = load(spark, SF, "events")
    e.coalesce(1).write.parquet(f"{tmp_path}/in")
    s = lambda: streams.stream_table(spark, f"{tmp_path}/in", e)
    counts = streams.run_to_end(streams.windowed_counts(s()), "w", f"{tmp_path}/c1", "complete")
    assert counts.agg({"n": "sum"}).first()[0] == e.count()
    assert streams.run_to_end(streams.repeat_counts(s()), "r", f"{tmp_path}/c2", "update").agg({"n": "sum"}).first()[0] == e.count()
    got = streams.run_to_end(streams.bought_after_view(s()), "j", f"{tmp_path}/c3").count()
    assert got == streams.bought_after_view(e).count()
    assert streams.run_to_end(streams.sessions(s()), "s", f"{tmp_path}/c4").count() <= e.count()
