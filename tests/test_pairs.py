import re

import numpy as np
import pytest
from conftest import SF

from pairlens.functions import checks as C
from pairlens.functions import kernels as K
from pairlens.operators import baselines, dedup, review, scores, sieve, workloads
from pairlens.plans import pair_queries, relational_queries
from pairlens.sources import mappings, tables

PAIR = "pair_id long, split string, lang string, origin string, seq long, reference string, summary string"


def pairs(spark, rows):
    return spark.createDataFrame([(i, s, "en", "o", i, r, t) for i, s, r, t in rows], PAIR)


def test_duplicate_classes(spark):
    rows = [(1, "A", "x"), (2, "A", "x"), (3, "A", "y"), (4, "B", "x"), (5, "C", "z"), (6, "A", "z"), (7, "B", "y"), (8, "D", "w")]
    p = pairs(spark, [(i, "train", r, s) for i, r, s in rows])
    got = {r.pair_id: r.verdict for r in dedup.additive(p).collect()}
    assert got == {1: "valid", 2: "exact", 3: "dup_reference", 4: "dup_summary", 5: "valid", 6: "cross_both", 7: "valid", 8: "valid"}
    kept = lambda s: sorted(r.pair_id for r in dedup.keep(p, s).collect())
    assert kept("first_occurrence") == [1, 5, 8] and kept("exact") == [1, 3, 4, 5, 6, 7, 8] and kept("drop_all") == [8]


def test_null_texts_and_repeated_places(spark):
    """Null sides end, are kept by no strategy and block nothing; equal seq values don't multiply rows."""
    rows = [(1, "train", "A", "x"), (2, "train", None, "x"), (3, "train", "A", None), (4, "test", None, None), (5, "train", "B", "y"), (6, "train", "B", "y")]
    p = spark.createDataFrame([(i, s, "en", "o", 7, r, t) for i, s, r, t in rows], PAIR)
    for scope in ("corpus", "split"):
        got = sorted((r.pair_id, r.verdict) for r in dedup.additive(p, scope=scope).collect())
        assert got == [(1, "valid"), (2, "missing"), (3, "missing"), (4, "missing"), (5, "valid"), (6, "exact")]
        for s, kept in (("additive", [1, 5]), ("first_occurrence", [1, 5]), ("exact", [1, 5]), ("drop_all", [1]), ("keep_longest", [1, 5])):
            assert sorted(r.pair_id for r in dedup.keep(p, s, scope=scope).collect()) == kept, s


def test_a_long_chain_ends_in_few_rounds(spark, monkeypatch):
    """A1-x1, A1-x2, A2-x2, ...: rounds alone would take half its length; every second pair stays."""
    n, calls = 10_000, []
    real = dedup.checkpointed
    monkeypatch.setattr(dedup, "checkpointed", lambda df: calls.append(1) or real(df))
    p = spark.range(n).selectExpr("id as pair_id", "'train' as split", "'en' as lang", "'o' as origin", "id as seq", "concat('A', id div 2) as reference", "concat('x', (id + 1) div 2) as summary")
    got = {r.pair_id: r.verdict for r in dedup.additive(p).collect()}
    assert len(got) == n and all((v == "valid") == (i % 2 == 0) for i, v in got.items()) and len(calls) < 60


def test_small_splits_are_spared(spark):
    p = pairs(spark, [(1, "train", "A", "x"), (2, "test", "A", "y")])
    assert [r.pair_id for r in dedup.keep(p).collect()] == [2]
    assert [r.pair_id for r in dedup.keep(p, split_order=("train", "validation", "test")).collect()] == [1]
    assert dedup.keep(p, scope="split").count() == 2


def test_additive_equals_the_sequential_pass(spark):
    import random

    r = random.Random(4)
    rows = [(i, r.choice(["train", "test", "validation"]), f"r{r.randint(0, 60)}", f"s{r.randint(0, 60)}") for i in range(300)]
    order, refs, summs, kept = {"test": 0, "validation": 1, "train": 2}, set(), set(), set()
    for i, s, a, b in sorted(rows, key=lambda x: (order[x[1]], x[0])):
        if a not in refs and b not in summs:
            kept.add(i)
            refs.add(a)
            summs.add(b)
    assert {x.pair_id for x in dedup.keep(pairs(spark, rows)).collect()} == kept


def test_ratio_borders(spark):
    rows = [(1, "train", "r" * 125, "s" * 100), (2, "train", "r" * 124, "s" * 100), (3, "train", "r" * 100, "r" * 100), (4, "train", None, "x"), (5, "train", "r" * 60, "s" * 19), (6, "train", "r" * 49, "s" * 20), (7, "train", "ab%_c" * 30, "ab%_c" * 10)]
    got = {r.pair_id: r.verdict for r in sieve.Sieve(dedup=None).label(pairs(spark, rows)).collect()}
    assert got == {1: "valid", 2: "low_cr", 3: "identical", 4: "empty", 5: "summ_short", 6: "ref_short", 7: "extractive"}
    with pytest.raises(ValueError):
        C.low_compression(C.F.lit("a"), C.F.lit("b"), 0.9)


def test_expected_first_fail_counts(spark):
    d = "/root/testdata/sf0.01"
    count = lambda n: {r.verdict: r.n for r in sieve.Sieve().label(mappings.MAPPINGS[n](spark, d)).groupBy("verdict").agg(C.F.count("*").alias("n")).collect()}
    assert count("headline_body") == {"empty": 69, "ref_short": 13, "summ_short": 66, "low_cr": 71, "extractive": 69, "exact": 46, "dup_reference": 2, "dup_summary": 140, "valid": 524}
    assert count("mixed_news") == {"empty": 36, "ref_short": 11, "summ_short": 67, "identical": 28, "low_cr": 42, "extractive": 469, "exact": 10, "cross_both": 1, "dup_reference": 1, "dup_summary": 59, "valid": 276}


def test_kernels():
    assert [K.stem_de(w) for w in ("speicherbehältern", "grenzpostens", "ausgefeiltere", "kinder")] == ["speicherbehal", "grenzpo", "ausgefeil", "kind"]
    assert [K.stem_de(w, True) for w in ("Speicherbehältern", "Grenzpostens", "Ausgefeiltere")] == ["speicherbehalt", "grenzpost", "ausgefeilt"]
    a, b = "der hund schläft im haus".split(), "der hund liegt im garten".split()
    assert [round(x, 6) for x in (K.rouge_n(a, b, 1)[2], K.rouge_n(a, b, 2)[2], K.rouge_l(a, b)[2])] == [0.6, 0.25, 0.6]
    assert K.rouge_n(a, a, 2)[2] == K.rouge_l(a, a)[2] == 1.0 and K.rouge_n([], b, 1)[2] == 0.0 and K.rouge_l(a[::-1], a)[2] < K.rouge_n(a[::-1], a, 1)[2] == 1.0
    assert K.rouge_lsum([a, b], [b])[1] == 1.0
    assert K.loop_length("a b c a b c a b c".split()) == 3.0 and K.block_repeats("a b c a b c d".split()) == ["a", "b", "c", "a", "b", "d"]
    assert K.fragments("a b c d".split(), "b c x a".split()) == (0.75, 5 / 4)
    s = ["the cat sat", "the cat sat on", "dogs run far", "the cat sat here"]
    assert 2 not in K.central_places(s, 3) and K.central_places(s[:2], 3) == [0, 1] and K.oracle_places(s, "dogs run far", 2) == [2]


def test_lcs_equals_the_table():
    import random

    r = random.Random(1)
    for _ in range(100):
        a, b = ([r.choice("abcd") for _ in range(r.randint(0, 30))] for _ in range(2))
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        assert K.lcs_length(a, b) == t[-1][-1] == len(K.lcs_places(a, b))


def test_filtering_takes_the_copying_systems_lead(spark):
    """Scores of systems that copy the start collapse on the filtered split, those of an abstractive one don't."""
    e = {(r.system, r.split): r for r in scores.filter_effect(workloads.before_after(spark, "/root/testdata/sf0.01")).collect()}
    assert e["lead_3", "validation"].drop > 20 and e["lead_3", "validation"].kept < 0.4
    assert abs(e["target_noiser", "validation"].drop) < 5
    rank = {(r.system, r.split): r for r in scores.rank_shift(workloads.before_after(spark, "/root/testdata/sf0.01")).collect()}
    assert rank["target_noiser", "test"].rank_filtered == 1


def test_bootstrap_is_the_same_at_any_partitioning(spark):
    df = spark.createDataFrame([(i, (i * 37 % 101) / 101) for i in range(400)], "pair_id long, r1 double").withColumn("system", C.F.lit("x"))
    a, b = (scores.bootstrap(df.repartition(n), "r1", ["system"], n=300).first() for n in (1, 5))
    assert [round(x, 5) for x in a[1:]] == [round(x, 5) for x in b[1:]] and a.low < a.mid < a.high and abs(a.mid - 0.495) < 0.02


def test_no_python_in_the_sieve_plan(spark):
    plan = sieve.Sieve(dedup=None).label(mappings.headline_body(spark, SF))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan
    assert not re.search("Window", dedup.prints(mappings.headline_body(spark, SF))._jdf.queryExecution().executedPlan().toString())


def test_round_trips(spark, tmp_path):
    p = mappings.headline_body(spark, SF)
    p.write.json(f"{tmp_path}/j")
    assert tables.read_pairs(spark, f"{tmp_path}/j").drop("_corrupt_record").exceptAll(p).count() == 0
    tables.write_labelled(sieve.Sieve(dedup=None).label(p), f"{tmp_path}/l")
    assert spark.read.parquet(f"{tmp_path}/l").count() == p.count()
    assert tables.read_bytes(spark, f"{tmp_path}/j/*.json").where("valid").count() > 0
    tables.register(spark, p)
    assert {tuple(r) for r in spark.sql("SELECT pair_id, sieve_verdict(reference, summary) FROM pairs").collect()} == {tuple(r) for r in sieve.Sieve(dedup=None).label(p).select("pair_id", "verdict").collect()}


def test_every_oracle_belongs_to_a_query():
    assert set(pair_queries.O) <= set(pair_queries.Q) and set(relational_queries.O) <= set(relational_queries.Q)


def test_review_of_nothing(spark):
    none = pairs(spark, [])
    assert review.violin(sieve.Sieve().label(none)).count() == 0 and baselines.lead(none).count() == 0


@pytest.mark.parametrize("name", ["central_hashed", "central_tfidf", "central_overlap", "central_threshold", "oracle_extract"])
def test_baselines_cover_every_pair(spark, name):
    got = [r.pair_id for r in pair_queries.Q[name](spark, SF).collect()]
    assert sorted(got) == sorted(r.pair_id for r in mappings.headline_body(spark, SF).collect())


def test_edits_of_whole_texts(spark):
    def edits(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    p = {r.pair_id: r for r in mappings.headline_body(spark, SF).collect()}
    got = {r.pair_id: r.edits for r in pair_queries.Q["copy_edits"](spark, SF).collect()}
    assert set(got) == set(p)
    for i in sorted(p, key=lambda k: len(p[k].reference) * len(p[k].summary))[:: max(1, len(p) // 12)][:12]:
        assert got[i] == edits(p[i].reference, p[i].summary)


def test_fault_runs_over_block_edges(spark):
    import random

    r = random.Random(6)
    rows = [(i, "valid" if r.random() < 0.4 else "low_cr") for i in range(0, 400) if i // 10 != 7 and r.random() < 0.8]
    exp, held = [], []
    for i, v in [*rows, (-1, "valid")]:
        if v != "valid":
            held.append(i)
        else:
            exp += [(held[0], held[-1], len(held))] if len(held) >= 2 else []
            held = []
    df = spark.createDataFrame(rows, "seq long, verdict string")
    for block in (3, 10, 1000):
        assert sorted(tuple(x) for x in dedup.runs_of_faults(df, block=block).collect()) == exp


@pytest.mark.parametrize("rows", [50_000, 60])
def test_redrawn_samples_have_the_spread_of_the_mean(spark, monkeypatch, rows):
    """Blocks of 60 rows or one block: the interval is that of the mean, and doesn't depend on the partitions."""
    monkeypatch.setattr(scores, "BLOCK_ROWS", rows)
    df = spark.range(600).selectExpr("'s' as system", "id as pair_id", "case when id % 7 = 0 then null else (id * 37 % 100) / 100.0 end as r1")
    got = scores.bootstrap_draws(df, "r1", ["system"], n=1000).collect()[0]
    v = [x.r1 for x in df.where("r1 is not null").collect()]
    v = [float(x) for x in v]
    mean = sum(v) / len(v)
    half = 1.96 * (sum((x - mean) ** 2 for x in v) / len(v) / len(v)) ** 0.5
    assert abs(got.mid - mean) < 0.2 * half and abs(got.high - got.low - 2 * half) < 0.25 * half
    assert scores.bootstrap_draws(df.repartition(7), "r1", ["system"], n=1000).collect()[0] == got


def test_habits_and_gaps(spark):
    meta = spark.createDataFrame([("a", True, True, True, ["rouge1"]), ("b", True, False, False, ["rouge1", "factuality"]), ("c", False, True, False, ["BLEU"])], "system string, published boolean, public boolean, reports_baseline boolean, metrics array<string>")
    got = {r.published: tuple(r)[1:] for r in scores.evaluation_audit(meta).collect()}
    assert got == {True: (2, 1, 1, 0), False: (1, 0, 0, 0)}
    side = lambda rows: spark.createDataFrame(rows, "system string, r1 double")
    gaps = {r.system: (r.gap, r.within) for r in scores.reproduction_gap(side([("a", 30.0), ("b", 20.0)]), side([("a", 29.6), ("b", 23.0)]), ["system"]).collect()}
    assert gaps == {"a": (0.4, True), "b": (-3.0, False)}


def test_degrees_without_pairs_as_rows(spark):
    """A thousand vectors in a group, some of them copies: no operator makes a row for each pair."""
    r = np.random.default_rng(3)
    v = r.standard_normal((1000, 8)).astype(np.float32)
    v[:300] = v[0]
    df = spark.createDataFrame([(i, 1, x) for i, x in enumerate(v.tolist())], "vec_id long, label int, embedding array<float>")
    got = baselines.vector_degree(df, threshold=0.3)
    w = v.astype(float)
    near = sum(np.outer(w[:, k], w[:, k]) for k in range(8)).round(6) >= 0.3
    np.fill_diagonal(near, False)
    assert {x.vec_id: x.degree for x in got.collect()} == dict(enumerate(near.sum(1).tolist()))
    made = re.findall(r"number of output rows: ([\d,]+)", _metrics(got))
    assert made and max(int(x.replace(",", "")) for x in made) < 20_000


def _metrics(df):
    """Row counts of the plan's operators after collect()."""
    out, todo = [], [df._jdf.queryExecution().executedPlan()]
    while todo:
        p = todo.pop()
        name = p.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(p.executedPlan())
        elif name.endswith("QueryStageExec"):
            todo.append(p.plan())
        else:
            todo += [p.children().apply(i) for i in range(p.children().length())]
        if p.metrics().contains("numOutputRows"):
            out.append(f"number of output rows: {p.metrics().apply('numOutputRows').value()}")
    return "\n".join(out)


def test_degrees_of_odd_rows(spark):
    """Keys twice in a group or in two groups, nulls, other lengths, products at the border of rounding, NaN."""
    nan, inf = float("nan"), float("inf")
    rows = [
        (1, 1, [1.0, 0.0]), (1, 1, [0.5, 0.5]), (1, 2, [1.0, 0.0]), (2, 1, [0.5, 0.0]), (None, 1, [1.0, 0.0]), (3, None, [1.0, 0.0]), (4, 1, None), (5, 1, [1.0, None]), (6, 1, [1.0]),
        (7, 1, []), (8, 2, [0.0999995, 0.0]), (9, 2, [0.0999994, 9.0]), (10, 2, [0.0999996, -1.0]), (11, 3, [nan, 1.0]), (12, 3, [1.0, 0.0]), (13, 4, [1e300, 1e300]), (14, 4, [1e300, -1e300]), (15, 4, [inf, 1.0]), (16, 4, [-inf, 1.0]),
    ]
    df = spark.createDataFrame([(k, g, v) for k, g, v in rows], "vec_id long, label int, embedding array<double>")
    dot = C.F.aggregate(C.F.zip_with("u", "v", lambda p, q: p * q), C.F.lit(0.0), lambda s, x: s + x)
    for t in (0.1, 0.3, -0.2):
        a = df.selectExpr("row_number() over (order by vec_id, label, size(embedding), embedding) as i", "vec_id", "label", "embedding as u")
        b = df.selectExpr("vec_id as y", "label as h", "embedding as v")
        near = a.join(b, (a.label == b.h) & (a.vec_id != b.y)).where(C.F.round(dot, 6) >= t).groupBy("i").count()
        exp = a.join(near, "i", "left").selectExpr("vec_id", "label", "coalesce(count, 0) as degree")
        assert sorted(map(repr, baselines.vector_degree(df, threshold=t).collect())) == sorted(map(repr, exp.collect())), t


def test_near_counts_at_the_border():
    """Products a hair from the border, as halves of the sixth digit: decided as sums in order, in blocks of any size."""
    r = np.random.default_rng(8)
    a = r.standard_normal((70, 16)).astype(np.float32)
    t = float(np.round(a[3].astype(float) @ a[5].astype(float), 6))
    a[7] = a[5] * np.float32(1 - 1e-7)
    n = r.integers(1, 4, 70)
    w = sum(np.outer(a[:, k].astype(float), a[:, k].astype(float)) for k in range(16))
    for least in (t, t + 1e-6, t - 1e-6, 0.0):
        exp = np.array([sum(int(m) for x, m in zip(row, n) if round(x, 6) >= least) for row in w.tolist()])
        for rows, columns in ((240, 2048), (7, 11)):
            got = K.near_counts(a, n, a, n, least, rows, columns)
            assert (got[0] == exp).all() and (got[1] == exp).all()


def test_vectors_at_a_higher_cosine_meet_in_cells(spark):
    """central_vectors: degrees as over all pairs, and no join whose condition is a product."""
    df = pair_queries.Q["central_vectors"](spark, SF)
    assert not any("Join" in x and "aggregate(" in x for x in df._jdf.queryExecution().optimizedPlan().toString().splitlines())
    rows = spark.read.parquet(f"{SF}/embeddings.parquet").collect()
    v, label = np.array([x.embedding for x in rows], float), np.array([x.label for x in rows])
    near = (sum(np.outer(v[:, k], v[:, k]) for k in range(v.shape[1])).round(6) >= 0.3) & (label[:, None] == label)
    np.fill_diagonal(near, False)
    assert {x.vec_id: x.degree for x in df.collect()} == {x.vec_id: n for x, n in zip(rows, near.sum(1).tolist(), strict=True)}


def test_habits_are_read_from_the_documents(spark):
    """The audit has a record for each document."""
    df = pair_queries.Q["evaluation_audit"](spark, SF)
    assert {x.rsplit("/", 1)[1] for x in df.inputFiles()} == {"documents.parquet"}
    p = sieve.Sieve(dedup=None).label_rows(mappings.headline_body(spark, SF)).collect()
    exp = {}
    for x in p:
        e = exp.setdefault(x.split != "train", [0, 0, 0, 0])
        parts = [y for y in re.sub(r"([.!?])[ \t]+", "\\1\n", x.reference).split("\n") if y.strip(" \t")]
        beyond = bool(re.search("[0-9]", x.summary or ""))
        for i, yes in enumerate((True, len(parts) > 3, beyond, beyond and x.verdict == "valid")):
            e[i] += yes
    assert {x.published: list(x)[1:] for x in df.collect()} == exp


def test_records_of_odd_documents(spark, tmp_path):
    rows = [(9, None), (8, ""), (19, "Sum of 3.\n" + "A b c. " * 20), (1, "word\nbody")]
    spark.createDataFrame([(i, t, "en", "o", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.system: tuple(r)[1:] for r in workloads.reports(spark, str(tmp_path)).collect()}
    assert got == {"9": (True, False, False, []), "8": (True, False, False, []), "19": (True, False, True, ["rouge1", "rouge2", "rougeL", "factuality"]), "1": (False, False, False, ["rouge1", "rougeL"])}
    assert {r.published: tuple(r)[1:] for r in workloads.habits(spark, str(tmp_path)).collect()} == {True: (3, 1, 1, 0), False: (1, 0, 0, 0)}


def test_the_grid_meets_the_documents(spark):
    """Pairs that pass each setting of the range, counted from the table; without pairs each setting has none."""
    df = pair_queries.Q["threshold_grid"](spark, SF)
    assert {x.rsplit("/", 1)[1] for x in df.inputFiles()} == {"documents.parquet"}
    p = [(len(x.reference), len(x.summary)) for x in mappings.headline_body(spark, SF).collect() if x.summary is not None]
    exp = {(cr, n): sum(r >= n and r >= s * cr for r, s in p) for cr in (1.0, 1.25, 1.5, 1.75) for n in (20, 35, 50)}
    assert {(x.min_cr, x.min_ref): x.passing for x in df.collect()} == exp
    assert [x.passing for x in sieve.passing(pairs(spark, []), sieve.grid(spark)).collect()] == [0] * 12
    odd = pairs(spark, [(1, "train", None, "x"), (2, "train", "r" * 35, "s" * 20), (3, "test", "r" * 50, None)])
    assert {(x.min_cr, x.min_ref) for x in sieve.passing(odd, sieve.grid(spark)).collect() if x.passing} == {(c, n) for c in (1.0, 1.25, 1.5, 1.75) for n in (20, 35)}


def test_vectors_that_share_a_hash(spark, monkeypatch):
    """Vectors find their counts by hash; those whose hash isn't their own also by their numbers."""
    monkeypatch.setattr(baselines, "vector_hash", lambda u: C.F.pmod(C.F.xxhash64(u), C.F.lit(5)))
    r = np.random.default_rng(4)
    v = np.round(r.standard_normal((60, 3)), 1).astype(np.float32)
    v[40:] = v[:20]
    v[0, 0], v[40, 0] = 0.0, -0.0
    label, ids = np.arange(60) % 2, np.arange(60)
    ids[58] = ids[56]  # a key twice in its group
    df = spark.createDataFrame([(int(i), int(g), x) for i, g, x in zip(ids, label, v.tolist(), strict=True)], "vec_id long, label int, embedding array<float>")
    near = (sum(np.outer(v[:, k].astype(float), v[:, k].astype(float)) for k in range(3)).round(6) >= 0.3) & (label[:, None] == label) & (ids[:, None] != ids)
    got = sorted((x.vec_id, x.label, x.degree) for x in baselines.vector_degree(df, threshold=0.3).collect())
    assert got == sorted(zip(ids.tolist(), label.tolist(), near.sum(1).tolist(), strict=True))


def test_counts_travel_without_their_vectors(spark):
    """central_vectors: counts go back to the rows by hash; no join has vectors as keys."""
    df = pair_queries.Q["central_vectors"](spark, SF)
    df.collect()
    keys = re.findall(r"(?:SortMergeJoin|BroadcastHashJoin|ShuffledHashJoin) \[([^\]]*)\], \[([^\]]*)\]", df._jdf.queryExecution().executedPlan().toString())
    assert keys and not any(re.search(r"\bu#", side) for join in keys for side in join)


def test_near_counts_within_halves():
    r = np.random.default_rng(9)
    a, n = r.standard_normal((97, 8)).astype(np.float32), r.integers(1, 3, 97)
    a[50:60] = a[:10]
    exp = K.near_counts(a, n, a, n, 0.3)[0]
    for small in (1, 5, 48, 97):
        assert (K.near_counts_within(a, n, 0.3, small) == exp).all()


def test_open_products_in_any_number():
    """Blocks whose products are all open (huge numbers, NaN) and blocks that end inside a word."""
    r = np.random.default_rng(10)
    a, b = np.round(r.standard_normal((300, 4)), 1), np.round(r.standard_normal((301, 4)), 1)
    a[7], b[9, 1], a[8] = 1e200, float("nan"), 1e-200
    w = sum(np.outer(a[:, k], b[:, k]) for k in range(4))
    one = (np.ones(300, np.int64), np.ones(301, np.int64))
    for t in (0.25, 0.0):
        near = (w.round(6) >= t) | np.isnan(w)
        for size in ((240, 2040), (255, 13)):
            got = K.near_counts(a, one[0], b, one[1], t, *size)
            assert (got[0] == near.sum(1)).all() and (got[1] == near.sum(0)).all()
