"""Queries of the checks, the sieve, review, baselines and scores, with SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlens.functions import checks as C
from pairlens.functions import text as T
from pairlens.operators import baselines as B
from pairlens.operators import dedup as U
from pairlens.operators import review as V
from pairlens.operators import scores as R
from pairlens.operators import sieve as S
from pairlens.operators import systems as Y
from pairlens.operators import workloads as W
from pairlens.session import load
from pairlens.sources.mappings import MAPPINGS

def ref():
    return F.col("reference")


def summ():
    return F.col("summary")


Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
O: dict[str, str] = {}

# SQL of the mappings and of the sieve, shared by the oracles
SPLIT = "CASE WHEN {k} % 10 = 9 THEN 'test' WHEN {k} % 10 = 8 THEN 'validation' ELSE 'train' END AS split"
M1 = f"m1 AS (SELECT doc_id AS pair_id, {SPLIT.format(k='doc_id')}, lang, source AS origin, doc_id AS seq, CASE WHEN instr(text, chr(10)) > 0 THEN substr(text, instr(text, chr(10)) + 1) ELSE '' END AS reference, split_part(text, chr(10), 1) AS summary FROM documents)"
M2 = f"m2 AS (SELECT doc_id AS pair_id, {SPLIT.format(k='doc_id')}, lang, source AS origin, doc_id AS seq, text AS reference, split_part(text, chr(10), 1) AS summary FROM documents)"
M3 = f"{M1}, {M2}, m3 AS (SELECT * FROM m2 WHERE (pair_id // 10) % 2 = 0 UNION ALL SELECT * FROM m1 WHERE (pair_id // 10) % 2 = 1)"
M5 = f"m5 AS (SELECT conv_id * 100 + turn AS pair_id, {SPLIT.format(k='conv_id')}, 'en' AS lang, 'conversations' AS origin, conv_id * 100 + turn AS seq, text AS reference, asked AS summary FROM (SELECT *, lag(role) OVER w AS before, lag(text) OVER w AS asked FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'assistant' AND before = 'user')"
MAPPED = {"headline_body": ("m1", M1), "lead_inclusive": ("m2", M2), "mixed_news": ("m3", M3), "prompt_reply": ("m5", M5)}


def row_sql(m: str, r: int = 50, s: int = 20, cr: float = 1.25) -> str:
    return f"rows_ AS (SELECT *, CASE WHEN reference IS NULL OR summary IS NULL OR length(reference) = 0 OR length(summary) = 0 THEN 'empty' WHEN length(reference) < {r} THEN 'ref_short' WHEN length(summary) < {s} THEN 'summ_short' WHEN reference = summary THEN 'identical' WHEN length(reference)::DOUBLE < length(summary) * {cr}::DOUBLE THEN 'low_cr' WHEN contains(reference, summary) THEN 'extractive' ELSE 'valid' END AS verdict FROM {m})"


ROUNDS = """ranked AS (SELECT pair_id, split, (CASE split WHEN 'test' THEN 0 WHEN 'validation' THEN 1 ELSE 2 END) * 100000000000000 + seq AS rank, md5(reference) AS fr, md5(summary) AS fs FROM {source}),
state AS (SELECT 0 AS n, pair_id, rank, fr, fs, 'open' AS st FROM ranked
  UNION ALL
  SELECT n, pair_id, rank, fr, fs, CASE WHEN st <> 'open' THEN st WHEN won THEN 'kept' WHEN bool_or(won OR st = 'kept') OVER (PARTITION BY fr) OR bool_or(won OR st = 'kept') OVER (PARTITION BY fs) THEN 'out' ELSE 'open' END
  FROM (SELECT n + 1 AS n, pair_id, rank, fr, fs, st, st = 'open' AND rank = min(CASE WHEN st = 'open' THEN rank END) OVER (PARTITION BY fr) AND rank = min(CASE WHEN st = 'open' THEN rank END) OVER (PARTITION BY fs) AS won, bool_or(st = 'open') OVER () AS more FROM state) WHERE more),
last_ AS (SELECT * FROM state WHERE n = (SELECT max(n) FROM state)),
kept AS (SELECT * FROM last_ WHERE st = 'kept'),
judged AS (SELECT l.pair_id, CASE WHEN l.st = 'kept' THEN 'valid' WHEN a.rank < l.rank AND b.rank < l.rank AND a.rank = b.rank THEN 'exact' WHEN a.rank < l.rank AND b.rank < l.rank THEN 'cross_both' WHEN a.rank < l.rank THEN 'dup_reference' ELSE 'dup_summary' END AS verdict, CASE WHEN l.st <> 'kept' AND a.rank < l.rank THEN a.pair_id END AS blocker_ref, CASE WHEN l.st <> 'kept' AND b.rank < l.rank THEN b.pair_id END AS blocker_summ FROM last_ l LEFT JOIN kept a ON a.fr = l.fr LEFT JOIN kept b ON b.fs = l.fs)"""


def label_sql(m: str, cte: str, **limits) -> str:
    return f"WITH RECURSIVE {cte}, {row_sql(m, **limits)}, passed AS (SELECT * FROM rows_ WHERE verdict = 'valid'), {ROUNDS.format(source='passed')}, labelled AS (SELECT r.* REPLACE (coalesce(j.verdict, r.verdict) AS verdict) FROM rows_ r LEFT JOIN judged j USING (pair_id))"


LABEL1, LABEL3 = label_sql("m1", M1), label_sql("m3", M3)
STATES = "states AS (SELECT *, unnest(CASE WHEN verdict = 'valid' THEN ['unfiltered', 'filtered'] ELSE ['unfiltered'] END) AS state FROM labelled)"
SENTS = r"list_filter(list_transform(string_split(regexp_replace({c}, '([.!?])[ \t]+', '\1' || chr(10), 'g'), chr(10)), lambda s: regexp_replace(s, '^[ \t]+|[ \t]+$', '', 'g')), lambda s: s <> '')"
TOKS = r"regexp_extract_all(lower({c}), '[\p{{L}}\p{{N}}]+')"
WORDS = r"list_filter(regexp_split_to_array({c}, '[\x20\x09-\x0D]+'), lambda w: w <> '')"


def sents(c: str) -> str:
    return SENTS.format(c=c)


def toks(c: str) -> str:
    return TOKS.format(c=c)


def m1(f: Callable[[DataFrame], DataFrame], name: str = "headline_body"):
    return lambda s, d: f(MAPPINGS[name](s, d))


def add(key: str, build, sql: str | None = None) -> None:
    Q[key] = build
    if sql:
        O[key] = sql


# mappings
for _n, (_t, _c) in MAPPED.items():
    add(f"pairs_{_n}", (lambda n: lambda s, d: MAPPINGS[n](s, d))(_n), f"WITH {_c} SELECT * FROM {_t}")
for _n in ("page_title_body", "dialogue_digest", "passage_host", "boilerplate_pairs"):
    add(f"pairs_{_n}", (lambda n: lambda s, d: MAPPINGS[n](s, d))(_n))
O["pairs_dialogue_digest"] = f"SELECT conv_id AS pair_id, {SPLIT.format(k='conv_id')}, 'en' AS lang, 'conversations' AS origin, conv_id AS seq, string_agg(text, chr(10) ORDER BY turn) AS reference, max_by(text, turn) FILTER (WHERE role = 'assistant') AS summary FROM conversations GROUP BY conv_id"
O["pairs_passage_host"] = f"SELECT doc_id AS pair_id, {SPLIT.format(k='doc_id')}, lang, source AS origin, doc_id * 100000 + item_id AS seq, d.text AS reference, b.text AS summary FROM documents d JOIN benchmark b ON contains(d.text, b.text)"
O["pairs_boilerplate_pairs"] = f"WITH l AS (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), n AS (SELECT line, count(*) AS n FROM l WHERE line <> '' GROUP BY line), t AS (SELECT doc_id, line FROM l JOIN n USING (line) QUALIFY row_number() OVER (PARTITION BY doc_id ORDER BY n DESC, line) = 1) SELECT doc_id AS pair_id, {SPLIT.format(k='doc_id')}, lang, source AS origin, doc_id AS seq, text AS reference, line AS summary FROM documents JOIN t USING (doc_id)"

# row-level checks
_p = f"WITH {M1} SELECT pair_id, "
add("chk_missing", m1(lambda p: p.select("pair_id", C.is_missing(ref(), summ()).alias("bad"))), _p + "length(reference) = 0 OR length(summary) = 0 AS bad FROM m1")
add("chk_blank", m1(lambda p: p.select("pair_id", C.is_blank(ref()).alias("ref_bad"), C.is_blank(summ()).alias("summ_bad"))), _p + r"regexp_full_match(reference, '[\s\x{00a0}\x{200b}\x{feff}]*') AS ref_bad, regexp_full_match(summary, '[\s\x{00a0}\x{200b}\x{feff}]*') AS summ_bad FROM m1")
add("chk_symbolic", m1(lambda p: p.select("pair_id", C.is_symbolic(ref()).alias("ref_bad"), C.is_symbolic(summ()).alias("summ_bad"))), _p + r"NOT regexp_matches(reference, '[\p{L}\p{N}]') AS ref_bad, NOT regexp_matches(summary, '[\p{L}\p{N}]') AS summ_bad FROM m1")
add("chk_encoding", m1(lambda p: p.select("pair_id", C.is_misencoded(ref()).alias("bad"))), _p + r"regexp_matches(reference, '\x{fffd}|[\x00-\x08\x0e-\x1f\x7f]|\x{00c3}[\x{0080}-\x{00bf}]') AS bad FROM m1")
add("chk_empty_levels", m1(lambda p: p.select(*(F.count_if(C.is_empty(ref(), summ(), x)).alias(x) for x in C.LEVELS))), f"""WITH {M1}, t AS (SELECT length(reference) = 0 OR length(summary) = 0 AS a, regexp_full_match(reference, '[\\s\\x{{00a0}}\\x{{200b}}\\x{{feff}}]*') OR regexp_full_match(summary, '[\\s\\x{{00a0}}\\x{{200b}}\\x{{feff}}]*') AS b, NOT regexp_matches(reference, '[\\p{{L}}\\p{{N}}]') OR NOT regexp_matches(summary, '[\\p{{L}}\\p{{N}}]') AS c, regexp_matches(reference || chr(32) || summary, '\\x{{fffd}}|[\\x00-\\x08\\x0e-\\x1f\\x7f]|\\x{{00c3}}[\\x{{0080}}-\\x{{00bf}}]') AS d FROM m1)
SELECT count(*) FILTER (WHERE a) AS missing, count(*) FILTER (WHERE a OR b) AS blank, count(*) FILTER (WHERE a OR b OR c) AS symbols, count(*) FILTER (WHERE a OR b OR c OR d) AS encoding FROM t""")
add("chk_min_len", m1(lambda p: p.select("pair_id", C.too_short(ref(), 50).alias("ref_bad"), C.too_short(summ(), 20).alias("summ_bad"))), _p + "length(reference) < 50 AS ref_bad, length(summary) < 20 AS summ_bad FROM m1")
_by = S.Sieve(by=("origin", {"src0": S.Profile.instructions()}), dedup=None)
add("chk_min_len_profiles", m1(lambda p: p.select("pair_id", _by.flags()["ref_short"].alias("ref_bad"), _by.flags()["summ_short"].alias("summ_bad"))), _p + "length(reference) < CASE origin WHEN 'src0' THEN 20 ELSE 50 END AS ref_bad, length(summary) < CASE origin WHEN 'src0' THEN 8 ELSE 20 END AS summ_bad FROM m1")
add("len_units", m1(lambda p: p.select("pair_id", *(T.n_units(ref(), u).alias(u) for u in ("char", "token", "sentence")))), _p + f"length(reference) AS char, len({WORDS.format(c='reference')}) AS token, len({sents('reference')}) AS sentence FROM m1")
add("chk_max_len", m1(lambda p: p.select("pair_id", C.too_long(ref(), 5000).alias("bad"))), _p + "length(reference) > 5000 AS bad FROM m1")
for _n, _k in (("headline_body", "cr_values"), ("prompt_reply", "cr_values_replies")):
    add(_k, m1(lambda p: p.select("pair_id", F.round(C.compression_ratio(ref(), summ()), 6).alias("cr")), _n), f"WITH {MAPPED[_n][1]} SELECT pair_id, round(length(reference)::DOUBLE / nullif(length(summary), 0), 6) AS cr FROM {MAPPED[_n][0]}")
add("chk_cr", m1(lambda p: p.select("pair_id", C.low_compression(ref(), summ()).alias("bad")), "prompt_reply"), f"WITH {M5} SELECT pair_id, length(reference)::DOUBLE < length(summary) * 1.25::DOUBLE AS bad FROM m5")
add("chk_cr_floor", m1(lambda p: p.select("pair_id", C.not_compressed(ref(), summ()).alias("bad"))), _p + "length(reference) <= length(summary) AS bad FROM m1")
add("chk_cr_max", m1(lambda p: p.select("pair_id", C.extreme_compression(ref(), summ(), 20.0).alias("bad"))), _p + "length(reference) > length(summary) * 20 AS bad FROM m1")
add("chk_identical", m1(lambda p: p.select("pair_id", C.identical(ref(), summ()).alias("bad")), "lead_inclusive"), f"WITH {M2} SELECT pair_id, reference = summary AS bad FROM m2")
add("chk_extractive", m1(lambda p: p.select("pair_id", C.fully_extractive(ref(), summ()).alias("bad")), "mixed_news"), f"WITH {M3} SELECT pair_id, contains(reference, summary) AS bad FROM m3")
add("chk_extractive_tokens", m1(lambda p: p.select("pair_id", C.fully_extractive(ref(), summ(), "token_run").alias("bad"))), _p + f"contains(' ' || array_to_string({toks('reference')}, ' ') || ' ', ' ' || array_to_string({toks('summary')}, ' ') || ' ') AS bad FROM m1")
add("chk_extractive_sents", m1(lambda p: p.select("pair_id", C.fully_extractive(ref(), summ(), "sentence_run").alias("run"), C.fully_extractive(ref(), summ(), "sentence_subset").alias("subset"))), _p + f"contains(chr(10) || array_to_string({sents('reference')}, chr(10)) || chr(10), chr(10) || array_to_string({sents('summary')}, chr(10)) || chr(10)) AS run, len(list_filter({sents('summary')}, lambda x: NOT list_contains({sents('reference')}, x))) = 0 AS subset FROM m1")
_copy = "SELECT pair_id, CASE WHEN instr(reference, summary) > 0 THEN instr(reference, summary) - 1 END AS copy_offset, CASE WHEN instr(reference, summary) > 0 THEN round((instr(reference, summary) - 1) / length(reference), 6) END AS copy_share, instr(reference, summary) = 1 AS is_prefix FROM "
add("copy_position", m1(lambda p: p.where(F.length("summary") > 0).select("pair_id", *(c.alias(n) for n, c in C.copy_position(ref(), summ()).items())), "lead_inclusive"), f"WITH {M2} {_copy} m2 WHERE length(summary) > 0")
add("copy_similarity", m1(lambda p: p.select("pair_id", F.round(C.jaccard(ref(), summ()), 6).alias("jaccard"))), _p + f"round(len(list_intersect(list_distinct({toks('reference')}), list_distinct({toks('summary')}))) / nullif(len(list_distinct(list_concat({toks('reference')}, {toks('summary')}))), 0)::DOUBLE, 6) AS jaccard FROM m1")
add("copy_edits", m1(lambda p: p.select("pair_id", F.levenshtein("reference", "summary").alias("edits"))))


def near_copy(s: SparkSession, d: str, unit: str = "token") -> DataFrame:
    """Longest common subsequence of tokens or characters over the summary's, for pairs that pass the row checks."""
    from pairlens.functions.udfs import char_lcs_length, lcs_length

    p = S.Sieve(dedup=None).label_rows(MAPPINGS["mixed_news"](s, d)).where("verdict = 'valid'")
    n, lcs = (F.size(T.tokens(summ())), lcs_length(T.tokens(ref()), T.tokens(summ()))) if unit == "token" else (F.length(summ()), char_lcs_length(ref(), summ()))
    share = F.try_divide(lcs.cast("double"), n.cast("double"))
    return p.select("pair_id", F.round(share, 6).alias("lcs_share"), (share >= 0.9).alias("near_copy"))


def common_run(s: SparkSession, d: str) -> DataFrame:
    """Longest run of characters that both sides have, over the summary's length."""
    from pairlens.functions.udfs import substring_length

    run = substring_length(ref(), summ())
    return MAPPINGS["headline_body"](s, d).select("pair_id", run.alias("run"), F.round(F.try_divide(run.cast("double"), F.length(summ()).cast("double")), 6).alias("share"))


def lcs_sql(cte: str, source: str, a: str, b: str) -> str:
    """lcs (pair_id, na, nb, hit): the table's rows one after the other, each from the one before by running maxima."""
    return f"""WITH RECURSIVE {cte}, lt AS (SELECT pair_id, {toks(a)} AS a, {toks(b)} AS b FROM {source}), la AS (SELECT pair_id, unnest(a) AS w, unnest(range(len(a))) AS i FROM lt),
    ld AS (SELECT pair_id, 0::BIGINT AS i, b, list_transform(range(len(b) + 1), lambda x: 0::BIGINT) AS r FROM lt
    UNION ALL SELECT ld.pair_id, ld.i + 1, b, list_prepend(0::BIGINT, list_transform(range(1, len(b) + 1), lambda j: list_max(list_transform(range(1, j + 1), lambda h: greatest(r[h + 1], r[h] + (b[h] = la.w)::BIGINT))))) FROM ld JOIN la ON la.pair_id = ld.pair_id AND la.i = ld.i),
    lcs AS (SELECT lt.pair_id, len(lt.a) AS na, len(lt.b) AS nb, ld.r[len(lt.b) + 1] AS hit FROM lt JOIN ld ON lt.pair_id = ld.pair_id AND ld.i = len(lt.a))"""


add("near_copy", near_copy, lcs_sql(f"{M3}, {row_sql('m3')}, passed AS (SELECT * FROM rows_ WHERE verdict = 'valid')", "passed", "reference", "summary") + " SELECT pair_id, round(hit / nullif(nb, 0)::DOUBLE, 6) AS lcs_share, hit / nullif(nb, 0)::DOUBLE >= 0.9 AS near_copy FROM lcs")
add("near_copy_chars", lambda s, d: near_copy(s, d, "char"))
add("copy_substring", common_run)

# duplicates
_d = f"WITH {M1}, p AS (SELECT *, md5(reference) AS fr, md5(summary) AS fs FROM m1) "
add("fingerprints", m1(lambda p: p.select("pair_id", T.fingerprint(ref()).alias("fr"), T.fingerprint(summ()).alias("fs"))), _d + "SELECT pair_id, fr, fs FROM p")
add("dup_exact", m1(lambda p: U.groups(p, "exact")), _d + "SELECT fr, fs, count(*) AS n, min(seq) AS first_seq, count(DISTINCT fr) AS n_other FROM p GROUP BY fr, fs HAVING count(*) > 1")
add("dup_reference", m1(lambda p: U.groups(p, "reference")), _d + "SELECT fr, count(*) AS n, min(seq) AS first_seq, count(DISTINCT fs) AS n_other FROM p GROUP BY fr HAVING count(DISTINCT fs) > 1")
add("dup_summary", m1(lambda p: U.groups(p, "summary")), _d + "SELECT fs, count(*) AS n, min(seq) AS first_seq, count(DISTINCT fr) AS n_other FROM p GROUP BY fs HAVING count(DISTINCT fr) > 1")
add("dup_cross", m1(U.cross, "mixed_news"), f"WITH {M3}, p AS (SELECT pair_id, split, seq, (CASE split WHEN 'test' THEN 0 WHEN 'validation' THEN 1 ELSE 2 END) * 100000000000000 + seq AS rank, md5(reference) AS fr, md5(summary) AS fs FROM m3) SELECT pair_id, split, seq FROM p QUALIFY min(rank) OVER (PARTITION BY fr) < rank AND min(rank) OVER (PARTITION BY fs) < rank AND min(rank) OVER (PARTITION BY fr, fs) = rank")
for _n, _k in (("headline_body", "dedup_additive"), ("mixed_news", "dup_classes")):
    add(_k, m1(U.additive, _n), f"WITH RECURSIVE {MAPPED[_n][1]}, {ROUNDS.format(source=MAPPED[_n][0])} SELECT * FROM judged")
_rank = f"WITH {M1}, p AS (SELECT *, (CASE split WHEN 'test' THEN 0 WHEN 'validation' THEN 1 ELSE 2 END) * 100000000000000 + seq AS rank FROM m1) "
add("dedup_first", m1(lambda p: U.keep(p, "first_occurrence")), _rank + "SELECT pair_id FROM p QUALIFY min(rank) OVER (PARTITION BY reference) = rank AND min(rank) OVER (PARTITION BY summary) = rank")
add("dedup_exact_only", m1(lambda p: U.keep(p, "exact")), _rank + "SELECT pair_id FROM p QUALIFY min(rank) OVER (PARTITION BY reference, summary) = rank")
add("dedup_drop_all", m1(lambda p: U.keep(p, "drop_all")), _rank + "SELECT pair_id FROM p QUALIFY count(*) OVER (PARTITION BY reference) = 1 AND count(*) OVER (PARTITION BY summary) = 1")
add("dedup_keep_longest", m1(lambda p: U.keep(p, "keep_longest")), _rank + "SELECT pair_id FROM p QUALIFY row_number() OVER (PARTITION BY summary ORDER BY length(reference) DESC, rank) = 1")
_kept = {k: O[f"dedup_{v}"].split("SELECT pair_id FROM p")[1] for k, v in (("first_occurrence", "first"), ("exact", "exact_only"), ("drop_all", "drop_all"), ("keep_longest", "keep_longest"))}
add("dedup_compare", m1(U.compare), f"WITH RECURSIVE {M1}, {ROUNDS.format(source='m1')}, p AS (SELECT *, (CASE split WHEN 'test' THEN 0 WHEN 'validation' THEN 1 ELSE 2 END) * 100000000000000 + seq AS rank FROM m1), k AS (SELECT 'additive' AS strategy, pair_id FROM judged WHERE verdict = 'valid' " + " ".join(f"UNION ALL SELECT '{n}', pair_id FROM (SELECT pair_id FROM p{q})" for n, q in _kept.items()) + ") SELECT strategy, split, count(*) AS kept FROM k JOIN m1 USING (pair_id) GROUP BY strategy, split")
add("dedup_order_effect", m1(lambda p: p.select("pair_id", "split").join(U.keep(p, split_order=("train", "validation", "test")), "pair_id", "left_semi").groupBy("split").agg(F.count(F.lit(1)).alias("kept"))), f"WITH RECURSIVE {M1}, {ROUNDS.format(source='m1').replace(chr(39) + 'test' + chr(39) + ' THEN 0', chr(39) + 'train' + chr(39) + ' THEN 0')} SELECT split, count(*) AS kept FROM judged JOIN m1 USING (pair_id) WHERE verdict = 'valid' GROUP BY split")
add("split_leakage", W.leakage, _d + ", t AS (SELECT 'reference' AS side, fr AS f, split FROM p UNION ALL SELECT 'summary', fs, split FROM p), g AS (SELECT side, f, string_agg(DISTINCT split, '+' ORDER BY split) AS splits FROM t GROUP BY side, f HAVING count(DISTINCT split) > 1) SELECT side, splits, count(*) AS n FROM g GROUP BY side, splits")
add("top_repeats", m1(U.top_repeats), f"WITH {M1} SELECT summary AS text, count(*) AS n FROM m1 GROUP BY summary HAVING count(*) > 1 ORDER BY n DESC, md5(summary) LIMIT 10")
add("alignment_suspects", m1(U.alignment_suspects), _d + "SELECT origin, fs, count(DISTINCT reference) AS n_references, min(seq) AS first_seq FROM p GROUP BY origin, fs HAVING count(DISTINCT reference) > 1")

# the sieve
for _n, _k in (("headline_body", "sieve_label"), ("mixed_news", "sieve_label_mixed")):
    add(_k, m1(lambda p: S.Sieve().label(p).select("pair_id", "verdict"), _n), label_sql(MAPPED[_n][0], MAPPED[_n][1]) + " SELECT pair_id, verdict FROM labelled")
add("sieve_label_replies", m1(lambda p: W.INSTRUCTIONS.label(p).select("pair_id", "verdict"), "prompt_reply"), label_sql("m5", M5, r=20, s=8) + " SELECT pair_id, verdict FROM labelled")
add("sieve_flags", m1(lambda p: p.select("pair_id", *(c.alias(n) for n, c in S.Sieve().flags().items()))), _p + "length(reference) = 0 OR length(summary) = 0 AS empty, length(reference) < 50 AS ref_short, length(summary) < 20 AS summ_short, reference = summary AS identical, length(reference)::DOUBLE < length(summary) * 1.25::DOUBLE AS low_cr, contains(reference, summary) AS extractive FROM m1")
add("sieve_clean", m1(lambda p: S.Sieve().clean(p).select("pair_id", "split"), "mixed_news"), LABEL3 + " SELECT pair_id, split FROM labelled WHERE verdict = 'valid'")
_fun = " SELECT '{c}' AS corpus, split, verdict, n, round(n / sum(n) OVER (PARTITION BY split), 6) AS share, verdict <> 'valid' AND n / sum(n) OVER (PARTITION BY split) > 0.02 AS bold FROM (SELECT split, verdict, count(*) AS n FROM labelled GROUP BY split, verdict)"
add("funnel", lambda s, d: S.funnel(W.labelled(s, d, "headline_body"), "headline_body"), LABEL1 + _fun.format(c="headline_body"))
add("funnel_bold", lambda s, d: S.funnel(W.labelled(s, d, "mixed_news"), "mixed_news").where("bold").select("split", "verdict", "share"), LABEL3 + f" SELECT split, verdict, share FROM ({_fun.format(c='x')}) WHERE bold")
add("funnel_wide", lambda s, d: S.wide_funnel(W.labelled(s, d, "mixed_news")), LABEL3 + " SELECT split, " + ", ".join(f"count(*) FILTER (WHERE verdict = '{v}') AS {v}" for v in S.VERDICTS) + " FROM labelled GROUP BY split")
add("affected_share", lambda s, d: S.affected(W.labelled(s, d, "mixed_news"), "mixed_news"), LABEL3 + ", a AS (SELECT count(*) AS n, round(avg((verdict <> 'valid')::INT), 6) AS share FROM labelled) SELECT 'mixed_news' AS corpus, n, share, share > 0.25 AS over_quarter, share > 0.5 AS over_half FROM a")
add("sieve_sweep", m1(lambda p: S.sweep(p, [1.1, 1.25, 1.5, 2.0], [20, 50, 100])), f"WITH {M1} SELECT min_cr, min_ref, count(*) FILTER (WHERE length(reference) < min_ref) AS ref_short, count(*) FILTER (WHERE length(reference)::DOUBLE < length(summary) * min_cr) AS low_cr FROM m1, (SELECT unnest([1.1::DOUBLE, 1.25, 1.5, 2.0]) AS min_cr), (SELECT unnest([20, 50, 100]) AS min_ref) GROUP BY ALL")
_flags = ("empty", "ref_short", "summ_short", "identical", "low_cr", "extractive")
add("sieve_ablation", m1(lambda p: S.ablate(p, S.Sieve())), f"WITH f AS ({O['sieve_flags']}) " + " UNION ALL ".join(f"SELECT '{n}' AS left_out, count(*) FILTER (WHERE NOT ({' OR '.join(x for x in _flags if x != n)})) AS passing FROM f" for n in ("none", *_flags)))
add("fault_runs", lambda s, d: U.runs_of_faults(W.labelled(s, d, "headline_body")), LABEL1 + ", i AS (SELECT seq, verdict <> 'valid' AS bad, row_number() OVER (ORDER BY seq) - row_number() OVER (PARTITION BY verdict <> 'valid' ORDER BY seq) AS isle FROM labelled) SELECT min(seq) AS first_seq, max(seq) AS last_seq, count(*) AS n FROM i WHERE bad GROUP BY isle HAVING count(*) >= 2")

# review and distributions
add("inspect_in_order", lambda s, d: V.in_order(load(s, d, "documents").select("doc_id", "source", "n_chars"), [F.col("source"), F.desc("n_chars"), F.col("doc_id")], 20, 5), "SELECT doc_id, source, n_chars FROM documents ORDER BY source, n_chars DESC, doc_id LIMIT 20 OFFSET 5")
add("inspect_in_time", lambda s, d: V.in_order(load(s, d, "events").select("event_id", "ts"), [F.col("ts"), F.col("event_id")], 20), "SELECT event_id, ts FROM events ORDER BY ts, event_id LIMIT 20")
add("inspect_random", lambda s, d: V.random_sample(load(s, d, "documents").select("doc_id", "lang"), 25, "doc_id", 7), "SELECT doc_id, lang FROM documents ORDER BY md5(doc_id::VARCHAR || '7') LIMIT 25")
add("inspect_stratified", m1(lambda p: V.random_sample(S.Sieve(dedup=None).label_rows(p).select("pair_id", "verdict"), 3, "pair_id", 7, by="verdict")), f"WITH {M1}, {row_sql('m1')} SELECT pair_id, verdict FROM rows_ QUALIFY row_number() OVER (PARTITION BY verdict ORDER BY md5(pair_id::VARCHAR || '7')) <= 3")
add("inspect_extremes", m1(lambda p: V.extremes(p, F.length("reference"), 10, "pair_id")), f"WITH {M1}, v AS (SELECT pair_id, length(reference) AS value FROM m1) (SELECT *, 'low' AS side FROM v ORDER BY value, pair_id LIMIT 10) UNION ALL (SELECT *, 'high' FROM v ORDER BY value DESC, pair_id LIMIT 10)")
add("inspect_iqr", m1(lambda p: V.outliers(p, F.length("reference"), "pair_id")), f"WITH {M1}, v AS (SELECT pair_id, length(reference)::DOUBLE AS value FROM m1), s AS (SELECT quantile_cont(value, 0.25) AS a, quantile_cont(value, 0.75) AS b FROM v) SELECT pair_id, value FROM v, s WHERE value < a - 1.5 * (b - a) OR value > b + 1.5 * (b - a)")
add("inspect_zscore", m1(lambda p: V.outliers(p, F.length("reference"), "pair_id", "zscore", 3.0)), f"WITH {M1}, v AS (SELECT pair_id, length(reference)::DOUBLE AS value FROM m1), s AS (SELECT avg(value) AS a, stddev_samp(value) AS b FROM v) SELECT pair_id, value FROM v, s WHERE value < a - 3 * b OR value > a + 3 * b")
add("inspect_representative", m1(lambda p: V.representatives(p, F.length("reference"), "pair_id", 15)), f"WITH {M1}, v AS (SELECT pair_id, length(reference)::DOUBLE AS value FROM m1), s AS (SELECT median(value) AS c FROM v) SELECT pair_id, value FROM v, s ORDER BY abs(value - c), pair_id LIMIT 15")
_q = "count(value) AS n, round(avg(value), 6) AS mean, round(stddev_samp(value), 6) AS sd, min(value) AS least, round(quantile_cont(value, 0.25), 6) AS q1, round(median(value), 6) AS median, round(quantile_cont(value, 0.75), 6) AS q3, max(value) AS most"
add("length_stats", m1(lambda p: V.describe(p, F.length("reference"), ["split"])), f"WITH {M1}, v AS (SELECT split, length(reference)::DOUBLE AS value FROM m1) SELECT split, {_q} FROM v GROUP BY split")
add("violin_stats", lambda s, d: V.violin(W.labelled(s, d, "mixed_news")), LABEL3 + f", {STATES}, v AS (SELECT split, state, 'reference' AS side, length(reference)::DOUBLE AS value FROM states UNION ALL SELECT split, state, 'summary', length(summary)::DOUBLE FROM states) SELECT split, state, side, {_q} FROM v GROUP BY split, state, side")
add("violin_density", lambda s, d: V.density(W.labelled(s, d, "headline_body")), LABEL1 + f", {STATES}, b AS (SELECT state, length(reference) // 200 AS bin, count(*) AS n FROM states GROUP BY 1, 2), t AS (SELECT state, sum(n) AS total FROM b GROUP BY 1), a AS (SELECT *, unnest(range(bin - 20, bin + 21)) AS place FROM b) SELECT a.state, place AS bin, round(sum(n * exp(-0.5 * pow(((place - bin) * 200) / 200.0, 2))) / (200.0 * 2.5066282746310002e0) / any_value(total), 9) AS density FROM a JOIN t USING (state) WHERE place >= 0 GROUP BY a.state, place")
add("length_shift", lambda s, d: V.shift(W.labelled(s, d, "mixed_news")), LABEL3 + f", {STATES}, v AS (SELECT state, length(reference) AS size FROM states), b AS (SELECT size // 100 AS bin, count(*) FILTER (WHERE state = 'unfiltered') AS a, count(*) FILTER (WHERE state = 'filtered') AS b FROM v GROUP BY 1), g AS (SELECT abs(sum(a) OVER (ORDER BY bin) / sum(a) OVER () - sum(b) OVER (ORDER BY bin) / sum(b) OVER ()) AS gap FROM b) SELECT (SELECT round(max(gap), 6) FROM g) AS max_gap, (SELECT round(avg(size) FILTER (WHERE state = 'filtered') - avg(size) FILTER (WHERE state = 'unfiltered'), 6) FROM v) AS mean_change")
add("output_lengths", m1(lambda p: V.describe(Y.prefix_copier(p), F.length("output"), ["split"])), f"WITH {M1}, v AS (SELECT split, length(array_to_string(({WORDS.format(c='reference')})[1:48], ' '))::DOUBLE AS value FROM m1) SELECT split, {_q} FROM v GROUP BY split")

# baselines
add("sentences", lambda s, d: load(s, d, "documents").select("doc_id", F.posexplode(T.sentences(F.col("text"))).alias("pos", "sentence")), f"SELECT doc_id, unnest(range(len(z))) AS pos, unnest(z) AS sentence FROM (SELECT doc_id, {sents('text')} AS z FROM documents)")
_lead = lambda k: f"array_to_string(({sents('reference')})[1:{k}], ' ')"
add("lead3", m1(lambda p: B.lead(p).select("pair_id", "output")), _p + f"{_lead(3)} AS output FROM m1")
add("lead_fixed", m1(lambda p: B.lead(p, 5).select("pair_id", "output")), _p + f"{_lead(5)} AS output FROM m1")
add("lead_paragraph", m1(lambda p: B.lead_paragraph(p).select("pair_id", "output")), _p + "split_part(reference, chr(10), 1) AS output FROM m1")
_ratio = f"WITH {M1}, ns AS (SELECT *, len({sents('reference')}) AS nr, len({sents('summary')}) AS nq FROM m1), ratio AS (SELECT avg(nr::DOUBLE / nullif(nq, 0)) AS ratio FROM ns WHERE split = 'train'), ks AS (SELECT ns.*, greatest(1, least(coalesce(floor(nr / ratio + 0.5), 1), nr))::INT AS k FROM ns, ratio) "
add("mean_cr", m1(lambda p: B.mean_ratio(p).select(F.round("ratio", 6).alias("ratio"))), _ratio + "SELECT round(ratio, 6) AS ratio FROM ratio")
add("k_hat", m1(lambda p: B.with_k(p, B.mean_ratio(p)).select("pair_id", "k")), _ratio + "SELECT pair_id, k FROM ks")
add("lead_k", m1(lambda p: B.lead_k(p, B.mean_ratio(p)).select("pair_id", "output")), _ratio + f"SELECT pair_id, {_lead('k')} AS output FROM ks")
add("random_k", m1(lambda p: B.random_k(p, B.mean_ratio(p)).select("pair_id", "output")), _ratio + f", z AS (SELECT pair_id, k, {sents('reference')} AS s FROM ks), u AS (SELECT pair_id, k, unnest(s) AS x, unnest(range(len(s))) AS i FROM z), o AS (SELECT * FROM u QUALIFY row_number() OVER (PARTITION BY pair_id ORDER BY md5(x || i::VARCHAR || '0'), i) <= k) SELECT z.pair_id, coalesce(string_agg(o.x, ' ' ORDER BY o.i), '') AS output FROM z LEFT JOIN o USING (pair_id) GROUP BY z.pair_id")
for _w in ("hashed", "tfidf", "overlap"):
    add(f"central_{_w}", (lambda w: m1(lambda p: B.central(p, B.mean_ratio(p), w).select("pair_id", "output")))(_w))
add("central_threshold", m1(lambda p: B.central(p, B.mean_ratio(p), graph="threshold").select("pair_id", "output")))
_deg = "SELECT e.vec_id, e.label, (SELECT count(*) FROM embeddings f WHERE f.label = e.label AND f.vec_id <> e.vec_id AND round(list_dot_product(e.embedding::DOUBLE[], f.embedding::DOUBLE[]), 6) >= {t}) AS degree FROM embeddings e"
add("central_degree", lambda s, d: B.vector_degree(load(s, d, "embeddings")), _deg.format(t=0.1))
add("central_vectors", lambda s, d: B.vector_degree(load(s, d, "embeddings"), threshold=0.3), _deg.format(t=0.3))
add("oracle_extract", m1(lambda p: B.oracle_extract(p).select("pair_id", "output")))

# scores
add("tokens", m1(lambda p: p.select("pair_id", F.array_join(T.tokens(summ()), " ").alias("tokens"))), _p + f"array_to_string({toks('summary')}, ' ') AS tokens FROM m1")


def rouge_sql(n: int) -> str:
    g = lambda c, o: f"SELECT pair_id, g, count(*) AS {o} FROM (SELECT pair_id, unnest(CASE WHEN len(t) >= {n} THEN list_transform(range(1, len(t) - {n - 2}), lambda i: array_to_string(t[i:i + {n - 1}], ' ')) ELSE []::VARCHAR[] END) AS g FROM (SELECT pair_id, {toks(c)} AS t FROM o)) GROUP BY pair_id, g"
    return f"WITH {M1}, o AS (SELECT pair_id, summary, {_lead(3)} AS output FROM m1), a AS ({g('output', 'na')}), b AS ({g('summary', 'nb')}), c AS (SELECT pair_id, sum(least(coalesce(na, 0), coalesce(nb, 0))) AS hit, sum(na) AS na, sum(nb) AS nb FROM a FULL JOIN b USING (pair_id, g) GROUP BY pair_id), s AS (SELECT pair_id, coalesce(hit / nullif(na, 0), 0) AS p, coalesce(hit / nullif(nb, 0), 0) AS r FROM o LEFT JOIN c USING (pair_id)) SELECT pair_id, round(p, 6) AS p, round(r, 6) AS r, round(coalesce(2 * p * r / nullif(p + r, 0), 0), 6) AS f FROM s"


for _i in (1, 2, 3):
    add(f"rouge{_i}", (lambda i: m1(lambda p: R.relational_rouge(B.lead(p), "output", "summary", i)))(_i), rouge_sql(_i))
add("rouge_kernel", m1(lambda p: B.lead(p).select("pair_id", R.rouge(F.col("output"), summ(), stem=None).alias("s")).select("pair_id", F.round("s.r1_p", 6).alias("p"), F.round("s.r1_r", 6).alias("r"), F.round("s.r1_f", 6).alias("f"))), rouge_sql(1))
add("rougeL", m1(lambda p: B.lead(p).select("pair_id", F.round(R.rouge(F.col("output"), summ()).getField("rl_f"), 6).alias("f"))))
add("rougeL_plain", m1(lambda p: B.lead(p).select("pair_id", F.round(R.rouge(F.col("output"), summ(), None).getField("rl_f"), 6).alias("f"))), lcs_sql(f"{M1}, o AS (SELECT pair_id, summary, {_lead(3)} AS output FROM m1)", "o", "output", "summary") + " SELECT pair_id, round(CASE WHEN hit > 0 THEN 2 * (hit / na::DOUBLE) * (hit / nb::DOUBLE) / (hit / na::DOUBLE + hit / nb::DOUBLE) ELSE 0 END, 6) AS f FROM lcs")


def rouge_lsum(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.udfs import rouge_lsum as u

    return B.lead(MAPPINGS["headline_body"](s, d)).select("pair_id", F.round(u(T.sentences(F.col("output")), T.sentences(summ())), 6).alias("f"))


def stems(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.udfs import stem_de

    w = load(s, d, "documents").where("lang = 'de'").select(F.explode(T.tokens(F.col("text"))).alias("word")).distinct()
    return w.select("word", stem_de("word").alias("stem"))


add("rougeLsum", rouge_lsum)
add("stem_de", stems)
add("score_table", W.before_after)
add("bootstrap_ci", lambda s, d: R.bootstrap(W.scored(s, d, "headline_body").where("system = 'lead_3'"), "r1", ["system", "split"]))
add("rouge_sensitivity", m1(lambda p: B.lead(p).select(*(R.rouge(F.col("output"), summ(), st, asc).getField("r1_f").alias(n) for n, st, asc in (("plain", None, False), ("stemmed", "de", False), ("ascii", None, True)))).agg(*(F.round(100 * F.avg(n), 4).alias(n) for n in ("plain", "stemmed", "ascii")))))
add("filter_effect", lambda s, d: R.filter_effect(W.before_after(s, d)))
add("rank_shift", lambda s, d: R.rank_shift(W.before_after(s, d)))
add("rank_agreement", lambda s, d: R.kendall_tau(R.rank_shift(W.before_after(s, d))))
add("best_marks", lambda s, d: R.mark_best(W.before_after(s, d), ["split", "state"]))
add("baseline_margin", lambda s, d: R.baseline_margin(W.before_after(s, d), ["lead_3", "lead_k", "central"], ["split", "state"]))
add("baseline_spread", lambda s, d: R.baseline_spread(W.before_after(s, d), ["lead_3", "lead_k"], ["split", "state"]))
add("baselines_on_clean", W.baselines_on_clean)
add("other_domain", W.other_domain)
add("failure_cases", W.failure_cases)
add("funnels_all", W.funnels)
add("funnels_german", lambda s, d: W.funnels(s, d, "de"))
add("baseline_intervals", W.baseline_intervals)
add("repro_gap", W.reproduction)
add("evaluation_audit", W.habits, f"WITH {M1}, {row_sql('m1')}, r AS (SELECT split <> 'train' AS published, verdict = 'valid' AS public, len({sents('reference')}) > 3 AS baseline, regexp_matches(summary, '[0-9]') AS beyond FROM rows_) SELECT published, count(*) AS n, count(*) FILTER (WHERE baseline) AS with_baseline, count(*) FILTER (WHERE beyond) AS beyond_ngrams, count(*) FILTER (WHERE public AND beyond) AS public_beyond FROM r GROUP BY published")
_shift = O["length_shift"].replace(LABEL3, "").replace("FROM states)", "FROM states WHERE split = 'train')")
add("length_shift_train", W.train_shift, f"SELECT * FROM ({LABEL1}{_shift.replace('SELECT (SELECT round(max(gap)', chr(39).join(['SELECT ', 'headline_body', ' AS corpus, (SELECT round(max(gap)']))}) UNION ALL SELECT * FROM ({LABEL3}{_shift.replace('SELECT (SELECT round(max(gap)', chr(39).join(['SELECT ', 'mixed_news', ' AS corpus, (SELECT round(max(gap)']))})")
add("label_agreement", W.label_agreement, LABEL1 + " SELECT verdict, count(*) FILTER (WHERE quality = 0) AS bad, count(*) FILTER (WHERE quality = 1) AS good FROM labelled JOIN labels ON doc_id = pair_id GROUP BY verdict")
_nov = lambda n: f"CASE WHEN len(t) >= {n} THEN list_transform(range(1, len(t) - {n - 2}), lambda i: array_to_string(t[i:i + {n - 1}], ' ')) ELSE []::VARCHAR[] END"
add("novel_ngrams", m1(lambda p: p.select("pair_id", *(c.alias(n) for n, c in R.novelty(ref(), summ(), 2).items()))), f"WITH {M1}, z AS (SELECT pair_id, list_distinct((SELECT {_nov(2)} FROM (SELECT {toks('summary')} AS t))) AS a, (SELECT {_nov(2)} FROM (SELECT {toks('reference')} AS t)) AS b FROM m1), y AS (SELECT pair_id, len(a) AS n_grams, len(a) - len(list_intersect(a, b)) AS n_novel FROM z) SELECT *, round(n_novel / nullif(n_grams, 0)::DOUBLE, 6) AS novel_share FROM y")
_out48 = f"array_to_string(({WORDS.format(c='reference')})[1:48], ' ')"
add("prefix_copy", m1(lambda p: Y.prefix_copier(p).select("pair_id", R.prefix_copy(ref(), F.col("output")).alias("share"))), f"WITH {M1}, o AS (SELECT pair_id, {toks('reference')} AS b, {toks(_out48)} AS a FROM m1), f AS (SELECT pair_id, len(a) AS n, list_position(list_transform(range(1, len(a) + 1), lambda i: coalesce(a[i] = b[i], false)), false) AS first FROM o) SELECT pair_id, round(CASE WHEN n = 0 THEN 0.0 WHEN coalesce(first, 0) = 0 THEN 1.0 ELSE (first - 1)::DOUBLE / n END, 6) AS share FROM f")
add("copied_output", m1(lambda p: Y.prefix_copier(p).select("pair_id", C.fully_extractive(ref(), F.col("output"), "token_run").alias("copied"))), f"WITH {M1} SELECT pair_id, contains(' ' || array_to_string({toks('reference')}, ' ') || ' ', ' ' || array_to_string({toks(_out48)}, ' ') || ' ') AS copied FROM m1")
add("repetition", m1(lambda p: Y.looper(p).select("pair_id", R.repetition(F.col("output")).alias("share"))), f"WITH {M1}, z AS (SELECT pair_id, (SELECT {_nov(3)} FROM (SELECT {toks('o')} AS t FROM (SELECT array_to_string(flatten([({WORDS.format(c='reference')})[1:3] for i in range(16)]), ' ') AS o))) AS g FROM m1) SELECT pair_id, round(coalesce(1 - len(list_distinct(g)) / nullif(len(g), 0)::DOUBLE, 0), 6) AS share FROM z")
add("context_overflow", lambda s, d: load(s, d, "documents").select("doc_id", R.context_overflow(F.col("text")).alias("too_long")), f"SELECT doc_id, len({WORDS.format(c='text')}) > 512 AS too_long FROM documents")
add("unsupported_items", m1(lambda p: p.select("pair_id", R.unsupported(ref(), summ()).alias("n"))), _p + "len(list_filter(list_distinct(regexp_extract_all(summary, '[0-9]+|[A-Z][a-z]+')), lambda x: NOT list_contains(regexp_extract_all(reference, '[0-9]+|[A-Z][a-z]+'), x))) AS n FROM m1")
add("lead_bias", m1(lambda p: p.where(F.length("summary") > 0).select(C.copy_position(ref(), summ())["copy_share"].alias("x")).where("x is not null").groupBy(F.floor(F.col("x") * 10).alias("tenth")).agg(F.count(F.lit(1)).alias("n")), "passage_host"), "SELECT floor(x * 10)::BIGINT AS tenth, count(*) AS n FROM (SELECT round((instr(d.text, b.text) - 1) / length(d.text), 6) AS x FROM documents d JOIN benchmark b ON contains(d.text, b.text)) GROUP BY 1")


def fragments(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.udfs import fragment_stats

    p = MAPPINGS["headline_body"](s, d).select("pair_id", fragment_stats(T.tokens(ref()), T.tokens(summ())).alias("z"))
    return p.select("pair_id", F.round("z.coverage", 6).alias("coverage"), F.round("z.density", 6).alias("density"))


def loops(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.udfs import blocked, loop_length

    return Y.looper(MAPPINGS["headline_body"](s, d)).select("pair_id", F.round(loop_length(T.tokens(F.col("output"))), 4).alias("periods"), F.size(blocked(T.tokens(F.col("output")))).alias("after_blocking"))


add("fragments", fragments)
add("block_repeats", loops)


# the SQL surface
def sql_surface(s: SparkSession, d: str) -> DataFrame:
    """The checks and the score by their SQL names."""
    from pairlens.sources.tables import register

    register(s, B.lead(MAPPINGS["headline_body"](s, d)), "pairlens_surface")
    return s.sql("SELECT pair_id, round(compression_ratio(reference, summary), 6) AS cr, sieve_verdict(reference, summary) AS verdict, round(rouge_f(output, summary), 6) AS f FROM pairlens_surface")


def sentence_table(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.tables import register_tables

    register_tables(s)
    load(s, d, "documents").createOrReplaceTempView("pairlens_documents")
    return s.sql("SELECT doc_id, z.pos, z.sentence FROM pairlens_documents, LATERAL sentence_rows(text) z")


def gram_counts(s: SparkSession, d: str) -> DataFrame:
    from pairlens.functions.tables import register_tables

    register_tables(s)
    MAPPINGS["headline_body"](s, d).createOrReplaceTempView("pairlens_heads")
    return s.sql("SELECT z.gram, count(*) AS n FROM pairlens_heads, LATERAL gram_table(summary, 2) z GROUP BY z.gram")


def novel_shares(s: SparkSession, d: str) -> DataFrame:
    """The grouped aggregate over a pair's bigrams; pairs without any are left out, as there is nothing to group."""
    from pairlens.functions.udfs import novel_share

    new = lambda a, b: F.transform(a, lambda g: F.struct(g.alias("gram"), F.array_contains(b, g).alias("known")))
    both = MAPPINGS["headline_body"](s, d).select("pair_id", F.get(F.transform(F.array(F.struct(T.ngrams(T.tokens(summ()), 2).alias("a"), T.ngrams(T.tokens(ref()), 2).alias("b"))), lambda z: new(z["a"], z["b"])), 0).alias("z"))
    grams = both.select("pair_id", F.inline("z"))
    return grams.groupBy("pair_id").agg(F.round(novel_share("gram", "known"), 6).alias("share"))


add("sql_surface", sql_surface, f"SELECT a.pair_id, a.cr, a.verdict, b.f FROM (WITH {M1}, {row_sql('m1')} SELECT pair_id, round(length(reference)::DOUBLE / nullif(length(summary), 0), 6) AS cr, verdict FROM rows_) a JOIN ({rouge_sql(1)}) b ON a.pair_id = b.pair_id")
add("sentence_table", sentence_table, O["sentences"])
_bi = f"WITH {M1}, z AS (SELECT pair_id, unnest((SELECT {_nov(2)} FROM (SELECT {toks('summary')} AS t))) AS gram FROM m1)"
add("gram_table", gram_counts, _bi + " SELECT gram, count(*) AS n FROM z GROUP BY gram")
add("novel_share_agg", novel_shares, f"SELECT pair_id, novel_share AS share FROM ({O['novel_ngrams']}) WHERE n_grams > 0")
add("threshold_grid", lambda s, d: S.passing(MAPPINGS["headline_body"](s, d), S.grid(s)), f"WITH {M1}, g AS (SELECT round(1.0::DOUBLE + (i % 4) * 0.25::DOUBLE, 6) AS min_cr, (20 + (i // 4) * 15)::INT AS min_ref FROM range(12) AS t(i)) SELECT min_cr, min_ref, count(pair_id) AS passing FROM g LEFT JOIN m1 ON length(reference) >= min_ref AND length(reference)::DOUBLE >= length(summary) * min_cr GROUP BY min_cr, min_ref")


def pages_text(s: SparkSession, d: str) -> DataFrame:
    from pairlens.sources.mappings import page_text

    return load(s, d, "pages").select("page_id", page_text(F.col("html"), True).alias("title"), page_text(F.col("html")).alias("text"))


def page_sql(part: str) -> str:
    out = f"regexp_replace(regexp_replace(regexp_extract(html, '(?s)<{part}>(.*?)</{part}>', 1), '(?s)<h1>.*?</h1>', ' ', 'g'), '(?s)<[^>]*>', ' ', 'g')"
    for entity, plain in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        out = f"replace({out}, '{entity}', '{plain}')"
    return f"regexp_replace(regexp_replace({out}, '[\\s\\x0b]+', ' ', 'g'), '^ | $', '', 'g')"


add("page_text", pages_text, f"SELECT page_id, {page_sql('title')} AS title, {page_sql('article')} AS text FROM pages")
O["pairs_page_title_body"] = f"SELECT page_id AS pair_id, {SPLIT.format(k='page_id')}, regexp_extract(html, 'lang=\"([a-z]+)\"', 1) AS lang, 'pages' AS origin, page_id AS seq, {page_sql('article')} AS reference, {page_sql('title')} AS summary FROM pages"
