"""The experiments on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairlens.functions import checks
from pairlens.functions.text import sentences, tokens
from pairlens.operators import baselines, dedup, review, scores, sieve, systems
from pairlens.session import checkpointed, load
from pairlens.sources.mappings import MAPPINGS

NEWS, INSTRUCTIONS = sieve.Sieve(), sieve.Sieve(sieve.Profile.instructions())


def profile_of(name: str) -> sieve.Sieve:
    return INSTRUCTIONS if name == "prompt_reply" else NEWS


def labelled(spark: SparkSession, sf: str, name: str, lang: str | None = None) -> DataFrame:
    p = MAPPINGS[name](spark, sf)
    return checkpointed(profile_of(name).label(p if lang is None else p.where(F.col("lang") == lang)))


def funnels(spark: SparkSession, sf: str, lang: str | None = None, names: tuple[str, ...] = tuple(MAPPINGS)[:7]) -> DataFrame:
    out = None
    for n in names:
        one = sieve.funnel(labelled(spark, sf, n, lang), n)
        out = one if out is None else out.unionByName(one)
    return out


def run_systems(pairs: DataFrame, train: DataFrame) -> DataFrame:
    """Outputs of the three baselines and of the stand-ins for evaluated pairs; the ratio comes from the train pairs."""
    ratio = checkpointed(baselines.mean_ratio(train))
    cols = ["system", "pair_id", "split", "summary", "reference", "verdict", "output"]
    base = [("lead_3", baselines.lead(pairs)), ("lead_k", baselines.lead_k(pairs, ratio)), ("central", baselines.central(pairs, ratio))]
    outs = [d.withColumn("system", F.lit(n)).select(cols) for n, d in base] + [f(pairs).select(cols) for f in systems.SYSTEMS]
    out = outs[0]
    for o in outs[1:]:
        out = out.unionByName(o)
    return out


def scored(spark: SparkSession, sf: str, name: str = "mixed_news", train_name: str | None = None) -> DataFrame:
    """system, pair_id, split, verdict, r1, r2, rl of validation and test pairs with both sides."""
    all_ = labelled(spark, sf, name)
    train = all_ if train_name is None else labelled(spark, sf, train_name)
    held = all_.where((F.col("split") != "train") & (F.col("verdict") != "empty"))
    s = run_systems(held, train.where("verdict = 'valid'")).withColumn("s", scores.rouge(F.col("output"), F.col("summary")))
    return checkpointed(s.select("system", "pair_id", "split", "verdict", F.col("s.r1_f").alias("r1"), F.col("s.r2_f").alias("r2"), F.col("s.rl_f").alias("rl")))


def before_after(spark: SparkSession, sf: str, name: str = "mixed_news") -> DataFrame:
    return scores.table(review.states(scored(spark, sf, name)), ["system", "split", "state"])


def baselines_on_clean(spark: SparkSession, sf: str) -> DataFrame:
    out = None
    for name in ("headline_body", "mixed_news", "prompt_reply"):
        one = scored(spark, sf, name).where("verdict = 'valid' and system in ('lead_3', 'lead_k', 'central')")
        one = scores.table(one, ["system", "split"]).withColumn("corpus", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def baseline_intervals(spark: SparkSession, sf: str, name: str = "mixed_news", draws: str = "redrawn") -> DataFrame:
    """95 % intervals of R-1 of the three baselines on clean held-out pairs."""
    s = scored(spark, sf, name).where("verdict = 'valid' and system in ('lead_3', 'lead_k', 'central')")
    return (scores.bootstrap_draws if draws == "redrawn" else scores.bootstrap)(s, "r1", ["system", "split"])


def reproduction(spark: SparkSession, sf: str, name: str = "headline_body") -> DataFrame:
    """Scores reported with stemming on all held-out pairs against those that another scorer (no stemming, ASCII words)
    and the filtered pairs give: gap, and whether it stays within half a point."""
    all_ = labelled(spark, sf, name)
    held = all_.where("split <> 'train' and verdict <> 'empty'")
    ratio = checkpointed(baselines.mean_ratio(all_.where("verdict = 'valid'")))
    outs = baselines.lead(held).withColumn("system", F.lit("lead_3")).select("system", "split", "verdict", "summary", "output").unionByName(baselines.lead_k(held, ratio).withColumn("system", F.lit("lead_k")).select("system", "split", "verdict", "summary", "output"))
    f1 = lambda stem, ascii_: scores.rouge(F.col("output"), F.col("summary"), stem, ascii_).getField("r1_f")
    both = checkpointed(outs.select("system", "split", "verdict", f1("de", False).alias("stemmed"), f1(None, True).alias("ascii")))
    by = ["system", "split"]
    mean = lambda rows, c: rows.groupBy(*by).agg(F.round(100 * F.avg(c), 4).alias("r1"))
    reported = mean(both, "stemmed")
    settings = {"same": mean(both, "stemmed"), "other_scorer": mean(both, "ascii"), "filtered": mean(both.where("verdict = 'valid'"), "stemmed")}
    out = None
    for n, measured in settings.items():
        one = scores.reproduction_gap(reported, measured, by).select(F.lit(n).alias("setting"), *by, "gap", "within")
        out = one if out is None else out.unionByName(one)
    return out


def reports(spark: SparkSession, sf: str) -> DataFrame:
    """A record of evaluation per document, as a table of systems has them: published are held-out pairs, public those
    that pass the row checks; a baseline is reported where lead-3 leaves sentences out; metrics are the scores that the
    pair allows: ROUGE by the tokens of its summary, factuality where that has a number to check."""
    p = sieve.Sieve(dedup=None).label_rows(MAPPINGS["headline_body"](spark, sf))
    s = F.col("summary")
    allows = {"rouge1": F.size(tokens(s)) >= 1, "rouge2": F.size(tokens(s)) >= 2, "rougeL": F.size(tokens(s)) >= 1, "factuality": s.rlike("[0-9]")}
    return p.select(
        F.col("pair_id").cast("string").alias("system"), (F.col("split") != "train").alias("published"), (F.col("verdict") == "valid").alias("public"),
        (F.size(sentences(F.col("reference"))) > 3).alias("reports_baseline"), F.array_compact(F.array(*(F.when(c, F.lit(n)) for n, c in allows.items()))).alias("metrics"),
    )


def habits(spark: SparkSession, sf: str) -> DataFrame:
    """The checklist over the records of evaluation that the documents stand for."""
    return scores.evaluation_audit(reports(spark, sf))


def train_shift(spark: SparkSession, sf: str, names: tuple[str, ...] = ("headline_body", "mixed_news")) -> DataFrame:
    """Lengths before and after on the training splits of the corpora that lose most and still have pairs left."""
    out = None
    for n in names:
        one = review.shift(labelled(spark, sf, n).where("split = 'train'")).select(F.lit(n).alias("corpus"), "max_gap", "mean_change")
        out = one if out is None else out.unionByName(one)
    return out


def other_domain(spark: SparkSession, sf: str) -> DataFrame:
    """The ratio of one corpus applied to another."""
    return scores.table(scored(spark, sf, "prompt_reply", "headline_body").where("split = 'test' and system = 'lead_k'"), ["system", "split"])


def failure_cases(spark: SparkSession, sf: str, name: str = "mixed_news") -> DataFrame:
    """Per system: mean copied prefix, repetition, loop periods, share of the output that is a subsequence of the
    reference, copied outputs, new bigrams, unsupported items, outputs beyond the context."""
    from pairlens.functions.udfs import lcs_length, loop_length

    all_ = labelled(spark, sf, name)
    o = run_systems(all_.where("split <> 'train' and verdict <> 'empty'"), all_.where("verdict = 'valid'"))
    ref, out = F.col("reference"), F.col("output")
    return o.groupBy("system").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.avg(scores.prefix_copy(ref, out)), 4).alias("prefix_copy"), F.round(F.avg(scores.repetition(out)), 4).alias("repetition"),
        F.round(F.avg(loop_length(tokens(out))), 4).alias("loop_periods"), F.round(F.avg(F.try_divide(lcs_length(tokens(ref), tokens(out)).cast("double"), F.size(tokens(out)).cast("double"))), 4).alias("lcs_share"),
        F.round(F.avg(checks.fully_extractive(ref, out, "token_run").cast("double")), 4).alias("copied"),
        F.round(F.avg(scores.novelty(ref, out, 2)["novel_share"]), 4).alias("novel_bigrams"), F.round(F.avg(scores.unsupported(ref, out)), 4).alias("unsupported"), F.count_if(scores.context_overflow(out)).alias("too_long"),
    )


def label_agreement(spark: SparkSession, sf: str) -> DataFrame:
    """Verdicts against human quality labels."""
    v = labelled(spark, sf, "headline_body").select(F.col("pair_id").alias("doc_id"), "verdict")
    return v.join(load(spark, sf, "labels"), "doc_id").groupBy("verdict").agg(F.count_if(F.col("quality") == 0).alias("bad"), F.count_if(F.col("quality") == 1).alias("good"))


def leakage(spark: SparkSession, sf: str) -> DataFrame:
    return dedup.leakage(MAPPINGS["headline_body"](spark, sf))
