"""Scores of system outputs: ROUGE as an Arrow kernel and as relational plans, aggregates, bootstrap, comparisons."""

from __future__ import annotations

import time

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlens.functions import kernels as K
from pairlens.functions.text import ngrams, tokens, words

SCORES = "struct<r1_p double, r1_r double, r1_f double, r2_p double, r2_r double, r2_f double, rl_p double, rl_r double, rl_f double>"


def rouge(pred: Column, target: Column, stem: str | None = "de", ascii_only: bool = False) -> Column:
    """R-1, R-2 and R-L in one pass; an empty side scores 0."""

    def run(a: pd.Series, b: pd.Series) -> pd.DataFrame:
        rows = []
        for x, y in zip(a, b, strict=True):
            p, t = K.tokenize(x, stem, ascii_only), K.tokenize(y, stem, ascii_only)
            rows.append((*K.rouge_n(p, t, 1), *K.rouge_n(p, t, 2), *K.rouge_l(p, t)))
        return pd.DataFrame(rows, columns=[x.split()[0] for x in SCORES[7:-1].split(", ")], dtype=float)

    return F.pandas_udf(run, SCORES.replace("struct<", "").rstrip(">"))(pred, target)


#: Characters of the shorter side up to which a pair's grams are matched inside its row.
ROW_CHARS = 20_000


def relational_rouge(pairs: DataFrame, pred: str, target: str, n: int, key: str = "pair_id", row_chars: int = ROW_CHARS) -> DataFrame:
    """ROUGE-n without Python. Both sides of a pair are in one row, so grams are counted and clipped there, without an
    exchange; pairs whose shorter side is long are exploded and joined, as matching in a row takes the square."""
    short = F.coalesce(F.least(F.length(pred), F.length(target)), F.lit(0)) <= row_chars
    grams = lambda c: F.coalesce(ngrams(tokens(F.col(c)), n), F.array().cast("array<string>"))
    both = pairs.where(short).select(key, grams(pred).alias("x"), grams(target).alias("y"))
    times = lambda c, g: F.size(F.filter(c, lambda w: w == g))
    hit = F.aggregate(F.array_intersect("x", "y"), F.lit(0), lambda s, g: s + F.least(times(F.col("x"), g), times(F.col("y"), g)))
    out = both.select(key, hit.alias("hit"), F.size("x").alias("na"), F.size("y").alias("nb"))
    out = out.unionByName(_joined_grams(pairs.where(~short), pred, target, n, key))
    p, r = F.coalesce(F.try_divide("hit", "na"), F.lit(0.0)), F.coalesce(F.try_divide("hit", "nb"), F.lit(0.0))
    f = F.coalesce(F.try_divide(2 * p * r, p + r), F.lit(0.0))
    return out.select(key, F.round(p, 6).alias("p"), F.round(r, 6).alias("r"), F.round(f, 6).alias("f"))


def _joined_grams(pairs: DataFrame, pred: str, target: str, n: int, key: str) -> DataFrame:
    """key, hit, na, nb: the grams of both sides met by a join."""
    side = lambda c, name: pairs.select(key, F.explode(ngrams(tokens(F.col(c)), n)).alias("g")).groupBy(key, "g").agg(F.count(F.lit(1)).alias(name))
    both = side(pred, "a").join(side(target, "b"), [key, "g"], "full").groupBy(key).agg(F.sum(F.least(F.coalesce("a", F.lit(0)), F.coalesce("b", F.lit(0)))).alias("hit"), F.sum("a").alias("na"), F.sum("b").alias("nb"))
    return pairs.select(key).join(both, key, "left")


def timed(name: str, outputs: DataFrame, parameters: int | None = None) -> dict:
    """Seconds and outputs a second of a system, beside its size: the other side of its scores."""
    began, seen = time.perf_counter(), Observation()
    outputs.observe(seen, F.count(F.lit(1)).alias("n")).write.format("noop").mode("overwrite").save()
    took = time.perf_counter() - began
    return {"system": name, "outputs": seen.get["n"], "seconds": took, "per_second": seen.get["n"] / took, "parameters": parameters}


def table(scores: DataFrame, by: list[str]) -> DataFrame:
    """Macro averages x 100 of the F1 columns r1, r2, rl."""
    return scores.groupBy(*by).agg(F.count(F.lit(1)).alias("n"), *(F.round(100 * F.avg(m), 4).alias(m) for m in ("r1", "r2", "rl")))


def bootstrap(scores: DataFrame, value: str, by: list[str], key: str = "pair_id", n: int = 2000, confidence: float = 0.95, seed: int = 0) -> DataFrame:
    """Percentiles of resampled means. Each row has its own Poisson weight in every replica, drawn from its key, so
    partial sums can be made anywhere and the result doesn't depend on the partitioning."""
    lo, hi = (1 - confidence) / 2, (1 + confidence) / 2

    def partial(batches):
        for pdf in batches:
            for group, rows in pdf.groupby(by, dropna=False) if by else [((), pdf)]:
                s, w = np.zeros(n), np.zeros(n)
                for k, v in zip(rows[key], rows[value], strict=True):
                    x = np.random.Generator(np.random.PCG64([seed, int(k) & 0xFFFFFFFF, int(k) >> 32 & 0xFFFFFFFF])).poisson(1.0, n)
                    s, w = s + x * v, w + x
                yield pd.DataFrame({**dict(zip(by, [[g] for g in group], strict=True)), "replica": [list(range(n))], "s": [s.tolist()], "w": [w.tolist()]})

    fields = ", ".join(f"{b} {scores.schema[b].dataType.simpleString()}" for b in by)
    sums = scores.select(*by, key, F.col(value).cast("double").alias(value)).mapInPandas(partial, f"{fields}{', ' * bool(by)}replica array<int>, s array<double>, w array<double>")
    each = sums.select(*by, F.explode(F.arrays_zip("replica", "s", "w")).alias("z")).select(*by, "z.*").groupBy(*by, "replica").agg((F.sum("s") / F.sum("w")).alias("m"))
    return each.groupBy(*by).agg(*(F.round(F.percentile("m", F.lit(q)), 6).alias(a) for a, q in (("low", lo), ("mid", 0.5), ("high", hi))))


#: Rows of a block whose redraws one task makes.
BLOCK_ROWS = 50_000


def bootstrap_draws(scores: DataFrame, value: str, by: list[str], key: str = "pair_id", n: int = 2000, confidence: float = 0.95, seed: int = 0) -> DataFrame:
    """Percentiles of the means of n samples redrawn from the rows with replacement, each as large as the rows.

    Rows are dealt in blocks by a hash of their key. How many of a sample's draws fall in each block is one multinomial
    draw, which every block of a group makes alike from the seed; the draws inside a block are its own. So the samples
    are those of drawing from all rows at once, and no task holds more than a block. Null values are left out.
    """
    rows = scores.select(*by, key, F.col(value).cast("double").alias("v")).where("v is not null")
    rows = rows.withColumn("one", F.lit(1))
    group = [*by, "one"]
    counts = rows.groupBy(*group).agg(F.ceil(F.count(F.lit(1)) / BLOCK_ROWS).cast("int").alias("blocks"))
    dealt = rows.join(counts, group).withColumn("block", F.pmod(F.xxhash64(key), F.col("blocks")).cast("int"))
    sizes = dealt.groupBy(*group, "block").agg(F.count(F.lit(1)).alias("size"))
    whole = sizes.groupBy(*group).agg(F.array_sort(F.collect_list(F.struct("block", "size"))).alias("sizes"))
    keys = [F.col(b).alias(f"of_{b}") for b in (*group, "block")]
    plan = sizes.select(*group, "block").join(whole, group).select(*keys, F.transform("sizes", lambda x: x["block"]).alias("ids"), F.transform("sizes", lambda x: x["size"]).alias("sizes"))

    def draw(own: pd.DataFrame, how: pd.DataFrame) -> pd.DataFrame:
        sizes_, ids = np.array(how["sizes"].iloc[0], float), list(how["ids"].iloc[0])
        block, v = int(how["of_block"].iloc[0]), own.sort_values(key, kind="stable")["v"].to_numpy()
        share = np.random.Generator(np.random.PCG64([seed, 1])).multinomial(int(sizes_.sum()), sizes_ / sizes_.sum(), size=n)[:, ids.index(block)]
        rng = np.random.Generator(np.random.PCG64([seed, 2, block]))
        sums = [float(v[rng.integers(0, len(v), m)].sum()) for m in share.tolist()]
        return pd.DataFrame({**{b: [how[f"of_{b}"].iloc[0]] for b in group}, "s": [sums], "total": [int(sizes_.sum())]})

    fields = ", ".join(f"{b} {rows.schema[b].dataType.simpleString()}" for b in group)
    parts = dealt.groupBy(*group, "block").cogroup(plan.groupBy(*(f"of_{b}" for b in (*group, "block")))).applyInPandas(draw, f"{fields}, s array<double>, total bigint")
    each = parts.select(*by, "total", F.posexplode("s").alias("replica", "s")).groupBy(*by, "replica").agg((F.sum("s") / F.first("total")).alias("m"))
    return each.groupBy(*by).agg(*(F.round(F.percentile("m", F.lit(q)), 6).alias(a) for a, q in (("low", (1 - confidence) / 2), ("mid", 0.5), ("high", (1 + confidence) / 2))))


def evaluation_audit(meta: DataFrame) -> DataFrame:
    """Habits of evaluation over a table of systems (system, published, public, reports_baseline, metrics): per kind of
    publication how many there are, report a baseline, go beyond n-gram scores, and are public and do so."""
    beyond = F.exists("metrics", lambda m: ~F.lower(m).rlike("^(rouge|bleu)"))
    return meta.groupBy("published").agg(
        F.count(F.lit(1)).alias("n"), F.count_if("reports_baseline").alias("with_baseline"), F.count_if(beyond).alias("beyond_ngrams"), F.count_if(F.col("public") & beyond).alias("public_beyond")
    )


def filter_effect(scores: DataFrame, metric: str = "r1") -> DataFrame:
    """system, split, unfiltered, filtered, drop, kept: scores has a row per system, split and state."""
    p = scores.groupBy("system", "split").pivot("state", ["unfiltered", "filtered"]).agg(F.first(metric))
    return p.select("system", "split", "unfiltered", "filtered", F.round(F.col("unfiltered") - F.col("filtered"), 4).alias("drop"), F.round(F.try_divide("filtered", "unfiltered"), 4).alias("kept"))


def rank_shift(scores: DataFrame, metric: str = "r1") -> DataFrame:
    e = filter_effect(scores, metric)
    rank = lambda c: F.rank().over(W.partitionBy("split").orderBy(F.desc(c)))
    return e.select("system", "split", rank("unfiltered").alias("rank_unfiltered"), rank("filtered").alias("rank_filtered")).withColumn("moved", F.col("rank_unfiltered") - F.col("rank_filtered"))


def kendall_tau(ranks: DataFrame) -> DataFrame:
    """Agreement of the two rankings per split, from pairs of systems (a handful)."""
    a, b = ranks.alias("a"), ranks.alias("b")
    j = a.join(b, (F.col("a.split") == F.col("b.split")) & (F.col("a.system") < F.col("b.system")))
    s = F.signum((F.col("a.rank_unfiltered") - F.col("b.rank_unfiltered")).cast("double")) * F.signum((F.col("a.rank_filtered") - F.col("b.rank_filtered")).cast("double"))
    return j.groupBy(F.col("a.split").alias("split")).agg(F.round(F.avg(s), 6).alias("tau"))


def mark_best(scores: DataFrame, by: list[str], metrics: tuple[str, ...] = ("r1", "r2", "rl")) -> DataFrame:
    w = W.partitionBy(*by)
    return scores.select("system", *by, *(x for m in metrics for x in (F.col(m), (F.col(m) == F.max(m).over(w)).alias(f"{m}_best"))))


def baseline_margin(scores: DataFrame, baselines: list[str], by: list[str], metric: str = "r1") -> DataFrame:
    w = W.partitionBy(*by)
    best = F.max(F.when(F.col("system").isin(baselines), F.col(metric))).over(w)
    return scores.select("system", *by, F.round(F.col(metric) - best, 4).alias("margin"))


def baseline_spread(scores: DataFrame, baselines: list[str], by: list[str], metric: str = "r1") -> DataFrame:
    return scores.where(F.col("system").isin(baselines)).groupBy(*by).agg(F.round(F.max(metric) - F.min(metric), 4).alias("spread"))


def reproduction_gap(reported: DataFrame, measured: DataFrame, by: list[str], metric: str = "r1", tolerance: float = 0.5) -> DataFrame:
    j = reported.select(*by, F.col(metric).alias("reported")).join(measured.select(*by, F.col(metric).alias("measured")), by)
    gap = F.round(F.col("reported") - F.col("measured"), 4)
    return j.select(*by, gap.alias("gap"), (F.abs(gap) <= tolerance).alias("within"))


def novelty(ref: Column, summ: Column, n: int) -> dict[str, Column]:
    mine = F.array_distinct(ngrams(tokens(summ), n))
    new = F.size(F.array_except(mine, ngrams(tokens(ref), n)))
    return {"n_grams": F.size(mine), "n_novel": new, "novel_share": F.round(F.try_divide(new.cast("double"), F.size(mine).cast("double")), 6)}


def repetition(out: Column, n: int = 3) -> Column:
    g = ngrams(tokens(out), n)
    return F.round(F.coalesce(1 - F.try_divide(F.size(F.array_distinct(g)).cast("double"), F.size(g).cast("double")), F.lit(0.0)), 6)


def prefix_copy(ref: Column, out: Column) -> Column:
    """Share of the output's tokens that equal the reference's from the start on."""
    a, b = tokens(out), tokens(ref)
    same = F.zip_with(a, F.slice(b, 1, F.greatest(F.size(a), F.lit(1))), lambda x, y: F.coalesce(x == y, F.lit(False)))
    first = F.array_position(F.slice(same, 1, F.greatest(F.size(a), F.lit(1))), F.lit(False))
    run = F.when(F.size(a) == 0, 0).when(first == 0, F.size(a)).otherwise(first - 1)
    return F.round(F.coalesce(F.try_divide(run.cast("double"), F.size(a).cast("double")), F.lit(0.0)), 6)


def context_overflow(c: Column, limit: int = 512, per_word: float = 1.0) -> Column:
    return F.size(words(c)) * F.lit(per_word) > limit


def unsupported(ref: Column, out: Column) -> Column:
    """Numbers and capitalised words of the output that the source doesn't have: a stand-in for a truth check."""
    items = lambda c: F.array_distinct(F.regexp_extract_all(c, F.lit(r"[0-9]+|[A-Z][a-z]+"), F.lit(0)))
    return F.size(F.array_except(items(out), items(ref)))
