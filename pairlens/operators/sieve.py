"""The sieve: ordered checks, the first that fails names the pair; then duplicates among those that pass."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from pairlens.functions import checks as C
from pairlens.operators import dedup

VERDICTS = ("empty", "ref_short", "summ_short", "identical", "low_cr", "high_cr", "extractive", "exact", "cross_both", "dup_reference", "dup_summary", "valid")


@dataclass(frozen=True)
class Profile:
    """Limits of a domain. news: 50 and 20 characters; instructions: 20 and 8."""

    min_ref: int = 50
    min_summ: int = 20
    min_cr: float = 1.25
    max_cr: float | None = None
    unit: str = "char"

    @classmethod
    def news(cls) -> Profile:
        return cls()

    @classmethod
    def instructions(cls) -> Profile:
        return cls(20, 8)


@dataclass(frozen=True)
class Sieve:
    profile: Profile = field(default_factory=Profile)
    level: str = "missing"
    mode: str = "substring"
    dedup: str | None = "additive"
    split_order: tuple[str, ...] = ("test", "validation", "train")
    scope: str = "corpus"
    #: Limits by a column's value: {value: Profile}; others have the sieve's profile.
    by: tuple[str, dict[str, Profile]] | None = None

    def _limit(self, name: str) -> Column:
        out = F.lit(getattr(self.profile, name))
        for value, p in (self.by[1] if self.by else {}).items():
            out = F.when(F.col(self.by[0]) == value, F.lit(getattr(p, name))).otherwise(out)
        return out

    def flags(self) -> dict[str, Column]:
        """Every check on its own, in order."""
        r, s, p = F.col("reference"), F.col("summary"), self.profile
        out = {
            "empty": C.is_empty(r, s, self.level), "ref_short": C.too_short(r, self._limit("min_ref"), p.unit), "summ_short": C.too_short(s, self._limit("min_summ"), p.unit),
            "identical": C.identical(r, s), "low_cr": F.coalesce(C.n_units(r, p.unit).cast("double") < C.n_units(s, p.unit) * self._limit("min_cr").cast("double"), F.lit(False)),
            "extractive": C.fully_extractive(r, s, self.mode),
        }
        if p.max_cr:
            out["high_cr"] = C.extreme_compression(r, s, p.max_cr, p.unit)
        return out

    def row_verdict(self) -> Column:
        """The first check that fails, else valid: one CASE, cheap tests first, the search for the copy last."""
        out = F.lit("valid")
        f = self.flags()
        for name in [n for n in ("empty", "ref_short", "summ_short", "identical", "low_cr", "high_cr", "extractive") if n in f][::-1]:
            out = F.when(f[name], name).otherwise(out)
        return out

    def label_rows(self, pairs: DataFrame) -> DataFrame:
        return pairs.withColumn("verdict", self.row_verdict())

    def label(self, pairs: DataFrame) -> DataFrame:
        """pairs with verdict."""
        rows = self.label_rows(pairs)
        if not self.dedup:
            return rows
        passed = rows.where("verdict = 'valid'")
        if self.dedup == "additive":
            d = dedup.additive(passed, self.split_order, self.scope).select("pair_id", F.col("verdict").alias("d"))
        else:
            d = passed.select("pair_id").join(dedup.keep(passed, self.dedup, self.split_order, self.scope), "pair_id", "left_anti").select("pair_id", F.lit(self.dedup).alias("d"))
        return rows.join(d, "pair_id", "left").withColumn("verdict", F.coalesce("d", "verdict")).drop("d")

    def clean(self, pairs: DataFrame) -> DataFrame:
        return self.label(pairs).where("verdict = 'valid'").drop("verdict")


def funnel(labelled: DataFrame, corpus: str, bold_share: float = 0.02, fold: bool = False) -> DataFrame:
    """corpus, split, verdict, n, share of the split, bold (a reject above the share). fold counts cross_both as exact."""
    v = F.when(F.col("verdict") == "cross_both", "exact").otherwise(F.col("verdict")) if fold else F.col("verdict")
    n = labelled.groupBy("split", v.alias("verdict")).agg(F.count(F.lit(1)).alias("n"))
    total = n.groupBy("split").agg(F.sum("n").alias("total"))
    share = F.col("n") / F.col("total")
    return n.join(F.broadcast(total), "split").select(F.lit(corpus).alias("corpus"), "split", "verdict", "n", F.round(share, 6).alias("share"), ((F.col("verdict") != "valid") & (share > bold_share)).alias("bold"))


def observed(labelled: DataFrame) -> tuple[DataFrame, Observation]:
    """The rows as they are, with an observation that holds the counts of verdicts once they have been written."""
    seen = Observation()
    return labelled.observe(seen, F.count(F.lit(1)).alias("n"), *(F.count_if(F.col("verdict") == v).alias(v) for v in VERDICTS)), seen


def grid(spark: SparkSession, first: float = 1.0, step: float = 0.25, ratios: int = 4, least: int = 20, wider: int = 15, lengths: int = 3) -> DataFrame:
    """min_cr, min_ref: every setting of a sweep, from a range."""
    i = F.col("id")
    return spark.range(ratios * lengths).select(F.round(first + (i % ratios) * step, 6).alias("min_cr"), (least + F.floor(i / ratios) * wider).cast("int").alias("min_ref"))


def passing(pairs: DataFrame, settings: DataFrame) -> DataFrame:
    """min_cr, min_ref, passing: the pairs that both limits of a setting let through. Only a pair's two lengths meet the
    settings, of which there is a handful."""
    sized = pairs.select(F.length("reference").alias("lr"), F.length("summary").alias("ls"))
    through = (F.col("lr") >= F.col("min_ref")) & (F.col("lr").cast("double") >= F.col("ls") * F.col("min_cr"))
    n = sized.crossJoin(F.broadcast(settings)).groupBy("min_cr", "min_ref").agg(F.count_if(through).alias("n"))
    return settings.join(n, ["min_cr", "min_ref"], "left").select("min_cr", "min_ref", F.coalesce("n", F.lit(0)).alias("passing"))


def wide_funnel(labelled: DataFrame) -> DataFrame:
    """A row per split, a column per verdict."""
    return labelled.groupBy("split").pivot("verdict", list(VERDICTS)).agg(F.count(F.lit(1))).na.fill(0)


def affected(labelled: DataFrame, corpus: str) -> DataFrame:
    bad = F.avg((F.col("verdict") != "valid").cast("double"))
    return labelled.agg(F.count(F.lit(1)).alias("n"), F.round(bad, 6).alias("share")).select(F.lit(corpus).alias("corpus"), "n", "share", (F.col("share") > 0.25).alias("over_quarter"), (F.col("share") > 0.5).alias("over_half"))


def sweep(pairs: DataFrame, min_cr: list[float], min_ref: list[int]) -> DataFrame:
    """Rejects of each setting in one pass: the grid is a handful of rows beside each pair's two lengths."""
    grid = F.array(*(F.struct(F.lit(float(c)).alias("min_cr"), F.lit(m).alias("min_ref")) for c in min_cr for m in min_ref))
    sized = pairs.select(F.coalesce(F.length("reference"), F.lit(0)).alias("lr"), F.coalesce(F.length("summary"), F.lit(0)).alias("ls"), F.explode(grid).alias("g")).select("lr", "ls", "g.*")
    return sized.groupBy("min_cr", "min_ref").agg(F.count_if(F.col("lr") < F.col("min_ref")).alias("ref_short"), F.count_if(F.col("lr").cast("double") < F.col("ls") * F.col("min_cr")).alias("low_cr"))


def ablate(pairs: DataFrame, sieve: Sieve) -> DataFrame:
    """Pairs that pass when one row check is left out, from one pass over all flags."""
    f = sieve.flags()
    flagged = pairs.select(*(c.alias(n) for n, c in f.items()))
    names = list(f)
    passes = {"none": names, **{n: [m for m in names if m != n] for n in names}}
    row = flagged.agg(*(F.count_if(~_any(ms)).alias(n) for n, ms in passes.items()))
    return row.unpivot([], list(passes), "left_out", "passing")


def _any(names: list[str]) -> Column:
    out = F.col(names[0])
    for n in names[1:]:
        out = out | F.col(n)
    return out
