"""Duplicates across a corpus of pairs: detection, order-respecting removal and other strategies.

Rows travel as (pair_id, rank, two fingerprints): texts are never shuffled.
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from pairlens.functions.text import fingerprint
from pairlens.session import checkpointed

ORDER = ("test", "validation", "train")


def prints(pairs: DataFrame, split_order: tuple[str, ...] = ORDER, scope: str = "corpus", algo: str = "md5") -> DataFrame:
    """pair_id, split, seq, rank (place of the split, seq, pair_id), fr, fs. With scope split, splits don't see each
    other. A pair without a text on a side has nothing to compare: it is left out here, so no strategy keeps it."""
    at = F.lit(len(split_order))
    for i, s in reversed(list(enumerate(split_order))):
        at = F.when(F.col("split") == s, i).otherwise(at)
    mark = (lambda c: F.concat(F.coalesce("split", F.lit("")), F.lit(":"), c)) if scope == "split" else (lambda c: c)
    whole = pairs.where(F.col("reference").isNotNull() & F.col("summary").isNotNull())
    return whole.select("pair_id", "split", "seq", F.struct(at.alias("at"), "seq", "pair_id").alias("rank"), mark(fingerprint(F.col("reference"), algo=algo)).alias("fr"), mark(fingerprint(F.col("summary"), algo=algo)).alias("fs"))


def groups(pairs: DataFrame, side: str) -> DataFrame:
    """Groups of more than one pair with the same text on a side (reference, summary) or both (exact)."""
    p = prints(pairs)
    keys = {"exact": ["fr", "fs"], "reference": ["fr"], "summary": ["fs"]}[side]
    other = {"exact": "fr", "reference": "fs", "summary": "fr"}[side]
    out = p.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.min("seq").alias("first_seq"), F.count_distinct(other).alias("n_other"))
    return out.where((F.col("n") > 1) & ((F.col("n_other") > 1) if side != "exact" else F.lit(True)))


def cross(pairs: DataFrame) -> DataFrame:
    """Pairs whose both texts came earlier, but never together."""
    p = prints(pairs)
    r = p.groupBy("fr").agg(F.min("rank").alias("r1"))
    s = p.groupBy("fs").agg(F.min("rank").alias("s1"))
    e = p.groupBy("fr", "fs").agg(F.min("rank").alias("e1"))
    return p.join(r, "fr").join(s, "fs").join(e, ["fr", "fs"]).where("r1 < rank and s1 < rank and e1 = rank").select("pair_id", "split", "seq")


#: Rounds of the additive removal before what is open is finished component by component.
ROUNDS = 6
#: Pairs of a component that one task may pass in order; larger components go on in rounds.
COMPONENT_PAIRS = 1_000_000


def _text_components(pairs: DataFrame) -> DataFrame:
    """(fr, component) of pairs linked by a text on either side: stars of texts point to ever smaller ones, so a chain
    ends in about the logarithm of its length."""
    edges = checkpointed(pairs.select(F.concat(F.lit("r"), "fr").alias("x"), F.concat(F.lit("s"), "fs").alias("y")).distinct())
    before = None
    while True:
        for large in (True, False):
            both = edges.unionByName(edges.select(F.col("y").alias("x"), F.col("x").alias("y"))) if large else edges.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y"))
            hubs = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
            seen = both.join(hubs, "x")
            pointed = seen.where("y > x") if large else seen
            out = pointed.select(F.col("y").alias("x"), F.col("m").alias("y"))
            edges = checkpointed((out if large else out.unionByName(hubs.select("x", F.col("m").alias("y")))).where("x <> y").distinct())
        state = tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("x", "y").cast("decimal(20,0)"))).first())
        if state == before:
            break
        before = state
    named = edges.select("x", F.col("y").alias("component")).unionByName(edges.select(F.col("y").alias("x"), F.col("y").alias("component")).distinct())
    return named.where("x like 'r%'").select(F.substring("x", 2, 1 << 30).alias("fr"), "component")


def _in_order(group: pd.DataFrame) -> pd.DataFrame:
    """The sequential pass over one component."""
    refs, summs, won = set(), set(), []
    for fr, fs in zip(group["fr"], group["fs"], strict=True):
        won.append(fr not in refs and fs not in summs)
        if won[-1]:
            refs.add(fr)
            summs.add(fs)
    return group[won]


def _finished(open_: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(pairs admitted, pairs still open): components of a size that one task may hold are passed in order."""
    parts = checkpointed(open_.join(_text_components(open_), "fr"))
    small = parts.groupBy("component").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") <= COMPONENT_PAIRS).select("component")
    sorted_ = parts.join(small, "component", "left_semi").select("component", "fr", "fs", "rank.at", "rank.seq", "rank.pair_id")
    fields = {f.name: f.dataType.simpleString() for f in sorted_.schema.fields}

    def run(group: pd.DataFrame) -> pd.DataFrame:
        return _in_order(group.sort_values(["at", "seq", "pair_id"], kind="stable"))

    done = sorted_.groupBy("component").applyInPandas(run, ", ".join(f"{k} {v}" for k, v in fields.items()))
    won = done.select("fr", "fs", F.struct("at", "seq", "pair_id").alias("rank"))
    return checkpointed(won), checkpointed(parts.join(small, "component", "left_anti").select("fr", "fs", "rank"))


def additive(pairs: DataFrame, split_order: tuple[str, ...] = ORDER, scope: str = "corpus", rounds: int = ROUNDS) -> DataFrame:
    """pair_id, verdict, blocker_ref, blocker_summ: starts empty and admits a pair when neither of its texts is in yet.

    A pair that is first among the open ones on both sides can't be blocked, so each round admits all such pairs at
    once and rejects those that share a text with them; the result is that of the sequential pass. Few rounds do on
    real orders; long chains of alternating texts that are open after so many are passed in order, each component in
    one task. A pair with a null text is admitted never and blocks nothing: its verdict is missing.
    """
    all_ = checkpointed(prints(pairs, split_order, scope))
    open_ = all_.groupBy("fr", "fs").agg(F.min("rank").alias("rank"))  # of exact copies only the first can be admitted
    kept, i, finished = None, 0, False
    while True:
        i += 1
        if i > rounds and not finished:
            won, open_ = _finished(open_)
            finished = True
        else:
            lr = open_.groupBy("fr").agg(F.min("rank").alias("lr"))
            ls = open_.groupBy("fs").agg(F.min("rank").alias("ls"))
            won = checkpointed(open_.join(lr, "fr").join(ls, "fs").where("rank = lr and rank = ls").select("fr", "fs", "rank"))
            open_ = checkpointed(open_.join(won.select("fr"), "fr", "left_anti").join(won.select("fs"), "fs", "left_anti"))
        kept = won if kept is None else kept.unionByName(won)
        if open_.isEmpty():
            break
    kept = checkpointed(kept)
    by_ref = kept.select("fr", F.col("rank.pair_id").alias("blocker_ref"), F.col("rank").alias("rank_ref"))
    by_summ = kept.select("fs", F.col("rank.pair_id").alias("blocker_summ"), F.col("rank").alias("rank_summ"))
    out = all_.join(by_ref, "fr", "left").join(by_summ, "fs", "left")
    r, s = F.col("rank_ref") < F.col("rank"), F.col("rank_summ") < F.col("rank")
    r, s = F.coalesce(r, F.lit(False)), F.coalesce(s, F.lit(False))
    me = F.coalesce(F.col("rank_ref") == F.col("rank"), F.lit(False))
    verdict = F.when(me, "valid").when(r & s & (F.col("rank_ref") == F.col("rank_summ")), "exact").when(r & s, "cross_both").when(r, "dup_reference").otherwise("dup_summary")
    judged = out.select("pair_id", verdict.alias("verdict"), F.when(~me & r, F.col("blocker_ref")).alias("blocker_ref"), F.when(~me & s, F.col("blocker_summ")).alias("blocker_summ"))
    none = F.lit(None).cast(judged.schema["blocker_ref"].dataType)
    missing = pairs.where(F.col("reference").isNull() | F.col("summary").isNull()).select("pair_id", F.lit("missing").alias("verdict"), none.alias("blocker_ref"), none.alias("blocker_summ"))
    return judged.unionByName(missing)


def keep(pairs: DataFrame, strategy: str = "additive", split_order: tuple[str, ...] = ORDER, scope: str = "corpus") -> DataFrame:
    """pair_id of the pairs that a strategy keeps: additive, first_occurrence, exact, drop_all or keep_longest. Pairs
    with a null text are kept by none."""
    if strategy == "additive":
        return additive(pairs, split_order, scope).where("verdict = 'valid'").select("pair_id")
    p = prints(pairs, split_order, scope)
    match strategy:
        case "first_occurrence":
            r, s = p.groupBy("fr").agg(F.min("rank").alias("r1")), p.groupBy("fs").agg(F.min("rank").alias("s1"))
            return p.join(r, "fr").join(s, "fs").where("rank = r1 and rank = s1").select("pair_id")
        case "exact":
            return p.groupBy("fr", "fs").agg(F.min_by("pair_id", "rank").alias("pair_id")).select("pair_id")
        case "drop_all":
            r, s = p.groupBy("fr").count().where("count > 1").select("fr"), p.groupBy("fs").count().where("count > 1").select("fs")
            return p.join(r, "fr", "left_anti").join(s, "fs", "left_anti").select("pair_id")
        case "keep_longest":
            sized = pairs.select("pair_id", F.length("reference").alias("size")).join(p, "pair_id")
            return sized.groupBy("fs").agg(F.min_by("pair_id", F.struct((-F.col("size")).alias("size"), "rank")).alias("pair_id")).select("pair_id")
    raise ValueError(f"unknown strategy {strategy}")


def compare(pairs: DataFrame, strategies: tuple[str, ...] = ("additive", "first_occurrence", "exact", "drop_all", "keep_longest")) -> DataFrame:
    out = None
    for s in strategies:
        one = pairs.select("pair_id", "split").join(keep(pairs, s), "pair_id", "left_semi").groupBy("split").agg(F.count(F.lit(1)).alias("kept")).select(F.lit(s).alias("strategy"), "split", "kept")
        out = one if out is None else out.unionByName(one)
    return out


def leakage(pairs: DataFrame) -> DataFrame:
    """Texts that stand in several splits: side, the splits, and how many texts."""
    p = prints(pairs)
    both = p.select("split", F.lit("reference").alias("side"), F.col("fr").alias("f")).unionByName(p.select("split", F.lit("summary").alias("side"), F.col("fs").alias("f")))
    return both.groupBy("side", "f").agg(F.array_join(F.array_sort(F.collect_set("split")), "+").alias("splits")).where("instr(splits, '+') > 0").groupBy("side", "splits").agg(F.count(F.lit(1)).alias("n"))


def top_repeats(pairs: DataFrame, side: str = "summary", k: int = 10) -> DataFrame:
    return pairs.groupBy(F.col(side).alias("text")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").orderBy(F.desc("n"), F.md5("text")).limit(k)


def alignment_suspects(pairs: DataFrame) -> DataFrame:
    """Summaries that go with several references of one origin."""
    return pairs.groupBy("origin", fingerprint(F.col("summary")).alias("fs")).agg(F.count_distinct("reference").alias("n_references"), F.min("seq").alias("first_seq")).where("n_references > 1")


def runs_of_faults(labelled: DataFrame, min_run: int = 2, block: int = 1_000_000) -> DataFrame:
    """Runs of neighbours in storage order that all fail; the order is cut in blocks of seq, so no task gets it all, and
    runs over an edge of blocks are put together again (at most two pieces a block)."""
    b = F.floor(F.col("seq") / block)
    w = W.partitionBy("block").orderBy("seq")
    marked = labelled.select("seq", "verdict", b.alias("block")).withColumn("bad", F.col("verdict") != "valid")
    v = W.partitionBy("block", "bad").orderBy("seq")
    ends = W.partitionBy("block")
    isles = marked.withColumn("isle", F.row_number().over(w) - F.row_number().over(v)).withColumn("lo", F.min("seq").over(ends)).withColumn("hi", F.max("seq").over(ends))
    # pieces that don't fail stay in until they have parted those that do
    pieces = isles.groupBy("block", "bad", "isle").agg(F.min("seq").alias("first_seq"), F.max("seq").alias("last_seq"), F.count(F.lit(1)).alias("n"), F.first("lo").alias("lo"), F.first("hi").alias("hi"))
    inner = F.col("bad") & (F.col("first_seq") > F.col("lo")) & (F.col("last_seq") < F.col("hi"))
    edge = pieces.where((F.col("first_seq") == F.col("lo")) | (F.col("last_seq") == F.col("hi")))
    order = W.orderBy("first_seq")
    joined = (F.col("first_seq") == F.col("lo")) & F.lag("bad").over(order) & F.col("bad")
    edge = edge.withColumn("run", F.sum(F.when(joined, 0).otherwise(1)).over(order)).where("bad")
    whole = edge.groupBy("run").agg(F.min("first_seq").alias("first_seq"), F.max("last_seq").alias("last_seq"), F.sum("n").alias("n"))
    return pieces.where(inner).select("first_seq", "last_seq", "n").unionByName(whole.select("first_seq", "last_seq", "n")).where(F.col("n") >= min_run)
