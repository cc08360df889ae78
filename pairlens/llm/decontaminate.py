"""Benchmark decontamination by templates: numbers, names and units become typed slots, windows of the result are
hash-joined with the benchmark's, and the values in the slots must map consistently. DataFrame functions only."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pairlens.llm.shared import Scratch

# Unit words that count as a unit after a number.
UNITS = (
    "mm cm dm m km in inch inches ft foot feet yd yard yards mi mile miles mg g kg t lb lbs oz ml cl l liter liters litre litres gal gallon gallons s sec second seconds min minute minutes h hr hour hours day days week weeks month months year years "
    "usd eur gbp dollar dollars euro euros cent cents pound pounds percent degree degrees w kw mw v a hz khz mhz ghz kb mb gb tb kmh mph celsius fahrenheit meter meters metre metres kilometer kilometers kilometre kilometres gram grams kilogram kilograms"
).split()
NUMBER, NAME, UNIT = "§d", "§n", "§u"
#: Words with a capital in a row from which a text's windows are also hashed as spelled.
CAPITALS = 4


@dataclass(frozen=True)
class Settings:
    #: Words in a window; a shorter item has itself as its window, if it has the shortest length or more.
    window: int = 8
    shortest: int = 5
    #: Share of an item's words that windows must cover on one alignment.
    cover: float = 0.5
    #: Share of the item's slot values that must go to one value each.
    consistent: float = 0.9
    #: Most benchmark windows that are broadcast; more are joined by a shuffle.
    broadcast_windows: int = 1_000_000


def _words(text: Column, slots: bool) -> Column:
    """Words in lower case without punctuation; with slots, those that stand for a number or unit are replaced and
    those that may be a name are marked.
    Both forms have a word at the same places: a word is never added, and goes only if it is all punctuation."""
    t = text
    if slots:
        t = F.regexp_replace(t, r"(?<![^\s(\[\"'$€£+-])[$€£+-]?\d[\d.,:/]*(?:st|nd|rd|th|%)?(?![\p{L}\d])", NUMBER)
        t = F.regexp_replace(t, rf"(?i)(?<={NUMBER}\s)(?:{'|'.join(sorted(UNITS, key=lambda u: (-len(u), u)))})(?![\p{{L}}\d])", UNIT)
        # a capital may start a name, at the start of a sentence as well: the word stays behind its mark
        t = F.regexp_replace(t, r"(?<![\p{L}\p{N}§])(\p{Lu}[\p{L}'-]*)", NAME + "$1")
    t = F.regexp_replace(F.lower(t), r"[^\p{L}\p{N}§\s]+", "")
    return F.filter(F.split(t, r"\s+"), lambda w: w != "")


def _slotted(w: Column) -> Column:
    """A marked name as a slot."""
    return F.when(w.startswith(NAME), F.lit(NAME)).otherwise(w)


def _named(w: Column) -> Column:
    """A marked name as its word."""
    return F.when(w.startswith(NAME), F.substr(w, F.lit(len(NAME) + 1))).otherwise(w)


def is_slot(w: Column) -> Column:
    return w.isin(NUMBER, NAME, UNIT)


def _all(conditions) -> Column:
    out = F.lit(True)
    for x in conditions:
        out = out & x
    return out


def _windows(hashes: str, lengths: list[int]) -> Column:
    """(length, place, hash) of every window of these lengths over an array column of word hashes."""
    h, per = F.col(hashes), []
    for n in lengths:
        per.append(F.when(F.size(h) >= n, _hashed(h, F.sequence(F.lit(0), F.size(h) - n), n)).otherwise(F.array().cast("array<struct<p:int,w:bigint>>")))
    return F.flatten(F.array(*per)) if len(per) > 1 else per[0]


def _hashed(h: Column, at: Column, n: int) -> Column:
    return F.transform(at, lambda i: F.struct(i.alias("p"), F.xxhash64(F.lit(n), *(F.get(h, i + j) for j in range(n))).alias("w")))


def contaminated(docs: DataFrame, benchmark: DataFrame, settings: Settings | None = None, text: str = "text", key: str = "doc_id", item: str = "item_id", item_text: str = "text", scratch: Scratch | None = None) -> DataFrame:
    """One row per document and item found in it: key, item, at (word of the document at which the item would start),
    covered, item_words, n_slots, n_consistent.

    A document holds an item if, on one alignment, windows with equal templates cover the set share of the item's
    words and the values in the item's slots go to one value each, up to the set share. Documents without hits give no
    row; null and empty texts have no windows; an item with fewer words than the shortest is left out. Rows with equal
    keys count as one document. Windows of slots alone don't count, as tables of figures have many of them.
    """
    c = settings or Settings()
    spark = docs.sparkSession
    s = scratch or Scratch(spark, "templates")
    items = benchmark.select(F.col(item).alias("item"), _words(F.coalesce(F.col(item_text), F.lit("")), True).alias("marked"), _words(F.coalesce(F.col(item_text), F.lit("")), False).alias("values"))
    items = items.where(F.size("marked") >= c.shortest).withColumn("size", F.size("marked")).dropDuplicates(["item"])
    items = items.select("item", "size", "values", F.transform("marked", _slotted).alias("template"), F.transform("marked", _named).alias("spelled"))
    items = s.keep(items.withColumn("h", F.transform("template", lambda w: F.xxhash64(w))).withColumn("hs", F.transform("spelled", lambda w: F.xxhash64(w))), "items")
    lengths = sorted(r[0] for r in items.select(F.least("size", F.lit(c.window))).distinct().collect())  # at most window of them
    nothing = f"{key} {docs.schema[key].dataType.simpleString()}, {item} {benchmark.schema[item].dataType.simpleString()}, at int, covered int, item_words int, n_slots int, n_consistent int"
    if not lengths:
        return spark.createDataFrame([], nothing)
    # windows with names as slots, and with names spelled out for texts in other letter cases
    kinds = [items.select("item", F.col(words).alias("words"), "size", F.explode(_windows(h, lengths)).alias("x")) for words, h in (("template", "h"), ("spelled", "hs"))]
    own = kinds[0].unionByName(kinds[1]).select("item", F.col("x.p").alias("q"), F.col("x.w").alias("w"), F.least("size", F.lit(c.window)).alias("n"), "words")
    own = own.where(F.exists(F.slice("words", F.col("q") + 1, F.col("n")), lambda w: ~is_slot(w))).select("item", "q", "w", "n").distinct()
    own = s.keep(own, "item-windows")
    small = own.count() <= c.broadcast_windows
    marked = docs.select(F.col(key).alias("doc"), _words(F.coalesce(F.col(text), F.lit("")), True).alias("m"))
    # where capitals follow one another (titles, capital letters throughout) words are spelled out as well
    starts = F.when(F.size("m") >= CAPITALS, F.sequence(F.lit(0), F.size("m") - CAPITALS)).otherwise(F.array().cast("array<int>"))
    in_a_row = F.filter(starts, lambda i: _all(F.get("m", i + j).startswith(NAME) for j in range(CAPITALS)))
    hashed = marked.select("doc", "m", F.transform("m", lambda w: F.xxhash64(_slotted(w))).alias("h"), in_a_row.alias("capitals"))
    hashed = hashed.select("doc", "h", "capitals", F.when(F.size("capitals") > 0, F.transform("m", lambda w: F.xxhash64(_named(w)))).otherwise(F.array().cast("array<bigint>")).alias("hs"))
    spelled = [_hashed(F.col("hs"), F.filter("capitals", lambda i, n=n: i <= F.size("hs") - n), n) for n in lengths]
    seen = hashed.select("doc", F.explode(F.concat(_windows("h", lengths), *spelled)).alias("x")).select("doc", F.col("x.p").alias("p"), F.col("x.w").alias("w"))
    hits = seen.join(F.broadcast(own) if small else own, "w").select("doc", "item", (F.col("p") - F.col("q")).alias("at"), "q", "n")
    # places of a window covered by hits on one alignment: the union of [q, q + n), taken from sorted places
    run = hits.groupBy("doc", "item", "at").agg(F.array_sort(F.collect_set("q")).alias("qs"), F.first("n").alias("n"))
    run = run.withColumn("covered", F.aggregate("qs", F.struct(F.lit(0).alias("sum"), F.lit(-1_000_000).alias("last")), lambda a, q: F.struct((a["sum"] + F.least(F.col("n"), q - a["last"])).alias("sum"), q.alias("last")), lambda a: a["sum"]))
    side = items.select("item", "size", F.size(F.filter("template", is_slot)).alias("slots"))
    found = run.join(F.broadcast(side) if small else side, "item").where(F.col("covered") >= c.cover * F.col("size"))
    found = s.keep(found.select("doc", "item", "at", "covered", "size", "slots"), "found")
    plain = found.where("slots = 0").select("doc", "item", "at", "covered", "size", "slots", F.lit(0).alias("kept_slots"))
    asked = s.keep(found.where("slots > 0"), "asked")
    texts = docs.select(F.col(key).alias("doc"), F.col(text).alias("text")).join(asked.select("doc").distinct(), "doc", "left_semi").dropDuplicates(["doc"])
    values = texts.select("doc", _words(F.coalesce("text", F.lit("")), False).alias("theirs"))
    checked = asked.join(values, "doc").join(items.select("item", "template", "values"), "item")
    # each slot's value here and there; a value of the item that meets two values of the document is inconsistent
    slots = F.filter(F.transform(F.sequence(F.lit(0), F.col("size") - 1), lambda i: F.struct(F.get("template", i).alias("kind"), F.get("values", i).alias("mine"), F.when(F.col("at") + i >= 0, F.get("theirs", F.col("at") + i)).alias("yours"))), lambda x: is_slot(x["kind"]) & x["yours"].isNotNull())
    checked = checked.withColumn("pairs", F.array_distinct(F.transform(slots, lambda x: F.struct(x["mine"], x["yours"]))))
    checked = checked.withColumn("mine", F.array_distinct(F.transform("pairs", lambda x: x["mine"])))
    ok = F.filter("mine", lambda m: F.size(F.filter("pairs", lambda x: x["mine"] == m)) == 1)
    checked = checked.select("doc", "item", "at", "covered", "size", F.size("mine").alias("slots"), F.size(ok).alias("kept_slots")).where(F.col("kept_slots") >= c.consistent * F.col("slots"))
    out = plain.unionByName(checked).groupBy("doc", "item").agg(F.max(F.struct("covered", (-F.col("at")).alias("back"), "size", "slots", "kept_slots")).alias("b"))
    return out.select(F.col("doc").alias(key), F.col("item").alias(item), (-F.col("b.back")).cast("int").alias("at"), F.col("b.covered").alias("covered"), F.col("b.size").alias("item_words"), F.col("b.slots").alias("n_slots"), F.col("b.kept_slots").alias("n_consistent"))
