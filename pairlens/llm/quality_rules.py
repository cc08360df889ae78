"""Quality rules: text statistics as Spark expressions and a decision list learned from labelled ones.

Statistics, training counts and verdicts are DataFrame operations; the driver only sees counts of a bounded sample.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = r"[\x20\x09-\x0D]+"
#: Statistics that conditions are made of.
FEATURES = ("n_words", "mean_word", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "upper_share", "mark_share")
#: Labelled rows that training reads at most: those with the least hashes of their keys.
SAMPLE_ROWS = 20_000
#: Thresholds tried per statistic and class.
CUTS = 24
#: Parts of the sample, each of which prunes the rules that the others grow.
FOLDS = 3


def text_stats(docs: DataFrame, text: str = "text") -> DataFrame:
    """docs with columns q_n_words, q_word_chars, q_n_symbols, q_n_dup_lines, q_n_repeat_words (long) and what further
    features need; docs itself must have no column that starts with q_. A null text counts as empty. Everything is
    worked out inside the row: nothing is shuffled.

    Words that stand in a repeated 5-word window are found by 64-bit hashes of the windows: only a text whose hashes
    are not all distinct sorts them, with their places, and looks at neighbours. Arrays stay columns of their own that
    the next step uses several times, so that the optimizer doesn't move their making into a lambda.
    """
    held, q = docs.columns, F.col
    t = F.coalesce(F.col(text), F.lit(""))
    one = docs.select(*held, t.alias("q_t"), F.filter(F.split(t, BLANKS), lambda w: w != "").alias("q_words"), F.filter(F.split(t, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("q_lines"))
    two = one.select(
        *held, F.size("q_words").cast("bigint").alias("q_n_words"), F.length(F.array_join("q_words", "")).cast("bigint").alias("q_word_chars"),
        F.length(F.regexp_replace("q_t", r"[^#*$%&|<>]+", "")).cast("bigint").alias("q_n_symbols"), F.size("q_lines").cast("bigint").alias("q_n_lines"),
        (F.size("q_lines") - F.size(F.array_distinct("q_lines"))).cast("bigint").alias("q_n_dup_lines"),
        F.length(F.regexp_replace("q_t", r"[^A-Z]+", "")).cast("bigint").alias("q_n_upper"), F.length(F.regexp_replace("q_t", r"[^!?]+", "")).cast("bigint").alias("q_n_marks"),
        F.transform("q_words", lambda w: F.xxhash64(w)).alias("q_h"),
    )
    names = ["q_n_words", "q_word_chars", "q_n_symbols", "q_n_lines", "q_n_dup_lines", "q_n_upper", "q_n_marks"]
    windows = F.transform(F.sequence(F.lit(0), F.size("q_h") - 5), lambda i: F.xxhash64(*(F.get("q_h", i + j) for j in range(5))))
    three = two.select(*held, *names, F.size(F.array_distinct("q_h")).cast("bigint").alias("q_n_distinct"), F.when(F.size("q_h") >= 5, windows).otherwise(F.array().cast("array<bigint>")).alias("q_w"))
    names.append("q_n_distinct")
    torn = F.size(F.array_distinct("q_w")) < F.size("q_w")
    four = three.select(*held, *names, F.when(torn, F.sort_array(F.transform("q_w", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))).alias("q_z"))
    twin = lambda x, i: ((i > 0) & (F.get("q_z", i - 1)["h"] == x["h"])) | F.coalesce(F.get("q_z", i + 1)["h"] == x["h"], F.lit(False))
    places = F.sort_array(F.transform(F.filter("q_z", twin), lambda x: x["i"]))
    covered = F.aggregate(places, F.struct(F.lit(0).cast("bigint").alias("n"), F.lit(-5).alias("last")), lambda a, p: F.struct((a["n"] + F.least(F.lit(5), p - a["last"])).alias("n"), p.alias("last")), lambda a: a["n"])
    return four.select(*held, *map(q, names), F.coalesce(covered, F.lit(0).cast("bigint")).alias("q_n_repeat_words"))


def features() -> dict[str, Column]:
    s = lambda c: F.col(f"q_{c}").cast("double")
    share = lambda a, b: F.coalesce(F.try_divide(s(a), s(b)), F.lit(0.0))
    return {
        "n_words": s("n_words"), "mean_word": share("word_chars", "n_words"), "symbol_share": share("n_symbols", "word_chars"), "dup_line_share": share("n_dup_lines", "n_lines"),
        "repeat_share": share("n_repeat_words", "n_words"), "distinct_share": share("n_distinct", "n_words"), "upper_share": share("n_upper", "word_chars"), "mark_share": share("n_marks", "word_chars"),
    }


def base_failed() -> Column:
    """Fixed limits that hold besides the learned list: under 10 words, or over a fifth of them in repeated windows."""
    return (F.col("q_n_words") < 10) | (100 * F.col("q_n_repeat_words") > 20 * F.col("q_n_words"))


@dataclass(frozen=True)
class Condition:
    feature: str
    above: bool
    cut: float

    def column(self) -> Column:
        f = features()[self.feature]
        return f > self.cut if self.above else f <= self.cut

    def __str__(self) -> str:
        return f"{self.feature} {'>' if self.above else '<='} {self.cut:.6g}"


@dataclass
class DecisionList:
    """Ordered rules that reject; a row that fits none is kept."""

    rules: list[list[Condition]] = field(default_factory=list)

    def column(self) -> Column:
        """The number of the first rule that fits, from 0; null for a row that is kept."""
        out = F.lit(None).cast("int")
        for i, rule in reversed(list(enumerate(self.rules))):
            fits = rule[0].column()
            for c in rule[1:]:
                fits = fits & c.column()
            out = F.when(fits, F.lit(i)).otherwise(out)
        return out

    def __str__(self) -> str:
        return "\n".join(f"reject if {' and '.join(map(str, r))}" for r in self.rules) + "\nelse keep"


def _bin(name: str, limits: list[float]) -> Column:
    """How many of the limits are below the value."""
    return F.size(F.filter(F.array(*map(F.lit, limits)), lambda x: x < F.col(name)))


def _gain(p0: int, n0: int, p: int, n: int) -> float:
    return p * (math.log2(p / (p + n)) - math.log2(p0 / (p0 + n0))) if p else 0.0


def _covers(rule: list[tuple[int, bool, int]], bins: tuple) -> bool:
    return all((bins[f] > b) == above for f, above, b in rule)


def _found(rule: list, cells: list[tuple]) -> tuple[int, int]:
    """Bad and good rows that a rule covers."""
    got = [c for c in cells if _covers(rule, c[0])]
    return sum(c[1] for c in got), sum(c[2] for c in got)


def _grow(cells: list[tuple], n_features: int, most: int) -> list[tuple[int, bool, int]]:
    """Adds the condition with the most information gain until no good row is covered or nothing helps."""
    rule: list[tuple[int, bool, int]] = []
    while len(rule) < most:
        p0, n0 = sum(c[1] for c in cells), sum(c[2] for c in cells)
        if not p0 or not n0:
            break
        top = (0.0, None)
        for f in range(n_features):
            sums: dict[int, list[int]] = {}
            for bins, p, n, _ in cells:
                s = sums.setdefault(bins[f], [0, 0])
                s[0], s[1] = s[0] + p, s[1] + n
            p = n = 0
            for b in sorted(sums)[:-1]:
                p, n = p + sums[b][0], n + sums[b][1]
                top = max(top, (_gain(p0, n0, p, n), (f, False, b)), (_gain(p0, n0, p0 - p, n0 - n), (f, True, b)), key=lambda x: x[0])
        if top[1] is None:
            break
        rule.append(top[1])
        cells = [c for c in cells if _covers([top[1]], c[0])]
    return rule


def _prune(rule: list, cells: list[tuple]) -> list:
    """The shortest head of the rule that does best on rows it was not grown on."""
    best: tuple = (-2.0, [])
    for k in range(1, len(rule) + 1):
        p, n = _found(rule[:k], cells)
        value = (p - n) / (p + n) if p + n else -1.0
        if value > best[0] + 1e-9:
            best = (value, rule[:k])
    return best[1]


def _best(cells: list[tuple], n_features: int, most: int, precision: float, enough: int) -> list:
    """Each fold in turn prunes what the others grew, so few labels serve both ends; of the rules that are precise
    enough on their own fold and on all rows, the one that finds most bad rows."""
    found: list[tuple] = []
    for fold in range(FOLDS):
        held, grown = [c for c in cells if c[3] == fold], [c for c in cells if c[3] != fold]
        rule = _prune(_grow(grown, n_features, most), held)
        if rule:
            (p, n), (p_all, n_all) = _found(rule, held), _found(rule, cells)
            if p and p >= precision * (p + n) and p_all >= enough and p_all >= precision * (p_all + n_all):
                found.append((p_all - n_all, -len(rule), fold, rule))
    return max(found)[-1] if found else []


def learn(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", label: str = "quality", sample_rows: int = SAMPLE_ROWS, cuts: int = CUTS, precision: float = 0.95, most_rules: int = 12, most_conditions: int = 4) -> DecisionList:
    """A list that rejects rows like those labelled 0: sequential covering over the rows that the fixed limits keep.
    Each rule is grown on two folds and pruned on the third; the list ends when no rule is precise enough and finds
    at least three bad rows (or a hundredth of them). A threshold stands midway between the two values it parts.

    At most sample_rows labelled rows are read, a bound that doesn't depend on the corpus; without labels of both kinds
    the list is empty. A key with several labels counts once, with the least. Rows with null labels are left out.
    """
    chosen = labels.where(F.col(label).isNotNull()).groupBy(key).agg((F.min(label) == 0).alias("bad")).orderBy(F.xxhash64(key), key).limit(sample_rows)
    # the limit above is this broadcast's size bound
    own = docs.select(key, text).join(F.broadcast(chosen), key).select(F.col(key).alias("key"), F.col(text).alias("text"), "bad")
    values = text_stats(own).select("bad", base_failed().alias("failed"), F.pmod(F.xxhash64("key", F.lit(7)), F.lit(FOLDS)).alias("fold"), "key", *(c.alias(n) for n, c in features().items()))
    held = values.repartition(4, "key").persist()
    values = held.where(~F.col("failed"))  # above what is held: below, it would work the statistics out once more
    try:
        at = [i / (cuts + 1) for i in range(1, cuts + 1)] + [1.0]
        # bad rows may be few: each class has cuts of its own
        rows = values.groupBy("bad").agg(*(F.percentile_approx(n, at, 10_000).alias(n) for n in FEATURES)).collect()
        if len(rows) < 2:
            return DecisionList()
        limits = {n: sorted({float(x) for r in rows for x in r[n]}) for n in FEATURES}
        place = [_bin(n, limits[n]).alias(n) for n in FEATURES]
        counted = values.select("bad", "fold", *place).groupBy("fold", *FEATURES).agg(F.sum(F.col("bad").cast("int")).alias("p"), F.sum((~F.col("bad")).cast("int")).alias("n")).collect()
        ends = values.select(F.explode(F.array(*(F.struct(F.lit(i).alias("f"), _bin(n, limits[n]).alias("b"), F.col(n).alias("x")) for i, n in enumerate(FEATURES)))).alias("z")).groupBy("z.f", "z.b").agg(F.min("z.x").alias("lo"), F.max("z.x").alias("hi")).collect()
    finally:
        held.unpersist()
    # bins: x has bin b if b of the limits are below it; bin > k means x > limits[k]
    cells = [(tuple(r[n] for n in FEATURES), r["p"], r["n"], r["fold"]) for r in counted]
    span = {(r["f"], r["b"]): (r["lo"], r["hi"]) for r in ends}

    def midway(f: int, b: int) -> float:
        below, above = [hi for (g, k), (_, hi) in span.items() if g == f and k <= b], [lo for (g, k), (lo, _) in span.items() if g == f and k > b]
        mid = (max(below) + min(above)) / 2
        short = float(f"{mid:.6g}")
        return short if max(below) <= short < min(above) else mid

    out, enough = DecisionList(), max(3, sum(c[1] for c in cells) // 100)
    while len(out.rules) < most_rules:
        rule = _best(cells, len(FEATURES), most_conditions, precision, enough)
        if not rule:
            break
        out.rules.append([Condition(FEATURES[f], above, midway(f, b)) for f, above, b in rule])
        cells = [c for c in cells if not _covers(rule, c[0])]
    return out


def judge(docs: DataFrame, rules: DecisionList, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs' key, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, rule (number of the learned
    rule that rejects, else null), kept. Row by row; repeated rows and null keys are judged like others."""
    stats = text_stats(docs.select(F.col(key).alias("key"), F.col(text).alias("text")))
    out = stats.select("key", *(F.col(f"q_{n}").alias(n) for n in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), base_failed().alias("base_failed"), rules.column().alias("rule"))
    return out.withColumn("kept", ~F.col("base_failed") & F.col("rule").isNull()).withColumnRenamed("key", key)


def keep_good(docs: DataFrame, rules: DecisionList, text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that neither the fixed limits nor a learned rule reject."""
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("row"), F.col(text).alias("text"))
    # a condition is moved below what it is made of, which would work all statistics out once per use; a column that
    # isn't deterministic holds it in place
    out = text_stats(packed).select("row", base_failed().alias("failed"), rules.column().alias("rule"), F.monotonically_increasing_id().alias("place"))
    return out.where(~F.col("failed") & F.col("rule").isNull() & (F.col("place") >= 0)).select("row.*")
