"""Quality rules with risk-controlled thresholds, with DataFrame functions only.

Every text is measured once. Each rule rejects a document whose measure is above
a cutoff. Labelled documents are dealt by a hash of their id into a tuning half,
which proposes for each stratum and rule the cutoff of the best gain, and a
holdout half, which certifies: rules are taken in order of gain, and for the
union of the first r the exact binomial probability of seeing no more rejected
good documents than were seen, were the true rate RISK, must be at most DELTA
over the number of tests of all strata (Bonferroni). The largest certified union
is in force; with probability 1 - DELTA no stratum loses more than RISK of its
good documents to the rules. A stratum with too few labels has no rule in force.

Defined cases: a null or empty text has no words, measures 0 and fails the base
test; a null stratum is a stratum; labels that are null or of unknown documents
are not used, of repeated ones the lowest counts; rows that repeat a doc_id are
each judged; an empty table gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import let, unit_draw, words, written

WINDOW, FEWEST_WORDS, MOST_REPEATED = 8, 20, 30
RISK, DELTA, BAD_PER_GOOD = 0.02, 0.05, 50
#: Rules: the measure, and the cutoffs among which the tuning half chooses.
RULES = {
    "symbol_share": (0.01, 0.02, 0.05, 0.1, 0.15, 0.2, 0.25, 0.3),
    "capital_share": (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8),
    "repeat_share": (0.02, 0.05, 0.1, 0.15, 0.2, 0.25),
    "dup_line_share": (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9),
    "word_length": (7.0, 7.5, 8.0, 8.5, 9.0, 10.0, 12.0, 16.0),
}


def repeated_words(listed: Column, width: int = WINDOW) -> Column:
    """How many words stand in windows of ``width`` words that the list has twice or more.

    Windows are hashes of word hashes. Lists whose windows all differ, nearly all
    of them, end at a hash set; the others sort (hash, place) and add up what the
    places of equal neighbours cover. The cost is n log n in the words of one text.
    """

    def cover(windows: Column) -> Column:
        placed = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        twice = lambda s: F.filter(F.transform(s, lambda x, j: F.when((x["h"] == F.get(s, j + 1)["h"]) | F.coalesce(x["h"] == F.get(s, j - 1)["h"], F.lit(False)), x["i"])), lambda i: i.isNotNull())
        spans = lambda p: F.transform(p, lambda i, j: F.least(F.lit(width), F.coalesce(F.get(p, j + 1) - i, F.lit(width))))
        places = let(placed, twice)
        return F.aggregate(let(F.sort_array(places), spans), F.lit(0), lambda a, x: a + x)

    def count(windows: Column) -> Column:
        return F.when(F.size(F.array_distinct(windows)) == F.size(windows), F.lit(0)).otherwise(cover(windows))

    hashes = F.transform(listed, lambda w: F.xxhash64(w))
    windows = lambda h: F.transform(F.sequence(F.lit(1), F.size(h) - (width - 1)), lambda i: F.xxhash64(F.slice(h, i, width)))
    return F.when(F.size(listed) < width, F.lit(0)).otherwise(let(let(hashes, windows), count))


COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_capitals")


def with_measures(docs: DataFrame) -> tuple[DataFrame, str]:
    """docs with the counts, shares and base test of every text, and the prefix of these columns' names, which clash with none of docs'."""
    prefix = "q_"
    while any(c.lower().startswith(prefix) for c in docs.columns):
        prefix = f"_{prefix}"
    text = F.coalesce(F.col("text"), F.lit(""))
    only = lambda kinds: F.length(F.regexp_replace(text, f"[^{kinds}]+", ""))
    wordy = F.filter(F.split(text, "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    counts = let(words(F.col("text")), lambda w: F.struct(F.size(w).alias("n"), F.length(F.array_join(w, "")).alias("chars"), repeated_words(w).alias("again")))
    lines = let(wordy, lambda x: F.struct(F.size(x).alias("n"), (F.size(x) - F.size(F.array_distinct(x))).alias("dup")))
    row = docs.select("*", *[c.alias(prefix + name) for c, name in ((counts, "c"), (lines, "l"), (only("#*$%&|<>"), "s"), (only("A-Z"), "k"))])
    own = ("c.n", "c.chars", "s", "l.dup", "c.again", "l.n", "k")
    flat = row.select(*docs.columns, *[F.col(prefix + c).cast("long").alias(prefix + name) for c, name in zip(own, COUNTS, strict=True)])
    share = lambda a, b: F.when(F.col(prefix + b) > 0, F.col(prefix + a) / F.col(prefix + b)).otherwise(F.lit(0.0))
    shares = {"symbol_share": share("n_symbols", "word_chars"), "capital_share": share("n_capitals", "word_chars"), "repeat_share": share("n_repeat_words", "n_words"), "dup_line_share": share("n_dup_lines", "n_lines"), "word_length": share("word_chars", "n_words")}
    failed = (F.col(prefix + "n_words") < FEWEST_WORDS) | (100 * F.col(prefix + "n_repeat_words") > MOST_REPEATED * F.col(prefix + "n_words"))
    return flat.withColumns({prefix + n: c for n, c in shares.items()}).withColumn(prefix + "base_failed", failed), prefix


def measures(docs: DataFrame, stratum: str = "lang") -> DataFrame:
    """doc_id, stratum, counts, shares and base_failed of every text, written once as narrow rows."""
    rows, prefix = with_measures(docs.select("doc_id", F.col(stratum).alias("stratum"), "text"))
    return written(rows.select("doc_id", "stratum", *[F.col(prefix + c).alias(c) for c in (*COUNTS, *RULES, "base_failed")]), "measures")


def as_likely(seen: Column, of: Column, rate: float) -> Column:
    """P(Binomial(of, rate) <= seen), exactly; 1 where seen is above the mean and the bound can't hold.

    Terms are added as logarithms from the first on, so no size underflows.
    """
    odds = math.log(rate / (1 - rate))
    first = of * F.lit(math.log1p(-rate))

    def add(a: Column, j: Column) -> Column:
        term = a["term"] + F.log((of - j + 1) / j) + odds
        high = F.greatest(a["total"], term)
        return F.struct(term.alias("term"), (high + F.log(F.exp(a["total"] - high) + F.exp(term - high))).alias("total"))

    total = F.aggregate(F.sequence(F.lit(1).cast("long"), seen), F.struct(first.alias("term"), first.alias("total")), add, lambda a: a["total"])
    return F.when(of <= 0, F.lit(1.0)).when(seen > of * rate, F.lit(1.0)).when(seen == 0, F.exp(first)).otherwise(F.exp(total))


def cutoffs(measured: DataFrame, labels: DataFrame, risk: float = RISK, delta: float = DELTA, rules: dict = RULES) -> DataFrame:
    """stratum and in_force, an array of (rule, cutoff): what the labels certify."""
    label = labels.where(F.col("doc_id").isNotNull() & F.col("quality").isNotNull()).groupBy("doc_id").agg((F.min("quality") > 0).alias("good"))
    half = (unit_draw(F.lit("holdout"), "doc_id") < 0.5).alias("holdout")
    known = written(measured.where(~F.col("base_failed")).join(label, "doc_id").select("stratum", "good", half, *rules), "labelled")
    above = lambda rule: F.struct(F.lit(rule).alias("rule"), F.size(F.filter(F.array(*map(F.lit, rules[rule])), lambda c: F.col(rule) > c)).alias("step"))
    steps = known.where(~F.col("holdout")).select("stratum", "good", F.inline(F.array(*map(above, rules)))).where("step > 0")
    counted = steps.groupBy("stratum", "rule", "step").agg(F.count_if("good").alias("good"), F.count_if(~F.col("good")).alias("bad"))
    reach = Window.partitionBy("stratum", "rule").orderBy(F.col("step").desc())
    gain = F.sum(F.col("bad") - BAD_PER_GOOD * F.col("good")).over(reach)
    at = F.create_map(*[x for r, cs in rules.items() for x in (F.lit(r), F.array(*map(F.lit, cs)))])
    best = counted.withColumn("gain", gain).where("gain > 0").groupBy("stratum", "rule").agg(F.max(F.struct("gain", "step")).alias("best"))
    proposed = best.select("stratum", F.struct((-F.col("best.gain")).alias("loss"), "rule", F.element_at(at[F.col("rule")], F.col("best.step")).alias("cutoff")).alias("x")).groupBy("stratum").agg(F.sort_array(F.collect_list("x")).alias("proposed"))
    # a stratum has at most one proposal for each rule, so the list above is no longer than RULES
    tested = proposed.join(known.where("holdout and good"), proposed["stratum"].eqNullSafe(known["stratum"]), "left").select(proposed["stratum"], "proposed", "good", *rules)
    hit = F.array_position(F.transform(F.col("proposed"), lambda p: F.coalesce(rejects(p, rules), F.lit(False))), F.lit(True))
    first = tested.groupBy("stratum", "proposed", hit.alias("first")).agg(F.count("good").alias("n"))
    tallies = first.groupBy("stratum", "proposed").agg(F.sum("n").alias("of"), F.collect_list(F.struct("first", "n")).alias("hits"))
    tests = F.lit(len(rules)) * F.sum(F.lit(1)).over(Window.partitionBy())
    upto = lambda r: F.aggregate(F.filter(F.col("hits"), lambda h: (h["first"] > 0) & (h["first"] <= r)), F.lit(0).cast("long"), lambda a, h: a + h["n"])
    passed = F.filter(F.sequence(F.lit(1), F.size("proposed")), lambda r: let(upto(r), lambda k: as_likely(k, F.col("of"), risk)) <= F.lit(delta) / F.col("tests"))
    sure = tallies.withColumn("tests", tests).withColumn("rank", F.coalesce(F.array_max(passed), F.lit(0)))
    return sure.select("stratum", F.transform(F.slice("proposed", F.lit(1), F.col("rank")), lambda p: F.struct(p["rule"].alias("rule"), p["cutoff"].alias("cutoff"))).alias("in_force"))


def rejects(rule: Column, rules: dict = RULES, prefix: str = "") -> Column:
    """Whether a (rule, cutoff) rejects the row."""
    value = F.lit(None).cast("double")
    for name in rules:
        value = F.when(rule["rule"] == name, F.col(prefix + name)).otherwise(value)
    return value > rule["cutoff"]


def verdicts(measured: DataFrame, force: DataFrame, stratum: str, prefix: str = "") -> DataFrame:
    """measured with kept; what is in force, a row for each stratum, is a written table whose size the planner knows."""
    of, rules, kept = prefix + "of", prefix + "in_force", prefix + "kept"
    joined = measured.join(force.toDF(of, rules), F.col(stratum).eqNullSafe(F.col(of)), "left")
    out = F.coalesce(F.exists(rules, lambda r: rejects(r, prefix=prefix)), F.lit(False))
    return joined.withColumn(kept, ~F.col(prefix + "base_failed") & ~out).drop(of, rules)


def judged(docs: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = RISK, delta: float = DELTA) -> DataFrame:
    """The measures of each document with base_failed and kept."""
    measured = measures(docs, stratum)
    return verdicts(measured, written(cutoffs(measured, labels, risk, delta), "cutoffs"), "stratum")


def quality_filter(docs: DataFrame, labels: DataFrame, stratum: str = "lang") -> DataFrame:
    """docs without the rows that the base test or a rule in force rejects; same columns.

    Rows are measured once and written with their measures. A verdict follows from
    the row and its stratum's cutoffs, so no text is shuffled, and no list of ids is joined.
    """
    rows, prefix = with_measures(docs)
    rows = written(rows, "measured")
    measured = rows.select("doc_id", F.col(stratum).alias("stratum"), *[F.col(prefix + c).alias(c) for c in (*COUNTS, *RULES, "base_failed")])
    force = written(cutoffs(measured, labels), "cutoffs")
    return verdicts(rows, force, stratum, prefix).where(F.col(prefix + "kept")).select(*docs.columns)
