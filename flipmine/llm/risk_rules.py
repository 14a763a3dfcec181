"""Quality rules with risk-controlled cutoffs: exact binomial bounds on labelled documents, per stratum.

DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

#: The shares that are tried as cutoffs, for every rule.
GRID = (0.01, 0.02, 0.03, 0.05, 0.08, 0.1, 0.15, 0.2, 0.25, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9)
#: The rules: a name and the share that it looks at, high being bad.
SHARES = ("symbols", "bangs", "capitals", "dup_lines", "repeats")
#: All rules together reject at most this share of a stratum's good documents, ...
RISK = 0.02
#: ... in all strata at once, but for this probability.
DOUBT = 0.05
#: One of so many good documents helps to order the cutoffs; the others test them.
GUIDES = 4
#: Cutoffs of so many strata at most are broadcast; beyond it they are joined.
MOST_BROADCAST = 50_000

SPACES = "[\\x20\\x09-\\x0D]"


def _matches(text: str, pattern: str) -> Column:
    return F.regexp_count(text, F.lit(pattern)).cast("long")


def measured(documents: DataFrame, keep: tuple[str, ...]) -> DataFrame:
    """The ``keep`` columns and the measures of every whole text; a null text has no words.

    Windows of three words are compared by 64-bit hashes. Only texts in which some window occurs again
    take the longer way of sorting their windows.
    """
    rows = documents.select(*keep, F.coalesce(F.col("text").cast("string"), F.lit("")).alias("whole"))
    rows = rows.select(
        *keep,
        F.filter(F.split("whole", SPACES + "+"), lambda w: w != "").alias("words"),
        F.filter(F.split("whole", "\n"), lambda line: line.rlike("[^\\x20\\x09-\\x0D]")).alias("lines"),
        _matches("whole", "[#*$%&|<>]").alias("n_symbols"), _matches("whole", "!").alias("n_bangs"), _matches("whole", "[A-Z]").alias("n_capitals"),
    )
    rows = rows.select(
        *keep, "words", "n_symbols", "n_bangs", "n_capitals",
        F.size("words").cast("long").alias("n_words"), F.char_length(F.array_join("words", "")).cast("long").alias("word_chars"),
        F.size("lines").cast("long").alias("n_lines"), (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
    )
    last = F.greatest(F.size("words") - 3, F.lit(0))
    window = lambda i: F.xxhash64(F.get("words", i), F.get("words", i + 1), F.get("words", i + 2))
    rows = rows.withColumn("windows", F.when(F.size("words") >= 3, F.transform(F.sequence(F.lit(0), last), window)).otherwise(F.array().cast("array<bigint>"))).drop("words")
    again = F.size(F.array_distinct("windows")) < F.size("windows")
    rows = rows.withColumn("ordered", F.when(again, F.array_sort(F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))).drop("windows")
    rows = rows.withColumn("places", F.array_sort(F.transform(F.filter("ordered", lambda x, j: F.coalesce(x["h"] == F.get("ordered", j - 1)["h"], F.lit(False)) | F.coalesce(x["h"] == F.get("ordered", j + 1)["h"], F.lit(False))), lambda x: x["i"]))).drop("ordered")
    covered = F.aggregate(F.transform("places", lambda p, j: F.least(F.lit(3), F.coalesce(F.get("places", j + 1) - p, F.lit(3)))), F.lit(0), lambda a, x: a + x)
    return rows.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("places")


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def shares() -> dict[str, Column]:
    part = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    return {"symbols": part("n_symbols", "word_chars"), "bangs": part("n_bangs", "word_chars"), "capitals": part("n_capitals", "word_chars"), "dup_lines": part("n_dup_lines", "n_lines"), "repeats": part("n_repeat_words", "n_words")}


def step(share: Column) -> Column:
    """How many cutoffs of the grid the share reaches."""
    return sum((F.when(share >= g, 1).otherwise(0) for g in GRID), F.lit(0))


def binomial_tail(n: Column, k: Column, risk: float) -> Column:
    """Probability of ``k`` or fewer of ``n`` at rate ``risk``; 1 where k lies above the mean, where no bound can hold."""
    from math import log

    odds = log(risk) - log(1 - risk)
    start = F.struct((n * log(1 - risk)).alias("term"), F.exp(n * log(1 - risk)).alias("sum"))

    def add(state: Column, i: Column) -> Column:
        term = state["term"] + F.log((n - i + 1) / i) + odds
        return F.struct(term.alias("term"), (state["sum"] + F.exp(term)).alias("sum"))

    summed = F.aggregate(F.when(k >= 1, F.sequence(F.lit(1).cast("long"), k)).otherwise(F.array().cast("array<bigint>")), start, add, lambda s: s["sum"])
    return F.when(k > n * risk, F.lit(1.0)).otherwise(summed)


def cutoffs(labelled: DataFrame, risk: float = RISK, doubt: float = DOUBT) -> DataFrame:
    """Per stratum and rule the step of the grid from which documents are rejected.

    ``labelled`` has doc_id, stratum, quality (1 good, 0 bad) and the measures. A stratum's cutoffs stand in one
    sequence, each rule's from the mildest on, and a test asks whether all up to a place reject together
    more than ``risk`` of the good documents (exact binomial, Clopper-Pearson). The sequence ends at the first place
    that is not safe, so its tests share nothing; strata share ``doubt`` evenly. The order comes from bad
    documents and from good ones that take no part in the tests: most further bad documents for each good one
    first. Cutoffs that reject no bad document beyond the base rules and the places before are left out. A
    stratum whose good documents could not show a cutoff safe even if none were rejected gets none and has no part of ``doubt``.
    """
    from math import log

    good = F.col("quality") == 1
    guide = F.crc32(F.concat(F.lit("guide"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))) % GUIDES == 0
    count = lambda of, name: F.sum(of.cast("long")).alias(name)
    # counts of each combination of steps first: few rows per stratum beside the documents
    steps = F.array(*(step(share).cast("int") for share in shares().values()))
    counts = labelled.withColumn("steps", steps).groupBy("stratum", "steps").agg(count(~good & ~base_failed(), "bad"), count(good & guide, "guides"), count(good & ~guide, "good"))
    counts = stored(counts, "quality-steps")
    totals = counts.groupBy("stratum").agg(F.sum("good").alias("n")).where(F.col("n") * log(1 - risk) <= log(doubt))
    tests = totals.count()
    if not tests:
        return labelled.sparkSession.createDataFrame([], "stratum string, rule string, cut int")
    reached = counts.join(totals, "stratum").select("*", F.posexplode("steps").alias("rule", "step")).where("step > 0").withColumn("cut", F.explode(F.sequence(F.lit(1), "step")))
    milder = Window.partitionBy("stratum", "rule").orderBy(F.desc("cut"))
    each = reached.groupBy("stratum", "rule", "cut").agg(F.sum("bad").alias("bad"), F.sum("guides").alias("guides"))
    each = each.withColumn("before", F.coalesce(F.lag("bad").over(milder), F.lit(0))).where("bad > before")
    each = each.withColumn("worth", F.min(F.col("bad") / (F.col("guides") + 1)).over(milder))
    order = each.select("stratum", "rule", "cut", F.row_number().over(Window.partitionBy("stratum").orderBy(F.desc("worth"), "rule", F.desc("cut"))).alias("place"))

    def at_first(order: DataFrame, what: str) -> DataFrame:
        """Documents of a kind by the first place of ``order`` that rejects them."""
        chain = order.groupBy("stratum").agg(F.collect_list(F.struct("rule", "cut", "place")).alias("chain"))
        first = F.array_min(F.transform(F.filter("chain", lambda x: F.get("steps", x["rule"]) >= x["cut"]), lambda x: x["place"]))
        return counts.join(chain, "stratum").select("stratum", first.alias("place"), what).groupBy("stratum", "place").agg(F.sum(what).alias(what))

    order = stored(order, "quality-order")
    order = stored(order.join(at_first(order, "bad").where("bad > 0"), ["stratum", "place"], "left_semi"), "quality-useful")
    rejected = at_first(order, "good")
    upto = Window.partitionBy("stratum").orderBy("place")
    k = F.sum(F.coalesce("good", F.lit(0).cast("long"))).over(upto)
    tested = order.join(rejected, ["stratum", "place"], "left").join(totals, "stratum").withColumn("k", k)
    # the more good documents are rejected the greater the tail, so all safe places come before the first that is not
    safe = tested.where(binomial_tail(F.col("n"), F.col("k"), risk) <= doubt / tests)
    names = F.array(*map(F.lit, SHARES))
    return safe.groupBy("stratum", F.get(names, F.col("rule")).alias("rule")).agg(F.min("cut").alias("cut"))


def judged(documents: DataFrame, labels: DataFrame, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """Measures, base_failed and kept for each row of ``documents`` (doc_id, text, lang; others are ignored).

    Strata are languages; a null one is a stratum of its own. ``labels`` has doc_id and quality; where
    a document has several, the worst counts; null doc_ids match none. Texts are read once; the measures,
    a few numbers per document, are stored, and labels and cutoffs are joined to them. An empty or
    null text fails the base rules. Without labels no cutoff is safe and the base rules decide alone.
    """
    own = tuple(dict.fromkeys((*keep, "doc_id")))
    rows = measured(documents.withColumn("stratum", F.coalesce(F.col("lang").cast("string"), F.lit(""))), (*own, "stratum"))
    rows = stored(rows.withColumns({"base_failed": base_failed()} | {f"step_{name}": step(share).cast("int") for name, share in shares().items()}), "quality-measures")
    known = labels.where(F.col("quality").isin(0, 1)).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min("quality").cast("long").alias("quality"))
    cuts = stored(cutoffs(rows.drop(*(c for c in own if c != "doc_id")).join(known, "doc_id")), "quality-cutoffs")
    wide = cuts.groupBy("stratum").agg(*(F.max(F.when(F.col("rule") == name, F.col("cut"))).alias(f"cut_{name}") for name in SHARES))
    if wide.count() <= MOST_BROADCAST:
        wide = F.broadcast(wide)
    rejected = F.lit(False)
    for name in SHARES:
        rejected = rejected | F.coalesce(F.col(f"step_{name}") >= F.col(f"cut_{name}"), F.lit(False))
    return rows.join(wide, "stratum", "left").select(
        *own, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & ~rejected).alias("kept")
    )
