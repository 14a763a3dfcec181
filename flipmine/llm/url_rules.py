"""URL filter: explicit host and path rules first, then association rules that FP-growth mines from labelled URLs.

DataFrame functions only; FP-growth is Spark's own and runs in the JVM.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

#: The explicit rules as (verdict, host, path).
RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: A mined rule fits so many blocked URLs and this share of all labelled ones at least, and is right for this share of those it fits.
LEAST_URLS, MIN_SUPPORT, MIN_CONFIDENCE = 20, 0.002, 0.8
#: A blocked URL offers so many tokens to FP-growth: those of most confidence by themselves. It has 2**10 sets of them at most; where a URL has more tokens to offer, ``levels`` finds the rest.
OFFERED = 10
#: So many rules at most are broadcast to the URLs' token sets; more are joined.
MOST_BROADCAST = 100_000

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def parsed(urls: DataFrame) -> DataFrame:
    """Adds host, path and tokens. A null url or one without ``://`` has an empty host and path and no tokens."""
    url = F.coalesce(F.col("url").cast("string"), F.lit(""))
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(coalesce(url, ''), locate('://', coalesce(url, '')) + 3)")).otherwise("")
    with_rest = urls.withColumn("rest", rest).withColumn("raw_host", F.regexp_extract("rest", "^[^/?#]*", 0))
    after = F.expr("substring(rest, length(raw_host) + 1)")
    cut = with_rest.withColumns({"host": F.translate("raw_host", _UPPER, _LOWER), "path": F.regexp_extract(after, "^[^?#]*", 0), "tail": F.translate(after, _UPPER, _LOWER)})
    words = lambda text, sep: F.filter(F.split(text, sep), lambda w: (w != "") & ~w.rlike("^[0-9]+$"))
    mark = lambda tokens, kind: F.transform(tokens, lambda t: F.concat(F.lit(kind), t))
    tokens = F.array_sort(F.array_distinct(F.concat(mark(words("host", "[.:-]+"), "h:"), mark(words("tail", "[^a-z0-9_]+"), "p:"))))
    return cut.withColumn("tokens", tokens).drop("rest", "raw_host", "tail")


def explicit(rules: tuple[tuple[str, str, str], ...] = RULES) -> tuple[Column, Column]:
    """The longest rule that fits host or a parent domain and begins the path, and its verdict; both null if none fits."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for kind, host, path in sorted(rules, key=lambda r: len(r[1] + r[2])):
        fits = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
        rule, verdict = F.when(fits, host + path).otherwise(rule), F.when(fits, kind).otherwise(verdict)
    return rule, verdict


def fitting(sets: DataFrame, rules: DataFrame) -> DataFrame:
    """``sets`` (tokens) with each of ``rules`` (wanted, anchor) that has all its tokens there.

    The index leads from a rule's rarest token, its anchor, to the rule; the other tokens are then looked up in the set.
    """
    met = sets.withColumn("anchor", F.explode("tokens")).join(rules, "anchor")
    return met.where(F.forall("wanted", lambda t: F.array_contains("tokens", t)))


def counted(rows: DataFrame, sets: DataFrame, each: DataFrame) -> DataFrame:
    """(wanted, anchor, n, bad): labelled and blocked URLs of ``rows`` (tokens, n, bad) that hold all tokens of each of ``sets`` (wanted)."""
    rarity = sets.select("wanted", F.explode("wanted").alias("token")).join(each.select("token", "n"), "token")
    anchored = rarity.groupBy("wanted").agg(F.min_by("token", F.struct("n", "token")).alias("anchor"))
    return fitting(rows, anchored).groupBy("wanted", "anchor").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))


def levels(rows: DataFrame, each: DataFrame, floor: int, min_confidence: float) -> DataFrame:
    """All rules (wanted, anchor, n, bad) of two tokens and more that hold no other one, however many tokens URLs have.

    Level by level: a set is looked at if all its sets of one token less are frequent and no rules. A set that stands
    for the same URLs as one of those is not extended, for what would follow from it follows from the
    shorter set too; tokens that always go together therefore cost no sets of their own.
    """
    front = each.where(F.col("bad") < min_confidence * F.col("n")).select(F.array("token").alias("wanted"), "n")
    out = rows.select(F.col("tokens").alias("wanted"), F.lit("").alias("anchor"), "n", "bad").limit(0)
    while True:
        ends = front.select(F.expr("slice(wanted, 1, size(wanted) - 1)").alias("head"), F.expr("element_at(wanted, -1)").alias("last"))
        pairs = ends.join(ends.withColumnRenamed("last", "next"), "head").where("last < next").select(F.expr("concat(head, array(last, next))").alias("wanted"))
        parts = pairs.select("wanted", F.expr("explode(transform(sequence(1, size(wanted)), j -> filter(wanted, (x, i) -> i + 1 <> j)))").alias("part"))
        parts = parts.join(front.select(F.col("wanted").alias("part"), "n"), "part").groupBy("wanted").agg(F.count(F.lit(1)).alias("hits"), F.min("n").alias("least"))
        sets = stored(parts.where(F.col("hits") == F.size("wanted")).select("wanted", "least"), "url-level")
        frequent = stored(counted(rows, sets.select("wanted"), each).where(F.col("bad") >= floor).join(sets, "wanted"), "url-frequent")
        out = out.unionByName(frequent.where(F.col("bad") >= min_confidence * F.col("n")).select("wanted", "anchor", "n", "bad"))
        front = frequent.where((F.col("bad") < min_confidence * F.col("n")) & (F.col("n") < F.col("least"))).select("wanted", "n")
        if front.isEmpty():
            return out


def mined(labelled: DataFrame, least: int = LEAST_URLS, min_support: float = MIN_SUPPORT, min_confidence: float = MIN_CONFIDENCE) -> DataFrame:
    """Rules (tokens, anchor, confidence, support) for ``block``; ``support`` counts blocked URLs.

    ``labelled`` has tokens and block (boolean). Tokens that are a rule by themselves come first; a longer rule with such a token
    would add nothing. FP-growth then looks among blocked URLs for sets of two and more of the other
    tokens, of which a URL offers at most ``OFFERED``, so that a URL of very many tokens stays cheap however
    often it occurs; if a URL has more to offer, the sets that this hides are found level by level. Support and confidence of what it finds are counted over all labelled URLs and all their tokens. A
    rule that holds another one is dropped: where it fits, the other fits too.
    """
    rows = labelled.where(F.size("tokens") > 0).groupBy("tokens").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("block").cast("long")).alias("bad"))
    rows = stored(rows, "url-labelled")
    total = rows.agg(F.sum("n").alias("n")).first()["n"] or 0
    floor = max(least, -(-int(min_support * total * 1000) // 1000))
    each = rows.select(F.explode("tokens").alias("token"), "n", "bad").groupBy("token").agg(F.sum("n").alias("n"), F.sum("bad").alias("bad"))
    each = stored(each.where(F.col("bad") >= floor).withColumn("confidence", F.col("bad") / F.col("n")), "url-tokens")
    alone = F.col("confidence") >= min_confidence
    singles = each.where(alone).select(F.array("token").alias("tokens"), F.col("token").alias("anchor"), "confidence", F.col("bad").alias("support"))
    offers = rows.where("bad > 0").select("tokens", F.explode("tokens").alias("token"), "bad").join(each.where(~alone).select("token", "confidence"), "token")
    best = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("confidence")).alias("less"), "token"))), 1, OFFERED)
    baskets = offers.groupBy("tokens").agg(F.array_sort(F.transform(best, lambda x: x["token"])).alias("items"), F.max("bad").alias("bad"), F.count(F.lit(1)).alias("offered")).where(F.size("items") > 1)
    baskets = stored(baskets.groupBy("items").agg(F.sum("bad").alias("bad"), F.max("offered").alias("offered")), "url-baskets")
    if baskets.isEmpty():
        return singles
    # equal baskets are told apart for the miner only here; its tree holds them once
    repeated = baskets.select("items", F.explode(F.sequence(F.lit(1).cast("long"), "bad")))
    number = baskets.agg(F.sum("bad")).first()[0]
    found = FPGrowth(itemsCol="items", minSupport=min(1.0, (floor - 0.5) / number)).fit(repeated.select("items")).freqItemsets
    found = found.where(F.size("items") > 1).select(F.array_sort("items").alias("wanted")).distinct()
    counts = counted(rows, stored(found, "url-itemsets"), each)
    right = (F.col("bad") >= floor) & (F.col("bad") >= min_confidence * F.col("n"))
    good = counts.where(right)
    if baskets.where(F.col("offered") > OFFERED).limit(1).count():
        good = good.unionByName(levels(rows, each, floor, min_confidence)).distinct()
    good = stored(good.select(F.col("wanted").alias("tokens"), "anchor", (F.col("bad") / F.col("n")).alias("confidence"), F.col("bad").alias("support")), "url-rules")
    inner = good.select(F.col("tokens").alias("wanted"), "anchor")
    wider = fitting(good.select("tokens"), inner).where(F.size("wanted") < F.size("tokens")).select("tokens").distinct()
    return singles.unionByName(good.join(wider, "tokens", "left_anti"))


def judge(pages: DataFrame, labelled: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES) -> DataFrame:
    """page_id, host, path, rule, verdict and the confidence of the best mined rule that fits.

    ``pages`` has page_id and url; ``labelled`` url and block, null where it is not known. Without a rule that fits, a page is
    blocked if a mined rule has all its tokens in the URL, else allowed; so null and odd URLs are
    allowed, and all are where there are no labels. Many pages share a set of tokens; rules meet the distinct sets,
    and the answer per set is joined back from a stored table, so a host that has a third of
    all pages is one row until then. Repeated rows are judged each; other columns are ignored.
    """
    cut = parsed(pages.select(F.col("page_id").cast("long").alias("page_id"), "url"))
    known = parsed(labelled.select("url", "block").where(F.col("block").isNotNull()))
    index = stored(mined(known).select(F.col("tokens").alias("wanted"), "anchor", "confidence"), "url-index")
    if index.count() <= MOST_BROADCAST:
        index = F.broadcast(index)
    best = stored(fitting(cut.select("tokens").distinct(), index).groupBy("tokens").agg(F.max("confidence").alias("confidence")), "url-sets")
    rule, verdict = explicit(rules)
    return cut.join(best, "tokens", "left").select(
        "page_id", "host", "path", rule.alias("rule"),
        F.coalesce(verdict, F.when(F.col("confidence").isNotNull(), "block").otherwise("allow")).alias("verdict"), "confidence",
    )
