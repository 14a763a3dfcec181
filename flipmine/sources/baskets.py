"""Baskets from the given tables: who bought, clicked or wrote what."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import ITEM_BUDGET, ITEMS_BROADCAST, CandidateBudgetExceeded
from .tables import load


@dataclass(frozen=True)
class Baskets:
    """``long`` (tid, item) without repeats, ``tids`` (tid) with the empty tuples too, ``items`` (item, label) dense from 0."""

    long: DataFrame
    tids: DataFrame
    items: DataFrame
    n_items: int
    copied: tuple[Baskets, int] | None = None  # what each tuple is a copy of, and how many there are
    lists: DataFrame | None = None  # (tid, items) where lists are made as such
    pairs: DataFrame | None = None  # ``long`` with its repeats

    def arrays(self, parts: int | None = None) -> DataFrame:
        """(tid, items): sorted item lists of all tuples, empty ones included; one shuffle by tid, of the originals where tuples are copies.

        With ``parts`` they are dealt to so many tasks.
        """
        if parts and self.pairs is not None:
            return gathered(self.pairs, self.tids, parts)
        plain = self._plain_arrays() if self.lists is None else self.lists
        return plain.repartition(parts) if parts else plain

    def _plain_arrays(self) -> DataFrame:
        if self.copied:
            return _copies(self.copied[0].arrays(), self.copied[1]).select("tid", "items")
        lists = self.long.groupBy("tid").agg(F.sort_array(F.collect_set("item")).alias("items"))
        return self.tids.join(lists, "tid", "left").select("tid", F.coalesce("items", F.array().cast("array<int>")).alias("items"))

    def dbsize(self) -> int:
        return self.tids.count()


def gathered(pairs: DataFrame, tids: DataFrame, parts: int) -> DataFrame:
    """(tid, items): sorted lists without repeats of the ``pairs`` (tid, item; none null) of each of ``tids``, in one shuffle without a join."""
    both = tids.select("tid", F.lit(-1).alias("item")).unionByName(pairs.select("tid", "item")).repartition(parts, "tid").sortWithinPartitions("tid", "item")

    def lists(tid: np.ndarray, item: np.ndarray) -> pa.RecordBatch:
        marks = np.flatnonzero(item < 0)  # a row of ``tids``; its items follow the last of its like
        own = np.flatnonzero((item >= 0) & np.isin(tid, tid[marks]))
        ends = np.searchsorted(tid[own], tid[marks], side="right")
        sizes = ends - np.searchsorted(tid[own], tid[marks])
        if (tid[marks][1:] == tid[marks][:-1]).any():  # a repeated tid has its list each time
            own = own[np.repeat(ends - np.cumsum(sizes), sizes) + np.arange(sizes.sum())]
        return pa.RecordBatch.from_arrays([pa.array(tid[marks], pa.int64()), pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(sizes))), pa.int32()), pa.array(item[own], pa.int32()))], ["tid", "items"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tid, item = np.zeros(0, np.int64), np.zeros(0, np.int32)
        for batch in batches:
            if none := batch.column(0).null_count:
                yield pa.RecordBatch.from_arrays([pa.nulls(none, pa.int64()), pa.array([[]] * none, pa.list_(pa.int32()))], ["tid", "items"])
                batch = batch.filter(batch.column(0).is_valid())
            tid, item = np.concatenate((tid, batch.column(0).to_numpy())), np.concatenate((item, batch.column(1).to_numpy()))
            new = np.ones(len(tid), bool)
            new[1:] = (tid[1:] != tid[:-1]) | (item[1:] != item[:-1]) | (item[1:] < 0)
            tid, item = tid[new], item[new]
            cut = int(np.searchsorted(tid, tid[-1])) if len(tid) else 0
            if cut:
                yield lists(tid[:cut], item[:cut])
                tid, item = tid[cut:], item[cut:]
        if len(tid):
            yield lists(tid, item)

    return both.mapInArrow(work, "tid long, items array<int>")


def dictionary(labels: DataFrame) -> tuple[DataFrame, int]:
    """Dense item ids in the order of labels (``labels`` has one column, label). The universe is small by contract: more than ITEM_BUDGET is an error."""
    rows = labels.where(F.col("label").isNotNull()).distinct().limit(ITEM_BUDGET + 1).toArrow().column(0)
    if len(rows) > ITEM_BUDGET:
        raise CandidateBudgetExceeded(f"more than {ITEM_BUDGET} items")
    # UTF-8 order, as Spark and DuckDB compare strings
    names = sorted(rows.to_pylist(), key=lambda x: x.encode())
    table = pa.table({"item": pa.array(range(len(names)), pa.int32()), "label": pa.array(names, pa.string())})
    return labels.sparkSession.createDataFrame(table, "item int, label string"), len(names)


def encode(members: DataFrame, tids: DataFrame, labels: DataFrame) -> Baskets:
    """Baskets from (tid, label); presence counts, not multiplicity; nulls are no purchases."""
    items, n = dictionary(labels)
    pairs = members.dropna().join(F.broadcast(items) if n <= ITEMS_BROADCAST else items, "label").select(F.col("tid").cast("long").alias("tid"), "item")
    return Baskets(pairs.distinct(), tids.select(F.col("tid").cast("long").alias("tid")), items, n, pairs=pairs)


#: What an order's lines are labelled by.
ORDER_ITEMS = {"brand": "p_brand", "name": "p_name", "type": "p_type", "name_type": "p_name, p_type", "part": "l_partkey", "supp": "l_suppkey"}


def from_orders(spark: SparkSession, sf_dir: str, kind: str, pushed: str | None = None) -> Baskets:
    """One tuple per order, those without lines included. ``pushed`` is a filter on the lines that reaches the scan."""
    if kind not in ORDER_ITEMS:
        raise ValueError(f"unknown kind {kind}; there are {sorted(ORDER_ITEMS)}")
    tids = load(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").alias("tid"))
    lines = load(spark, sf_dir, "lineitem")
    lines = lines.where(pushed) if pushed else lines
    if kind in ("part", "supp"):
        key, table = ("l_partkey", load(spark, sf_dir, "part", "p_partkey")) if kind == "part" else ("l_suppkey", load(spark, sf_dir, "supplier", "s_suppkey"))
        members = lines.select(F.col("l_orderkey").alias("tid"), F.col(key).cast("string").alias("label"))
        return encode(members, tids, table.select(F.col(table.columns[0]).cast("string").alias("label")))
    label = F.concat_ws("/", "p_name", "p_type") if kind == "name_type" else F.col(ORDER_ITEMS[kind])
    part = load(spark, sf_dir, "part", "p_partkey", "p_name", "p_brand", "p_type").select(F.col("p_partkey").alias("l_partkey"), label.alias("label"))
    members = lines.select("l_orderkey", "l_partkey").join(part, "l_partkey").select(F.col("l_orderkey").alias("tid"), "label")
    return encode(members, tids, part.select("label"))


def from_customers(spark: SparkSession, sf_dir: str) -> Baskets:
    """One tuple per customer with orders; items are the suppliers they ever bought from: the dense counter-example."""
    orders = load(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey")
    members = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("tid"), F.col("l_suppkey").cast("string").alias("label"))
    supplier = load(spark, sf_dir, "supplier", "s_suppkey").select(F.col("s_suppkey").cast("string").alias("label"))
    return encode(members, orders.select(F.col("o_custkey").alias("tid")).distinct(), supplier)


def user_day() -> str:
    """The tuple id of a user's day: user_id * 100000 + days since the epoch."""
    return "user_id * 100000 + unix_date(to_date(ts))"


def from_events(spark: SparkSession, sf_dir: str, item: str = "k") -> Baskets:
    """One tuple per user and day; items are the event's ``k`` property, or its type."""
    events = load(spark, sf_dir, "events", "ts", "user_id", "event_type", "props")
    label = F.get_json_object("props", "$.k") if item == "k" else F.col("event_type")
    members = events.select(F.expr(user_day()).alias("tid"), label.alias("label"))
    return encode(members, members.select("tid").distinct(), members.select("label"))


def words_of(column: str) -> Column:
    return F.regexp_extract_all(F.lower(column), F.lit(r"\p{L}+"), 0)


def from_texts(rows: DataFrame, first: int, last: int) -> Baskets:
    """One tuple per row (tid, text); items are the words of frequency rank ``first`` to ``last``, ties by word."""
    words = rows.select("tid", F.explode(F.array_distinct(words_of("text"))).alias("label"))
    ranks = words.groupBy("label").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "label").limit(last).offset(first - 1)
    return encode(words, rows.select("tid").distinct(), ranks.select("label"))


def from_documents(spark: SparkSession, sf_dir: str, first: int = 101, last: int = 1100, pattern: str | None = None, slice_: bool = False) -> Baskets:
    """Words of documents; ``pattern`` is a predicate on texts, ``slice_`` takes English ones labelled as good."""
    docs = load(spark, sf_dir, "documents", "doc_id", "text", "lang")
    docs = docs.where(F.col("text").rlike(pattern)) if pattern else docs
    if slice_:
        good = load(spark, sf_dir, "labels", "doc_id", "quality").where("quality = 1").select("doc_id")
        docs = docs.where("lang = 'en'").join(good, "doc_id", "left_semi")
    return from_texts(docs.select(F.col("doc_id").alias("tid"), "text"), first, last)


def from_conversations(spark: SparkSession, sf_dir: str, last: int = 500) -> Baskets:
    rows = load(spark, sf_dir, "conversations", "conv_id", "text").select(F.col("conv_id").alias("tid"), "text")
    return from_texts(rows, 1, last)


def from_pages(spark: SparkSession, sf_dir: str) -> Baskets:
    """One tuple per page; items are the names of the elements in its HTML."""
    pages = load(spark, sf_dir, "pages", "page_id", "html")
    tags = F.array_distinct(F.transform(F.regexp_extract_all("html", F.lit("<([a-zA-Z][a-zA-Z0-9]*)"), 1), lambda x: F.lower(x)))
    members = pages.select(F.col("page_id").alias("tid"), F.explode(tags).alias("label"))
    return encode(members, pages.select(F.col("page_id").alias("tid")), members.select("label"))


def from_embeddings(spark: SparkSession, sf_dir: str) -> Baskets:
    """Signs of vectors: dimension i is an item of a vector if its i-th number is positive."""
    rows = load(spark, sf_dir, "embeddings", "vec_id", "embedding")
    members = rows.select(F.col("vec_id").alias("tid"), F.posexplode("embedding").alias("at", "x")).where("x > 0").select("tid", F.lpad(F.col("at").cast("string"), 4, "0").alias("label"))
    return encode(members, rows.select(F.col("vec_id").alias("tid")), members.select("label"))


def replicate(baskets: Baskets, times: int) -> Baskets:
    """Every tuple ``times`` times under new ids: tid * times + copy."""
    return Baskets(_copies(baskets.long, times), _copies(baskets.tids, times), baskets.items, baskets.n_items, (baskets, times))


def _copies(df: DataFrame, times: int) -> DataFrame:
    return df.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1)))).withColumn("tid", F.col("tid") * times + F.col("copy")).drop("copy")


def restrict(baskets: Baskets, items: DataFrame, keep: bool = True) -> Baskets:
    """Only (or all but) the given items; ids stay."""
    return Baskets(baskets.long.join(items.select("item"), "item", "left_semi" if keep else "left_anti").select("tid", "item"), baskets.tids, baskets.items, baskets.n_items)
