"""Tables to transactions: binarise, item dictionary, mask packing.

``binarise`` gives the long form ``(tid, item, label)``; a transaction without
items has one row with a null item, so it still counts. ``encode`` numbers the
items that are frequent enough, by falling support, and packs each transaction
into mask words. An infrequent item is in no frequent pattern, so leaving it out
loses nothing. Null attributes give no item; a null label takes a row out of
class-wise counts only.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from prefpat.functions import bits

#: Mask columns grow with the frequent items; past this the plan itself gets too wide.
MAX_ITEMS = 4096

LONG_SCHEMA = T.StructType([T.StructField("tid", T.LongType()), T.StructField("item", T.StringType()), T.StructField("label", T.IntegerType())])


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """The columns of a schema, in its types; anything missing is an error."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"columns {missing} are missing from {df.columns}")
    return df.select(*[F.col(f.name).cast(f.dataType) for f in schema])


@dataclass
class EncodedDataset:
    """``transactions(tid, items, m0.., label)``, ``items(item_id, item, support)``."""

    name: str
    transactions: DataFrame
    items: DataFrame
    n: int
    n_pos: int
    n_labelled: int
    n_items: int
    n_items_all: int
    words: int = field(init=False)

    def __post_init__(self):
        self.words = bits.words_for(self.n_items)

    @property
    def masks(self) -> list[str]:
        return bits.mask_names(self.words)

    def persist(self) -> EncodedDataset:
        self.transactions = self.transactions.persist()
        return self


def binarise(df: DataFrame, tid: Column, items: Sequence[Column] | Column, label: Column | None = None) -> DataFrame:
    """Long form from attribute columns (strings or null), or from one array column.

    A row comes once for each of its items. What several rows of a transaction repeat
    stays: supports count transactions. Arrays and labels are made before rows are
    multiplied, not again for every item."""
    array = items if isinstance(items, Column) else F.array(*items)
    kind = F.lit(None).cast("int") if label is None else label.cast("int")
    rows = df.select(tid.cast("long").alias("tid"), F.array_distinct(array).alias("items"), kind.alias("label"))
    return rows.select("tid", F.explode_outer("items").alias("item"), "label").withColumn("item", F.col("item").cast("string"))


def item_supports(long: DataFrame) -> DataFrame:
    """``(item, support)`` of all items."""
    return long.where("item is not null").groupBy("item").agg(F.count_distinct("tid").alias("support"))


def item_rows(long: DataFrame) -> DataFrame:
    """``(item, support)`` with the number of an item's rows instead: no less than its support."""
    return long.where("item is not null").groupBy("item").agg(F.count(F.lit(1)).alias("support"))


def item_dictionary(supports: DataFrame, min_sup: int = 1) -> DataFrame:
    """``(item_id, item, support)`` of the items with enough support.

    Only the frequent items reach the one partition that numbers them.
    """
    counts = supports.where(F.col("support") >= min_sup)
    by_support = Window.orderBy(F.desc("support"), "item")
    return counts.select((F.row_number().over(by_support) - 1).cast("int").alias("item_id"), "item", "support")


def pack(long: DataFrame, dictionary: DataFrame, words: int) -> DataFrame:
    """Transactions from the long form; the dictionary has a checked size. Mask words alone
    are shuffled, and the items' ids are read off them."""
    known = long.join(F.broadcast(dictionary.select("item", "item_id")), "item", "left")
    masks = bits.mask_names(words)
    return known.groupBy("tid").agg(F.max("label").alias("label"), *bits.pack_item(F.col("item_id"), words)).select("tid", bits.ids(masks).alias("items"), *masks, "label")


def renumbered(transactions: DataFrame, ids: dict[int, int], words: int) -> DataFrame:
    """Transactions with new ids for old ones; items without one are left out."""
    new = F.array(*[F.lit(ids.get(i)).cast("int") for i in range(max(ids, default=-1) + 1)]) if ids else F.array().cast("array<int>")
    items = F.sort_array(F.filter(F.transform("items", lambda i: F.get(new, i)), lambda i: i.isNotNull()))
    return transactions.select("tid", items.alias("items"), "label").select("tid", "items", *bits.pack_array(F.col("items"), words), "label")


def encode(long: DataFrame, name: str = "data", min_sup: int = 1) -> EncodedDataset:
    """Numbers the items and packs the transactions.

    The long form is made twice and no more, and its rows are never shuffled one by one:
    items with rows enough to be frequent are numbered and packed, the transactions tell
    their supports, and by these the items are numbered anew if that changes anything.
    With more such items than can be packed, transactions are counted in the first place."""
    long = require(long, LONG_SCHEMA)
    rows = item_rows(long).persist()
    total, dictionary = rows.count(), item_dictionary(rows, min_sup).persist()
    first = dictionary.limit(MAX_ITEMS + 1).collect()
    if len(first) > MAX_ITEMS:
        dictionary = item_dictionary(item_supports(long), min_sup).persist()
        if (n := dictionary.count()) > MAX_ITEMS:
            raise ValueError(f"{n} items with support {min_sup} or more; at most {MAX_ITEMS} can be packed, raise the support")
        first = dictionary.collect()
    transactions = pack(long, dictionary, bits.words_for(len(first))).persist()
    supports = item_supports(transactions.select("tid", F.explode("items").alias("item")))
    exact = {r["item"]: r.support for r in supports.collect()}  # no more than MAX_ITEMS
    if any(exact[r.item_id] != r.support for r in first):
        counted = supports.withColumnRenamed("item", "item_id").join(F.broadcast(dictionary.select("item_id", "item")), "item_id")
        dictionary = item_dictionary(counted, min_sup).persist()
        old, first = {r["item"]: r.item_id for r in first}, dictionary.collect()
        transactions = renumbered(transactions, {old[r["item"]]: r.item_id for r in first}, bits.words_for(len(first))).persist()
    n, n_pos, n_labelled = transactions.agg(F.count(F.lit(1)), F.count_if(F.col("label") == 1), F.count("label")).first()
    return EncodedDataset(name, transactions, dictionary, n, n_pos, n_labelled, len(first), total)
