"""Pattern features and the sets of them that a model uses.

Feature ids: items ``0 .. M-1``, then length ``M``, frequency ``M+1``, and one for
each transaction (or bucket of like transactions) from ``M+2`` on.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.operators.encode import EncodedDataset

NAMED_SETS = {"I": ("items",), "ILF": ("items", "length", "frequency"), "ILFT": ("items", "length", "frequency", "transactions")}


@dataclass(frozen=True)
class FeatureSpec:
    """Which of items, length, frequency and transactions take part."""

    parts: tuple[str, ...]

    @classmethod
    def of(cls, spec) -> FeatureSpec:
        parts = NAMED_SETS[spec] if isinstance(spec, str) else tuple(spec)
        unknown = set(parts) - set(NAMED_SETS["ILFT"])
        if unknown:
            raise ValueError(f"unknown features {sorted(unknown)}")
        return cls(parts)

    def has(self, part: str) -> bool:
        return part in self.parts


def length(ds: EncodedDataset) -> Column:
    return F.col("len") / F.lit(float(ds.n_items))


def frequency(ds: EncodedDataset) -> Column:
    return F.col("sup") / F.lit(float(ds.n))


def item_rows(patterns: DataFrame) -> DataFrame:
    return patterns.select("pattern", F.explode("items").alias("feature_id"), F.lit(1.0).alias("value"))


def transaction_rows(patterns: DataFrame, ds: EncodedDataset) -> DataFrame:
    """``(pattern, tid)`` of a few patterns: which transactions they occur in.

    For shown patterns only; the patterns are broadcast, their number is checked.
    """
    masks = ds.masks
    few = patterns.select("pattern", *[F.col(m).alias(f"p_{m}") for m in masks])
    inside = bits.contains([F.col(m) for m in masks], [F.col(f"p_{m}") for m in masks])
    return ds.transactions.join(F.broadcast(few), inside).select("pattern", "tid")


def feature_rows(patterns: DataFrame, ds: EncodedDataset, spec: FeatureSpec) -> DataFrame:
    """Sparse ``(pattern, feature_id, value)`` without transactions."""
    parts = []
    if spec.has("items"):
        parts.append(item_rows(patterns))
    if spec.has("length"):
        parts.append(patterns.select("pattern", F.lit(ds.n_items).alias("feature_id"), length(ds).alias("value")))
    if spec.has("frequency"):
        parts.append(patterns.select("pattern", F.lit(ds.n_items + 1).alias("feature_id"), frequency(ds).alias("value")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
