"""Keys with a strict total order: a key column, and a tag that tells equal keys apart."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

KEY = "_key"


@dataclass(frozen=True)
class KeySpec:
    """``key`` is a column or an expression; ``tag`` columns make rows distinct; ``coin`` are the integers that draws are made of.

    Nulls come first or last as said; NaN is greater than all numbers and -0.0
    equals 0.0, as in Spark's own order. Without a tag, keys have to be distinct.
    """

    key: str
    tag: tuple[str, ...] = ()
    coin: tuple[str, ...] = field(default=())
    nulls_first: bool = True

    def column(self, df: DataFrame) -> Column:
        kind = df.select(F.expr(self.key).alias("k")).schema["k"].dataType
        if isinstance(kind, (T.MapType, T.VariantType)):
            raise TypeError(f"{kind.simpleString()} has no order; take a part of it as the key")
        key = F.expr(self.key)
        if isinstance(kind, (T.DoubleType, T.FloatType)):
            key = F.when(key == 0, F.lit(0.0).cast(kind)).otherwise(key)
        if isinstance(kind, T.TimestampType):
            key = key.cast("timestamp_ntz")
        nulls = key.isNull() != F.lit(self.nulls_first)
        return F.struct(nulls.alias("nulls"), key.alias("key"), *(F.col(t).alias(f"t{i}") for i, t in enumerate(self.tag)))

    def strict(self, df: DataFrame, *carried: str) -> DataFrame:
        """The strict key as ``_key``, and what draws or counts need; everything else is pruned."""
        kept = dict.fromkeys((*self.coin, *carried))
        return df.select(self.column(df).alias(KEY), *kept)


#: Strict keys of the given tables.
LINEITEM_TAG = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_shipdate")
LINEITEM_COIN = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber")


def lineitem(key: str = "l_extendedprice") -> KeySpec:
    return KeySpec(key, LINEITEM_TAG, LINEITEM_COIN)


def orders(key: str = "o_totalprice") -> KeySpec:
    return KeySpec(key, ("o_orderkey",), ("o_orderkey",))


def events(key: str = "value") -> KeySpec:
    return KeySpec(key, ("event_id",), ("event_id",))
