"""Where keys fall among sorted boundaries, and how many.

``position`` is the number of boundaries at or below a key (or strictly below).
A few untagged boundaries become a balanced decision tree of comparisons in
generated code. Otherwise numbers take a vectorised binary search of the key
alone, and only rows whose key equals a boundary's compare their tags: with the
few boundaries of that key, which a broadcast table of checked size holds, or,
where many share a key, by a second vectorised search of whole strict keys. Keys
of other types take that at once. The fold of higher-order functions serves
types that neither knows. What is sent out has as many entries as there are
boundaries, which is checked.
"""

from __future__ import annotations

from collections import Counter
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rangecut.plans.keys import KEY

#: Above so many boundaries generated code for a tree grows past the JVM's limit for a method.
TREE = 64
#: Boundaries of one count; beyond it splitters are found in stages.
MOST_BOUNDARIES = 2_000_000
#: Boundaries sent out as a table, and those of one key that a row is compared with one by one.
JOINED, SAME_KEY = 100_000, 8


def literal(value: Any, kind: T.DataType) -> Column:
    """A typed literal, of structs too."""
    if isinstance(kind, T.StructType):
        return F.struct(*(literal(v, f.dataType).alias(f.name) for v, f in zip(value, kind.fields, strict=True)))
    return F.lit(value).cast(kind)


def lookup(values: list[int], position: Column, kind: str = "int") -> Column:
    """``values[position]`` from one literal of equally wide entries, so that plans stay as small however many there are."""
    width = max((len(str(v)) for v in values), default=1)
    packed = F.lit("".join(str(v).rjust(width) for v in values).encode())
    return F.substring(packed, (position * width + 1).cast("int"), F.lit(width)).cast("string").cast(kind)


def tree(key: Column, boundaries: list[Column], strict: bool) -> Column:
    def build(start: int, end: int) -> Column:
        if start == end:
            return F.lit(start)
        middle = (start + end) // 2
        below = boundaries[middle] < key if strict else boundaries[middle] <= key
        return F.when(below, build(middle + 1, end)).otherwise(build(start, middle))

    return build(0, len(boundaries))


def fold(key: Column, array: Column, size: int, strict: bool) -> Column:
    """Binary search in a sorted array by higher-order functions."""
    steps = max(1, int(np.ceil(np.log2(size + 1))))

    def step(state: Column, _: Column) -> Column:
        middle = F.floor((state["lo"] + state["hi"]) / 2).cast("int")
        at = F.element_at(array, F.least(middle + 1, F.lit(size)))
        below = (at < key) if strict else (at <= key)
        going = state["lo"] < state["hi"]
        return F.struct(
            F.when(going & below, middle + 1).otherwise(state["lo"]).alias("lo"),
            F.when(going & ~below, middle).otherwise(state["hi"]).alias("hi"),
        )

    start = F.struct(F.lit(0).alias("lo"), F.lit(size).alias("hi"))
    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step, lambda s: s["lo"])


def numeric_search(values: np.ndarray):
    """(first, last) positions of a number among sorted values: the two differ where it equals some."""

    @F.pandas_udf("first int, last int")
    def search(keys: pd.Series) -> pd.DataFrame:
        x = keys.to_numpy(dtype=np.float64, na_value=np.nan)
        return pd.DataFrame({"first": np.searchsorted(values, x, "left").astype("int32"), "last": np.searchsorted(values, x, "right").astype("int32")})

    return search


def _codes(bounds: list, rows: np.ndarray) -> np.ndarray:
    """Whole numbers that order the values of one field, first the boundaries', then the rows'; nulls come first."""
    both = [*bounds, *rows.tolist()] if rows.dtype == object or rows.dtype.kind == "M" else None
    if both is None:
        values = np.array([np.nan if b is None else b for b in bounds], dtype=rows.dtype if rows.dtype.kind in "biu" and None not in bounds else np.float64)
        joined = np.concatenate([values, rows])
        missing = np.array([b is None for b in bounds] + [False] * len(rows))
        if rows.dtype.kind == "f":
            # A double column has nulls as NaN here; the key's own null flag stands before it.
            missing[len(bounds) :] = False
    else:
        if rows.dtype.kind == "M":
            both = [*(None if b is None else np.datetime64(b, "us").astype("int64") for b in bounds), *rows.astype("datetime64[us]").astype("int64").tolist()]
        missing = np.array([b is None for b in both])
        joined = np.array([b for b in both if b is not None], dtype=None if both and isinstance(next((b for b in both if b is not None), 0), (int, np.integer)) else object)
        codes = np.full(len(both), -1, np.int64)
        if len(joined):
            codes[~missing] = np.unique(joined, return_inverse=True)[1]
        return codes
    codes = np.unique(joined, return_inverse=True)[1].astype(np.int64)
    codes[missing] = -1
    return codes


def _places(fields: list[list], keys: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """(below, upto) of rows that aren't null among boundaries, given by their fields."""
    m, n = len(fields[0]), len(keys)
    columns = []
    for k, bounds in enumerate(fields):
        column = keys.iloc[:, k]
        rows = column.to_numpy()
        if k == 0:
            rows = rows.astype(bool)
        elif rows.dtype == object or column.isna().any() and rows.dtype.kind == "M":
            rows = column.astype(object).where(column.notna(), None).to_numpy()
        columns.append(_codes(bounds, rows))
    is_bound = np.concatenate([np.ones(m, np.int8), np.zeros(n, np.int8)])
    found = []
    for first in (1 - is_bound, is_bound):
        # Among equal keys, rows stand before boundaries to count those below, after them to count those at or below.
        order = np.lexsort((1 - first, *columns[::-1]))
        total = np.cumsum(is_bound[order], dtype=np.int64)
        place = np.empty(m + n, np.int64)
        place[order] = total
        found.append(place[m:])
    return found[0], found[1]


def strict_search(boundaries: list, values: np.ndarray | None = None, before: int = 0):
    """(below, upto): boundaries strictly below, and at or below, whole strict keys; null for null.

    ``values``: the boundaries' numbers, which ``before`` others precede. A batch
    then compares its numbers with the boundaries of the same numbers only.
    """
    m, fields = len(boundaries), [list(column) for column in zip(*(tuple(b) for b in boundaries), strict=True)]

    @F.pandas_udf("below int, upto int")
    def search(keys: pd.DataFrame) -> pd.DataFrame:
        wanted = keys.iloc[:, 0].notna().to_numpy()
        below, upto = np.zeros(len(keys), "int32"), np.zeros(len(keys), "int32")
        whole = wanted.copy()
        if values is not None and wanted.any():
            x = keys.iloc[:, 1].to_numpy(dtype=np.float64, na_value=np.nan)
            near = wanted & ~np.isnan(x)
            whole &= ~near
            if near.any():
                low, high = (before + np.searchsorted(values, x[near], side) for side in ("left", "right"))
                edges = np.zeros(m + 1, np.int64)
                np.add.at(edges, low, 1)
                np.add.at(edges, high, -1)
                at = np.flatnonzero(np.cumsum(edges[:-1]) > 0)
                skipped = low - np.searchsorted(at, low)
                below[near], upto[near] = (skipped + c for c in _places([[f[i] for i in at] for f in fields], keys[near]))
        if whole.any():
            below[whole], upto[whole] = _places(fields, keys[whole])
        frame = pd.DataFrame({"below": pd.Series(below, dtype="Int32"), "upto": pd.Series(upto, dtype="Int32")})
        frame[~wanted] = pd.NA
        return frame

    return search


_SEARCHED = ("boolean", "string", "date", "timestamp_ntz", "byte", "short", "integer", "long", "float", "double")


def with_position(df: DataFrame, boundaries: list, out: str, strict: bool = False, strategy: str = "auto", key: str = KEY, equal: str | None = None) -> DataFrame:
    """Adds ``out``, the position of ``key`` among ``boundaries`` (values of its type, sorted); ``equal``: whether it is one of them."""
    if len(boundaries) > MOST_BOUNDARIES:
        raise ValueError(f"{len(boundaries)} boundaries; at most {MOST_BOUNDARIES} are sent out, find splitters in stages")
    if not boundaries:
        found = df.withColumn(out, F.lit(0))
        return found.withColumn(equal, F.lit(False)) if equal else found
    kind = df.schema[key].dataType
    if strategy == "auto":
        known = all(f.dataType.typeName() in _SEARCHED for f in kind.fields)
        strategy = "tree" if len(kind.fields) == 2 and len(boundaries) <= TREE and not equal else "arrow" if known else "fold"
    if strategy == "tree":
        return df.withColumn(out, tree(F.col(key), [literal(b, kind) for b in boundaries], strict))
    if strategy == "fold":
        row = df.sparkSession.createDataFrame([(boundaries,)], T.StructType([T.StructField("_bounds", T.ArrayType(kind))]))
        joined = df.withColumn("_bounds", row.scalar())
        joined = joined.withColumn(out, fold(F.col(key), F.col("_bounds"), len(boundaries), strict))
        return (joined.withColumn(equal, F.array_contains("_bounds", F.col(key))) if equal else joined).drop("_bounds")
    search = strict_search(boundaries)
    pick = "below" if strict else "upto"
    if not isinstance(kind["key"].dataType, T.NumericType):
        found = df.withColumn("_strict", search(F.col(key))).withColumn(out, F.col(f"_strict.{pick}"))
        return (found.withColumn(equal, F.col("_strict.below") < F.col("_strict.upto")) if equal else found).drop("_strict")
    number = F.col(f"{key}.key").cast("double")
    # Nulls stand before all numbers or after; NaN after all numbers.
    before = sum(1 for b in boundaries if b[1] is None and not b[0])
    values = np.array([float(b[1]) for b in boundaries if b[1] is not None and b[1] == b[1]])
    found = df.withColumn("_near", numeric_search(values)(number))
    same = Counter(_kind_of(b[1]) for b in boundaries)
    if len(boundaries) <= JOINED and max(same.values()) <= SAME_KEY:
        nulls = sum(1 for b in boundaries if b[1] is None)
        base = F.when(number.isNull(), F.when(F.col(f"{key}.nulls"), F.lit(len(boundaries) - nulls)).otherwise(F.lit(0))).otherwise(F.col("_near.first") + before)
        same_key = F.when(number.isNull(), F.lit(-1)).when(F.isnan(number), F.lit(-2)).when(F.col("_near.first") < F.col("_near.last"), F.col("_near.first"))
        groups: dict[int, list] = {}
        for b in boundaries:
            of = _kind_of(b[1])
            groups.setdefault(of if isinstance(of, int) else int(np.searchsorted(values, of)), []).append(b)
        schema = T.StructType([T.StructField("_same", T.IntegerType()), T.StructField("_bounds", T.ArrayType(kind))])
        table = df.sparkSession.createDataFrame(list(groups.items()), schema)
        joined = found.withColumn("_same", same_key).join(F.broadcast(table), "_same", "left")  # at most JOINED entries
        passed = F.filter("_bounds", lambda b: (b < F.col(key)) if strict else (b <= F.col(key)))
        joined = joined.withColumn(out, (base + F.coalesce(F.size(passed), F.lit(0))).cast("int"))
        if equal:
            joined = joined.withColumn(equal, F.coalesce(F.exists("_bounds", lambda b: b == F.col(key)), F.lit(False)))
        return joined.drop("_near", "_same", "_bounds")
    search = strict_search(boundaries, values, before)
    plain = (F.col("_near.first") == F.col("_near.last")) & number.isNotNull() & ~F.isnan(number)
    found = found.withColumn("_strict", search(F.when(~plain, F.col(key))))
    found = found.withColumn(out, F.when(plain, F.col("_near.first") + before).otherwise(F.col(f"_strict.{pick}")))
    if equal:
        found = found.withColumn(equal, F.when(plain, F.lit(False)).otherwise(F.col("_strict.below") < F.col("_strict.upto")))
    return found.drop("_near", "_strict")


def _kind_of(value: Any) -> int | float:
    """What rows of equal plain key share: -1 for null, -2 for NaN, else the number."""
    return -1 if value is None else -2 if value != value else float(value)


def counts(df: DataFrame, boundaries: list, strategy: str = "auto", weight: str | None = None) -> list[int]:
    """Rows (or weights) at each position 0..len(boundaries). Tasks count first, so little is shuffled."""
    placed = with_position(df, boundaries, "_at", strategy=strategy)
    total = F.sum(weight) if weight else F.count(F.lit(1))
    found = {r["_at"]: r["total"] for r in placed.groupBy("_at").agg(total.alias("total")).collect()}
    return [found.get(i, 0) for i in range(len(boundaries) + 1)]


def sorted_counts(df: DataFrame, boundaries: list) -> DataFrame:
    """part, at, rows: local histograms by binary search of the boundaries in each partition's sorted numeric keys."""
    edges = np.array([float(b) for b in boundaries])

    def local(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        part, total = TaskContext.get().partitionId(), np.zeros(len(edges) + 1, np.int64)
        for batch in batches:  # each batch of a sorted partition is sorted
            keys = batch.column(0).to_numpy(zero_copy_only=False)
            cuts = np.searchsorted(keys, edges, "left")
            total += np.diff(np.concatenate([[0], cuts, [len(keys)]]))
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), part, np.int32)), pa.array(at.astype(np.int32)), pa.array(total[at])], names=["part", "at", "rows"])

    return df.mapInArrow(local, "part int, at int, rows long")
