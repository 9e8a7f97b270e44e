"""Fronts (skylines) of any DataFrame: rows whose criteria no other row of their group dominates. Smaller is better."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.dominance import dominates, wide_dominates


def _mask(values: np.ndarray) -> np.ndarray:
    """Non-dominated rows, by blocks against a growing front; sorted by sum, so a later row never dominates an earlier one."""
    order = np.lexsort([*values.T[::-1], values.sum(1)])
    front = np.zeros((0, values.shape[1]), values.dtype)
    keep = np.zeros(len(values), bool)
    for a in range(0, len(order), 256):
        at = order[a : a + 256]
        block = values[at]
        both = np.concatenate([front, block])
        le = (both[:, None, :] <= block[None, :, :]).all(2)
        lt = (both[:, None, :] < block[None, :, :]).any(2)
        good = ~(le & lt).any(0)
        keep[at[good]] = True
        front = np.concatenate([front, np.unique(block[good], axis=0)])
    return keep


def _local(df: DataFrame, criteria: list[str], by: list[str]) -> DataFrame:
    """Front of each group within every batch: fewer rows reach the exchange, none of the answer is lost."""

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            values = np.column_stack([b.column(b.schema.get_field_index(c)).to_numpy(zero_copy_only=False) for c in criteria])
            if not by:
                yield b.filter(pa.array(_mask(values)))
                continue
            keys = pa.table([b.column(b.schema.get_field_index(c)) for c in by], names=by).to_pandas()
            keep = np.zeros(b.num_rows, bool)
            for at in keys.groupby(by, dropna=False, sort=False).indices.values():
                keep[at[_mask(values[at])]] = True
            yield b.filter(pa.array(keep))

    return df.mapInArrow(run, df.schema)


def front(df: DataFrame, criteria: list[str], by: list[str] | None = None, how: str = "two_phase", ties: str = "all") -> DataFrame:
    """Rows of df that belong to their group's front.

    'anti': anti-join on dominance (the baseline; equi-join on `by`, quadratic in a group). 'two_phase': local fronts before
    one exchange, then the final one per group. 'sorted2': two criteria, a running minimum over a sort.
    ties: 'all' rows of equal vectors, or 'one' of them. Rows with a null criterion are not comparable and left out.
    """
    by = list(by or [])
    df = df.dropna(subset=criteria)
    if how == "anti":
        other = df.select(*(F.col(c).alias(f"__o_{c}") for c in [*by, *criteria])).distinct()
        on = wide_dominates([F.col(f"__o_{c}") for c in criteria], [F.col(c) for c in criteria])
        for c in by:
            on = on & F.col(c).eqNullSafe(F.col(f"__o_{c}"))
        out = df.join(other, on, "left_anti")
    elif how == "sorted2":
        if len(criteria) != 2:
            raise ValueError("sorted2 needs two criteria")
        a, b = criteria
        part = Window.partitionBy(*by) if by else Window.partitionBy(F.lit(0))
        # the least second criterion among rows with a smaller first one, and among equal first ones
        earlier = F.min(b).over(part.orderBy(a).rangeBetween(Window.unboundedPreceding, -1))
        equal = F.min(b).over((Window.partitionBy(*by, a)) if by else Window.partitionBy(a))
        local = _local(df, criteria, by)
        out = local.withColumn("__earlier", earlier).withColumn("__equal", equal).where((F.col("__earlier").isNull() | (F.col(b) < F.col("__earlier"))) & (F.col(b) == F.col("__equal"))).drop("__earlier", "__equal")
    elif how == "two_phase":
        local = _local(df, criteria, by)

        def final(pdf):
            return pdf[_mask(pdf[criteria].to_numpy())]

        out = local.groupBy(*by).applyInPandas(final, df.schema)
    else:
        raise ValueError(f"unknown way {how!r}")
    return out.dropDuplicates([*by, *criteria]) if ties == "one" else out


def front_agg(vectors: Column) -> Column:
    """Aggregate: the non-dominated vectors of a group, sorted, as an array of arrays."""
    every = F.collect_set(vectors)
    return F.array_sort(F.filter(every, lambda x: ~F.exists(every, lambda o: dominates(o, x))))


def merge_fronts(old: DataFrame, new: DataFrame, criteria: list[str], by: list[str]) -> DataFrame:
    """Front of both, with `changed`: the row is not in `old`."""
    both = front(old.select(*by, *criteria).unionByName(new.select(*by, *criteria)).distinct(), criteria, by)
    mark = old.select(*by, *criteria).distinct().withColumn("__old", F.lit(True))
    return both.join(mark, [*by, *criteria], "left").select(*by, *criteria, F.col("__old").isNull().alias("changed"))


def front_layers(df: DataFrame, criteria: list[str], by: list[str] | None = None, layers: int = 2) -> DataFrame:
    """Rows of the first `layers` fronts, peeled one after another, with their layer from 1."""
    rest, out = df, None
    for k in range(1, layers + 1):
        one = front(rest, criteria, by)
        out = one.withColumn("layer", F.lit(k)) if out is None else out.unionByName(one.withColumn("layer", F.lit(k)))
        if k < layers:
            keys = [*(by or []), *criteria]
            gone = one.select(*keys).distinct()
            on = None
            for c in keys:
                on = rest[c].eqNullSafe(gone[c]) if on is None else on & rest[c].eqNullSafe(gone[c])
            rest = rest.join(gone, on, "left_anti")
    return out


def front_topk(df: DataFrame, criteria: list[str], weights: list[float], k: int) -> DataFrame:
    """The k members of the front with the least weighted sum (weights positive)."""
    if min(weights) <= 0:
        raise ValueError("weights must be positive")
    score = sum((F.col(c) * w for c, w in zip(criteria, weights, strict=True)), F.lit(0.0))
    return front(df, criteria).withColumn("score", score).orderBy("score", *criteria).limit(k)
