"""User-defined semirings through Arrow: products, aggregates, and a table function."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql.functions import arrow_udf, pandas_udf, udtf
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import DataType

from layermul.semiring import Semiring


def _fold_runs(values: np.ndarray, lengths: np.ndarray, plus: Callable) -> np.ndarray:
    """Each run of values folded to one, by halves: neighbours in all runs are added at once."""
    while len(lengths) and lengths.max() > 1:
        start = np.cumsum(lengths) - lengths
        at = np.arange(len(values)) - np.repeat(start, lengths)
        last = np.repeat(lengths, lengths) - 1
        first = at % 2 == 0
        paired = np.flatnonzero(first & (at < last))
        values = values.copy()
        values[paired] = np.asarray(plus(pd.Series(values[paired]), pd.Series(values[paired + 1])))
        values, lengths = values[first], (lengths + 1) // 2
    return values


def user_semiring(name: str, add: Callable[[pd.Series], float], times: Callable[[pd.Series, pd.Series], pd.Series], kind: str = "bigint", plus: Callable[[pd.Series, pd.Series], pd.Series] | None = None) -> Semiring:
    """A semiring from two pandas functions: add folds a series to one value, times works on whole
    series. Batches travel by Arrow; prefer built-in semirings where they exist. add is called for every
    entry of the result; with plus, the sum of two series place by place, the entries of a batch are
    folded together instead (null products are left out; an entry's products must fit one row)."""

    arrow = to_arrow_type(DataType.fromDDL(kind)) if plus else None

    @pandas_udf(kind)
    def product(a: pd.Series, b: pd.Series) -> pd.Series:
        return times(a, b)

    @pandas_udf(kind)
    def fold(x: pd.Series) -> int:
        return add(x)

    @arrow_udf(kind)
    def fold_all(lists: pa.Array) -> pa.Array:
        lengths = np.diff(lists.offsets.to_numpy())
        out = np.zeros(len(lengths), lists.type.value_type.to_pandas_dtype())
        out[lengths > 0] = _fold_runs(lists.flatten().to_numpy(zero_copy_only=False), lengths[lengths > 0], plus)
        return pa.array(out, arrow, mask=lengths == 0)

    return Semiring(name, fold if plus is None else lambda x: fold_all(F.collect_list(x)), product, "", "")


@udtf(returnType="i bigint, v bigint")
class ExpandColumn:
    """One entry b of B and the column of A that it selects: the scaled column."""

    def eval(self, rows: list, values: list, b: int):
        for i, v in zip(rows, values, strict=True):
            yield i, v * b


def entry_mix() -> Column:
    """The checksum term of an entry that large products are compared by."""
    return F.col("v") * F.pmod(F.col("j"), F.lit(97))
