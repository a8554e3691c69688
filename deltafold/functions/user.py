"""User functions: scalar, aggregate and table-valued."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@F.pandas_udf("double")
def square_distance(x: pd.Series, y: pd.Series) -> pd.Series:
    """Squared distance to (25, 5), a batch at a time."""
    return (x - 25.0) ** 2 + (y - 5.0) ** 2


def aggregate_by(rows: DataFrame, key: str, value: str, zero: tuple, lift, merge) -> DataFrame:
    """(key, value array of long) by a user monoid of whole numbers.  Each batch is merged by key before the
    shuffle, so a hot key sends one row for each batch."""
    schema = "key long, value array<long>"
    arrow = pa.schema([("key", pa.int64()), ("value", pa.list_(pa.int64()))])

    def early(batches):
        for batch in batches:
            out: dict = {}
            for k, v in zip(batch[0].to_pylist(), batch[1].to_pylist(), strict=True):
                out[k] = merge(out.get(k, zero), lift(v))
            yield pa.record_batch([pa.array(list(out), pa.int64()), pa.array([list(v) for v in out.values()], pa.list_(pa.int64()))], schema=arrow)

    def late(table: pa.Table) -> pa.Table:
        total = zero
        for v in table["value"].to_pylist():
            total = merge(total, tuple(v))
        return pa.table({"key": [table["key"][0].as_py()], "value": [list(total)]}, schema=arrow)

    return rows.select(F.col(key).cast("long"), F.col(value).cast("long")).mapInArrow(early, schema).groupBy("key").applyInArrow(late, schema)


@F.udtf(returnType="token string")
class Tokens:
    """The space-separated tokens of a text, a row each."""

    def eval(self, text: str):
        for token in (text or "").split(" "):
            yield (token,)
