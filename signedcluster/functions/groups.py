"""Groups of rows handed to Python through Arrow, without one pandas frame for each group."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType


def map_groups(df: DataFrame, key: str, work, schema: str, *order: str) -> DataFrame:
    """``work(key, columns as lists) -> columns as lists`` for each value of the long column ``key``.

    One exchange deals rows by key and sorts them; a task holds one group at a time.
    """
    kinds = StructType.fromDDL(schema)
    arrow = to_arrow_schema(kinds)
    names = [f.name for f in arrow]

    def run(batches):
        now, held = None, None

        def made():
            out = {n: [] for n in names}
            for row in work(now, held):
                for n, v in zip(names, row, strict=True):
                    out[n].append(v)
            return pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)

        for batch in batches:
            if not batch.num_rows:
                continue
            keys = batch.column(key).to_numpy(zero_copy_only=False)
            cols = batch.to_pydict()
            edges = np.flatnonzero(np.diff(keys)) + 1
            for a, b in zip([0, *edges.tolist()], [*edges.tolist(), len(keys)], strict=True):
                if held is None or keys[a] != now:
                    if held is not None:
                        yield made()
                    now, held = keys[a], {k: [] for k in cols}
                for k, v in cols.items():
                    held[k].extend(v[a:b])
        if held is not None:
            yield made()

    return df.repartition(key).sortWithinPartitions(key, *order).mapInArrow(run, kinds)


def map_tables(df: DataFrame, key: str, work, schema: str, parts: int | None = None, last=lambda df: df) -> DataFrame:
    """``work(key, Arrow table of its rows) -> arrays by name`` for each value of the long column ``key``, a group at a time.
    ``last`` is what is done with the rows after the exchange, in ``parts`` partitions if given."""
    kinds = StructType.fromDDL(schema)
    arrow = to_arrow_schema(kinds)

    def run(batches):
        now, held = None, []

        def made():
            out = work(now, pa.Table.from_batches(held))
            return pa.RecordBatch.from_arrays([pa.array(out[f.name], type=f.type) for f in arrow], schema=arrow)

        for batch in batches:
            keys = batch.column(key).to_numpy(zero_copy_only=False)
            edges = np.flatnonzero(np.diff(keys)) + 1
            for a, b in zip([0, *edges.tolist()], [*edges.tolist(), len(keys)], strict=True):
                if b <= a:
                    continue
                if held and keys[a] != now:
                    yield made()
                    held = []
                now = int(keys[a])
                held.append(batch.slice(a, b - a))
        if held:
            yield made()

    dealt = df.repartition(parts, key) if parts else df.repartition(key)
    return last(dealt.sortWithinPartitions(key)).mapInArrow(run, kinds)
