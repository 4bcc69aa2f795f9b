"""Sequential numpy steps per group at the price of a batch: many small groups share one Arrow batch."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _starts(table: pa.Table, by: list[str]) -> np.ndarray:
    """First row of each run of equal keys; nulls are equal to each other."""
    n = table.num_rows
    new = np.zeros(n, dtype=bool)
    new[:1] = True
    for c in by:
        col = table.column(c).combine_chunks()
        a, b = col.slice(1), col.slice(0, n - 1)
        differ = pc.fill_null(pc.not_equal(a, b), False)
        differ = pc.or_(differ, pc.xor(pc.is_null(a), pc.is_null(b)))
        new[1:] |= differ.to_numpy(zero_copy_only=False)
    return np.nonzero(new)[0]


def add_columns(df: DataFrame, by, order, inputs: list[str], added: T.StructType, step: Callable[..., tuple]) -> DataFrame:
    """df with the columns of ``added``: ``step`` gets a group's ``inputs`` as float arrays in order and returns an array per added column.

    Rows come sorted by (by, order), so a group is a run of rows; only the run that a batch leaves open is held for the next.
    ``order`` must tell a group's rows apart where ``step`` depends on their order.
    """
    by, order = list(by), list(order)
    kept = df.drop(*added.names)
    schema = T.StructType([*kept.schema.fields, *added.fields])
    types = [pa.int32() if isinstance(f.dataType, T.IntegerType) else pa.int64() if isinstance(f.dataType, T.LongType) else pa.bool_() if isinstance(f.dataType, T.BooleanType) else pa.float64() for f in added.fields]
    names = added.names

    def solved(table: pa.Table, starts: np.ndarray):
        values = [np.asarray(table.column(c).combine_chunks().cast(pa.float64()).to_numpy(zero_copy_only=False), dtype=float) for c in inputs]
        parts = [step(*(v[a:b] for v in values)) for a, b in zip(starts, [*starts[1:], table.num_rows])]
        for k, (name, kind) in enumerate(zip(names, types)):
            table = table.append_column(name, pa.array(np.concatenate([p[k] for p in parts]), type=kind))
        yield from table.combine_chunks().to_batches()

    def run(batches):
        held = []
        for batch in batches:
            if not batch.num_rows:
                continue
            table = pa.Table.from_batches([batch])
            if held:  # does this batch begin a new group?
                seam = pa.concat_tables([held[-1].slice(held[-1].num_rows - 1), table])
                starts = _starts(seam, by)[1:]
                starts = starts - 1
            else:
                starts = _starts(table, by)[1:]
            if not len(starts):
                held.append(table)
                continue
            cut = int(starts[-1])
            whole = pa.concat_tables([*held, table.slice(0, cut)]).combine_chunks()
            if whole.num_rows:
                yield from solved(whole, _starts(whole, by))
            held = [table.slice(cut)]
        if held:
            last = pa.concat_tables(held).combine_chunks()
            yield from solved(last, _starts(last, by))

    return kept.repartition(*by).sortWithinPartitions(*by, *order).mapInArrow(run, schema)
