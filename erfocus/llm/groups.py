"""Whole groups out of sorted Arrow batches."""

from __future__ import annotations

import numpy as np
import pyarrow as pa


def starts(table: pa.Table, names: tuple[str, ...]) -> np.ndarray:
    """Rows at which a new group of equal values begins."""
    new = np.zeros(table.num_rows, dtype=bool)
    new[:1] = True
    for name in names:
        x = table.column(name).to_numpy()
        new[1:] |= x[1:] != x[:-1]
    return np.flatnonzero(new)


def by_group(use, *names: str):
    """A map over batches sorted by the named columns, that gives use() tables of whole groups."""

    def run(batches):
        held = None
        for batch in batches:
            table = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            last = starts(table, names)[-1] if table.num_rows else 0
            if last:
                yield from use(table.slice(0, last))
            held = table.slice(last)
        if held is not None and held.num_rows:
            yield from use(held)

    return run
