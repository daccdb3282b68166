"""Reading array columns as matrices, one per vector length."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc


def matrices(ids: pa.Array, column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """``(length, ids, matrix)`` of the rows that are whole: not null, no null or non-finite component.

    Rows without an id are left out.
    """
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    sizes = pc.fill_null(pc.list_value_length(column), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    known = pc.is_valid(ids).to_numpy(zero_copy_only=False)
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    starts = np.concatenate([[0], np.cumsum(np.maximum(sizes, 0))])[:-1]
    keys = pc.fill_null(ids, 0).to_numpy(zero_copy_only=False)
    for d in np.unique(sizes[sizes >= 0]):
        rows = np.flatnonzero((sizes == d) & known)
        m = values[starts[rows][:, None] + np.arange(d)]
        fine = np.isfinite(m).all(axis=1)
        if fine.any():
            yield int(d), keys[rows[fine]], m[fine]
