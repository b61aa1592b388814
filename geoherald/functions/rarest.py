"""The rarest term of each text, batch by batch. Tasks get this module by value, so it imports nothing of the package."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Rows that are looked at together.
TOGETHER = 1 << 17


def gathered(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    """Batches put together to tables of about ``rows``."""
    held, n = [], 0
    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= rows:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def rarest(batches: Iterator[pa.RecordBatch], terms: pa.Array, ranks: np.ndarray) -> Iterator[pa.RecordBatch]:
    """``kw, text, terms`` to ``kw, text, rare, rare_rk``: of a text's terms, of which there is one at least, the first in ``terms``."""
    for rows in gathered(batches, TOGETHER):
        texts = pa.concat_arrays(rows["terms"].chunks)
        at = pc.index_in(texts.flatten(), value_set=terms).to_numpy(zero_copy_only=False)
        ends = np.cumsum(pc.list_value_length(texts).to_numpy(zero_copy_only=False))
        least = np.minimum.reduceat(at, np.concatenate([[0], ends[:-1]])).astype(np.int64)
        out = pa.table({"kw": rows["kw"], "text": rows["text"], "rare": terms.take(pa.array(least)), "rare_rk": pa.array(ranks[least])})
        yield from out.to_batches()
