"""Routing where a row is, batch by batch: routing terms of subscriptions and workers of objects, without an exchange.

Tasks get this module by value, so it imports nothing of the package.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Rows that are looked at together.
TOGETHER = 1 << 16


def gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held, n = [], 0
    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= TOGETHER:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def lengths(lists: pa.Array) -> np.ndarray:
    return pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)


def _cut(*keys: np.ndarray) -> np.ndarray:
    """The first of each run of equal keys."""
    first = np.ones(len(keys[0]), dtype=bool)
    if len(first):
        first[1:] = np.logical_or.reduce([key[1:] != key[:-1] for key in keys])
    return np.flatnonzero(first)


def keyed(batches: Iterator[pa.RecordBatch], terms: pa.Array) -> Iterator[pa.RecordBatch]:
    """Subscriptions with ``routes``: the least frequent keyword of each clause, of equal ones the smaller term, with the places of
    the clauses that it stands for. ``terms`` are those with a frequency, in that order; any other comes before them."""
    for rows in gathered(batches):
        dnf = pa.concat_arrays(rows["dnf"].chunks)
        clauses = dnf.flatten()
        words = clauses.flatten()
        n_clauses, n_words = lengths(dnf), lengths(clauses)
        rank = pc.fill_null(pc.index_in(words, value_set=terms), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        if len(other := np.flatnonzero(rank < 0)):
            _, back = np.unique(np.array(words.take(pa.array(other)).to_pylist(), dtype=object), return_inverse=True)
            rank[other] = back - (back.max() + 1)
        clause = np.repeat(np.arange(len(n_words)), n_words)
        order = np.lexsort((rank, clause))
        least = order[_cut(clause[order])] if len(order) else order
        listed = clause[least]
        sub = np.repeat(np.arange(len(n_clauses)), n_clauses)
        nth = np.arange(len(sub)) - np.repeat(np.cumsum(n_clauses) - n_clauses, n_clauses)
        order = np.lexsort((listed, rank[least], sub[listed]))
        least, listed = least[order], listed[order]
        first = _cut(sub[listed], rank[least])
        routes = pa.StructArray.from_arrays(
            [words.take(pa.array(least[first])), pa.ListArray.from_arrays(pa.array(np.append(first, len(listed)), pa.int32()), pa.array(nth[listed], pa.int32()))], ["term", "clauses"]
        )
        ends = np.searchsorted(sub[listed][first], np.arange(len(n_clauses) + 1))
        out = rows.append_column("routes", pa.ListArray.from_arrays(pa.array(ends, pa.int32()), routes))
        yield from out.to_batches()


def _copied(rows: pa.Table, row: np.ndarray, worker: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Rows at workers, each worker of a row once."""
    order = np.lexsort((worker, row))
    row, worker = row[order], worker[order]
    once = _cut(row, worker)
    yield from rows.take(pa.array(row[once])).append_column("worker", pa.array(worker[once], pa.int32())).to_batches()


def responsible(batches: Iterator[pa.RecordBatch], chart) -> Iterator[pa.RecordBatch]:
    """Objects with ``cell`` and ``codes`` at each worker that is responsible for one of their terms (``cellmatch.Chart``)."""
    for rows in gathered(batches):
        cell = rows["cell"].to_numpy()
        lists = pa.concat_arrays(rows["codes"].chunks)
        row, codes = np.repeat(np.arange(len(cell)), lengths(lists)), lists.flatten().to_numpy()
        at, worker = cell[row], np.zeros(len(row), dtype=np.int64)
        order = np.argsort(chart.leaf_of[at], kind="stable")
        leaf = chart.leaf_of[at[order]]
        starts = _cut(leaf) if len(leaf) else np.zeros(0, dtype=np.int64)
        for a, b in zip(starts, np.append(starts[1:], len(leaf))):
            worker[order[a:b]] = chart.worker(at[order[a]], codes[order[a:b]])
        yield from _copied(rows.drop_columns(["codes"]), row, worker)


def waiting(batches: Iterator[pa.RecordBatch], terms: pa.Array, keys: np.ndarray, workers: np.ndarray) -> Iterator[pa.RecordBatch]:
    """Objects with ``cell`` at each worker that waits for one of their terms there. ``keys``, in order, are those of cells and of
    ``terms`` by their place: cell times number of terms, and place."""
    for rows in gathered(batches):
        lists = pa.concat_arrays(rows["terms"].chunks)
        place = pc.fill_null(pc.index_in(lists.flatten(), value_set=terms), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        row = np.repeat(np.arange(rows.num_rows), lengths(lists))
        row, place = row[place >= 0], place[place >= 0]
        key = rows["cell"].to_numpy().astype(np.int64)[row] * len(terms) + place
        low = np.searchsorted(keys, key)
        n = np.searchsorted(keys, key, side="right") - low
        entry = np.arange(int(n.sum())) + np.repeat(low - (np.cumsum(n) - n), n)
        yield from _copied(rows, np.repeat(row, n), workers[entry].astype(np.int64))
