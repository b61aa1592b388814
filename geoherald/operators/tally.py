"""Distinct ids by key: those of a batch go through the exchange in one block of numbers, each once. The blocks are
those of ``cellmatch``; tasks get both modules by value."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.cloudpickle import register_pickle_by_value
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geoherald.operators import cellmatch

# tasks need no path to the package
register_pickle_by_value(cellmatch)

#: Parts that the ids of a key are dealt to.
PARTS = 32


def _packer(cm, parts: int):
    def distinct(ids: np.ndarray, weights: np.ndarray, *keys: np.ndarray) -> tuple[np.ndarray, ...]:
        order = np.lexsort((weights, ids, *keys))
        columns = [c[order] for c in (ids, weights, *keys)]
        first = np.array(cm._cut(*columns)[:-1], dtype=np.int64)
        return tuple(c[first] for c in columns)

    def packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in cm._gathered(batches):
            column = lambda name, rows=rows: rows[name].combine_chunks().to_numpy(zero_copy_only=False).astype(np.int64)
            ids = column("id")
            part = (((ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(parts)).astype(np.int64)
            ids, weights, part, k1, k0 = distinct(ids, column("weight"), part, column("k1"), column("k0"))
            bounds = cm._cut(k0, k1, part)
            blocks = [cm.squeeze([np.diff(ids[a:b], prepend=0), weights[a:b]]) for a, b in zip(bounds, bounds[1:])]
            heads = bounds[:-1]
            yield pa.RecordBatch.from_arrays([pa.array(c[heads]) for c in (k0, k1, part)] + [pa.array(blocks, pa.binary())], ["k0", "k1", "part", "block"])

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Blocks in the order of their keys to distinct ids with their weights, key by key."""
        key, ids, weights = None, [], []

        def out() -> pa.RecordBatch:
            one, weight = distinct(np.concatenate(ids), np.concatenate(weights))
            return pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (key[0], key[1], len(one), int(weight.sum()))], ["k0", "k1", "n", "total"])

        for batch in batches:
            for *at, block in zip(*(batch.column(c).to_pylist() for c in ("k0", "k1", "part", "block"))):
                if at != key:
                    if key is not None:
                        yield out()
                    key, ids, weights = at, [], []
                apart, weight = cm.spread(block)
                ids.append(np.cumsum(apart))
                weights.append(weight)
        if key is not None:
            yield out()

    return packed, counted


def distinct_ids(rows: DataFrame, keys: tuple[str, ...], key_id: str, weight: Column | None = None, parts: int = 1) -> DataFrame:
    """``keys`` (one or two whole numbers), ``n`` and ``total``: distinct pairs of id and weight of each key, and their weights."""
    k0, k1 = keys[0], keys[1] if len(keys) > 1 else None
    packed, counted = _packer(cellmatch, parts)
    long = lambda c: c.cast("long")
    whole = rows.select(long(F.col(k0)).alias("k0"), (long(F.col(k1)) if k1 else F.lit(0).cast("long")).alias("k1"), long(F.col(key_id)).alias("id"), long(F.lit(0) if weight is None else weight).alias("weight"))
    # blocks are small for the work that they make: by their size they would be put together to too few tasks
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    blocks = whole.mapInArrow(packed, "k0 long, k1 long, part long, block binary").repartition(n, "k0", "k1", "part").sortWithinPartitions("k0", "k1", "part")
    found = blocks.mapInArrow(counted, "k0 long, k1 long, n long, total long").groupBy("k0", "k1").agg(F.sum("n").alias("n"), F.sum("total").alias("total"))
    types = {f.name: f.dataType for f in rows.schema.fields}
    return found.select(*(F.col(f"k{i}").cast(types[k]).alias(k) for i, k in enumerate(keys)), "n", "total")
