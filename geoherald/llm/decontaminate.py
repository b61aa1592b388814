"""Benchmark decontamination: size-partitioned MinHash containment search, verified exactly.

Similarity between a short item and a whole long document is tiny even when the item is inside it, so
both sides are cut to comparable sizes. Items fall into size classes (powers of two of their number
of shingles); for a class whose items have at most u shingles, a document is cut into segments of
2u shingles at every u, so that a passage of u shingles lies in one segment in full. A document's
minima are computed once, for blocks of the smallest u, and merged for the larger classes.

A segment is a candidate for an item if they agree in one of ``perms`` minima. For an item at its
class's lower end, with the least containment 0.8, the similarity is at least 0.19: the chance to
miss it is 0.81^96 = 2e-9. Items of at most half the smallest class's size are below that, so they are
looked up by their shingles instead, as many of them as leave too few for the containment. Each candidate is verified by the exact share of the item's shingles that
the whole document has.

The items are one side of a search: they are taken in blocks of at most ``ITEMS_AT_ONCE``, each
broadcast, and one pass over the documents is made for each block.

Results for odd rows: a null or empty text on either side matches nothing. An item of fewer words
than a shingle has its whole sequence as one, which only a document of just these words has.
Repeated rows are answered row by row. Empty tables give an empty result, or all documents. Only the
named columns are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from geoherald.llm.words import WordHashes, gram_hashes, shingle_set, split_words, word_hashes

ITEMS_AT_ONCE = 20_000


@dataclass(frozen=True)
class LeakParams:
    shingle: int = 5
    num: int = 80
    den: int = 100
    perms: int = 96
    smallest: int = 16


class ItemIndex:
    """The minima of a block of items, by size class."""

    def __init__(self, items: list[tuple[object, np.ndarray]], params: LeakParams):
        rng = np.random.default_rng(977)
        self.params = params
        # 32-bit words: four to eight of them are one vector instruction
        self.mult = rng.integers(0, 2**31, params.perms, dtype=np.uint32)[:, None] * np.uint32(2) + np.uint32(1)
        self.items = items
        sized: dict[int, list[int]] = {}
        short: list[tuple[int, int]] = []
        for k, (_, s) in enumerate(items):
            if len(s) <= params.smallest // 2:
                need = -(-params.num * len(s) // params.den)
                short += [(int(g), k) for g in s[: len(s) - need + 1]]
                continue
            u = params.smallest
            while u < len(s):
                u *= 2
            sized.setdefault(u, []).append(k)
        self.short = np.array([g for g, _ in sorted(short)], np.uint64)
        self.short_owner = np.array([k for _, k in sorted(short)], np.int64)
        self.classes: list[tuple[int, np.ndarray, np.ndarray]] = []
        for u, members in sorted(sized.items()):
            low = np.stack([self.hashed(items[k][1]).min(axis=1) for k in members])
            keys = self.keyed(low).ravel()
            owner = np.repeat(np.array(members), params.perms)
            order = np.argsort(keys, kind="stable")
            self.classes.append((u, keys[order], owner[order]))

    def hashed(self, grams: np.ndarray) -> np.ndarray:
        """One row per permutation: an odd multiple of each hash, which is well mixed itself."""
        return (grams >> np.uint64(32)).astype(np.uint32)[None, :] * self.mult

    def keyed(self, low: np.ndarray) -> np.ndarray:
        """Minima (one row per set) under the number of their permutation."""
        return low.astype(np.uint64) | (np.arange(self.params.perms, dtype=np.uint64)[None, :] << np.uint64(32))

    def block_minima(self, grams: np.ndarray) -> np.ndarray:
        """Minima of every block of ``smallest`` shingles; one column per block.

        Blocks lie side by side, so that minima are taken over whole vectors. The last one is filled up
        with its last shingle, which changes no minimum.
        """
        size, out = self.params.smallest, []
        step = size * 64
        for at in range(0, len(grams), step):
            part = grams[at : at + step]
            part = np.concatenate([part, np.repeat(part[-1:], -len(part) % size)])
            turned = np.ascontiguousarray(part.reshape(-1, size).T)
            out.append(self.hashed(turned.ravel()).reshape(self.params.perms, size, -1).min(axis=1))
        return np.concatenate(out, axis=1)

    def candidates(self, grams: np.ndarray) -> set[int]:
        found: set[int] = set()
        if not len(grams):
            return found
        if len(self.short):
            own = np.unique(grams)
            at = np.searchsorted(self.short, own)
            met = own[self.short[np.minimum(at, len(self.short) - 1)] == own]
            for first, last in zip(np.searchsorted(self.short, met), np.searchsorted(self.short, met, side="right")):
                found.update(self.short_owner[first:last].tolist())
        if not self.classes:
            return found
        low, size = self.block_minima(grams), self.params.smallest
        for u, keys, owner in self.classes:
            while size < u:
                if low.shape[1] > 1:
                    low = np.minimum.reduceat(low, np.arange(0, low.shape[1], 2), axis=1)
                size *= 2
            pairs = np.minimum(low[:, :-1], low[:, 1:]) if low.shape[1] > 1 else low
            seen = self.keyed(pairs.T).ravel()
            at = np.searchsorted(keys, seen)
            hit = np.flatnonzero(keys[np.minimum(at, len(keys) - 1)] == seen)
            for k in np.unique(seen[hit]):
                first, last = np.searchsorted(keys, k), np.searchsorted(keys, k, side="right")
                found.update(owner[first:last].tolist())
        return found

    def verified(self, grams: np.ndarray) -> list[tuple[object, int, int]]:
        """Item key, shingles of the item, shingles shared; where enough of them are shared."""
        out, own = [], None
        for k in sorted(self.candidates(grams)):
            own = np.unique(grams) if own is None else own
            key, s = self.items[k]
            shared = int(np.isin(s, own, assume_unique=True).sum())
            if shared * self.params.den >= self.params.num * len(s):
                out.append((key, len(s), shared))
        return out


def _blocks(items: DataFrame, item_key: str, item_text: str, params: LeakParams) -> Iterator[ItemIndex]:
    """Indexes of the items, a block at a time, so that the driver holds one block."""
    cache, held = WordHashes(), []
    for row in items.select(F.col(f"`{item_key}`"), F.col(f"`{item_text}`").cast("string")).toLocalIterator():
        s = shingle_set(row[1], params.shingle, cache)
        if len(s):
            held.append((row[0], s))
        if len(held) == ITEMS_AT_ONCE:
            yield ItemIndex(held, params)
            held = []
    if held:
        yield ItemIndex(held, params)


def find_leaks(
    docs: DataFrame,
    items: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    item_key: str = "item_id",
    item_text: str = "text",
    params: LeakParams = LeakParams(),
) -> DataFrame:
    """``key, item_key, n_item, n_shared`` for every item that a document contains to the threshold."""
    rows = docs.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("string").alias("text"))
    kinds = f"`{key}` {rows.schema['key'].dataType.simpleString()}, `{item_key}` {items.schema[item_key].dataType.simpleString()}, n_item long, n_shared long"
    item_arrow = to_arrow_type(items.schema[item_key].dataType)
    context = docs.sparkSession.sparkContext

    def search(index: ItemIndex) -> DataFrame:
        held = context.broadcast(index)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            index, cache = held.value, WordHashes()
            for batch in batches:
                at, ids, sizes, shared = [], [], [], []
                for k, t in enumerate(batch.column(1).to_pylist()):
                    grams = gram_hashes(word_hashes(split_words(t), cache), params.shingle)
                    for item, n, m in index.verified(grams):
                        at.append(k)
                        ids.append(item)
                        sizes.append(n)
                        shared.append(m)
                taken = batch.column(0).take(pa.array(at, pa.int64()))
                yield pa.RecordBatch.from_arrays([taken, pa.array(ids, item_arrow), pa.array(sizes, pa.int64()), pa.array(shared, pa.int64())], [key, item_key, "n_item", "n_shared"])

        return rows.mapInArrow(run, kinds)

    parts = [search(index) for index in _blocks(items, item_key, item_text, params)]
    if not parts:
        return docs.sparkSession.createDataFrame([], kinds)
    return reduce(DataFrame.union, parts)


def drop_leaking(docs: DataFrame, items: DataFrame, text: str = "text", item_key: str = "item_id", item_text: str = "text", params: LeakParams = LeakParams()) -> DataFrame:
    """The rows of ``docs`` that contain no item. Decided row by row, without a shuffle."""
    context = docs.sparkSession.sparkContext

    def with_leaks(index: ItemIndex) -> Column:
        held = context.broadcast(index)

        @F.arrow_udf("boolean")
        def leaks(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
            index, cache = held.value, WordHashes()
            for texts in batches:
                found = [bool(index.verified(gram_hashes(word_hashes(split_words(t), cache), params.shingle))) for t in texts.to_pylist()]
                yield pa.array(found, pa.bool_())

        return leaks(F.col(f"`{text}`").cast("string"))

    for index in _blocks(items, item_key, item_text, params):
        docs = docs.filter(~with_leaks(index))
    return docs
