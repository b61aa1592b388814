"""Repeated passages by sparse suffix arrays.

Suffixes start at words. Of all of them only those at content-selected places are kept: in every run of
``window`` runs of ``gram`` words, the place whose run has the least hash. A passage of ``least`` =
window + gram - 1 words holds a full window, so wherever it occurs the same place in it is kept.

1. One Arrow pass lists the kept places, one in about window/2 words. Those whose run of ``gram`` words
   occurs once are done with, by a count per run.
2. The other places are put together per document and meet its text again, which gives every suffix
   ``least - gram`` words of context on its right and on its left, as 16-bit hashes of words.
3. Suffixes of one run with equal contexts are counted as one kind. Two of a run share ``least`` words if
   for some split l + r = ``least - gram`` their l words on the left and r on the right are equal. Sorted by
   a context, a kind shares the most words of it with a neighbour, which bounds l from above and, by the
   other context, r; in between, kinds are counted under one key for each split, first within batches
   of neighbours and then by a count per key, and a kind with company under a key has its match there.
   The least and the greatest such l give the extent to both sides, over all partners. This is exact, and
   no task holds a run of any size alone.
4. Matches of a document are joined to spans, which are exact to the word, but for 16-bit collisions
   (one word more with a chance of 1/65536).

Results for odd rows: null and empty texts, and texts of fewer than ``least`` words, have no spans. A
document can repeat itself. Rows without an id take no part; rows with equal ids count as one
document. Repeated rows and ties need no rule, as equal suffixes are counted together. Only ``key`` and
``text`` are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geoherald.llm.scratch import discard, join_frequent, store, stored
from geoherald.llm.words import WordHashes, gram_hashes, mix, split_words, word_hashes

_STEP = np.uint64(0x9E3779B97F4A7C15)


@dataclass(frozen=True)
class SuffixParams:
    least: int = 50
    gram: int = 16

    @property
    def window(self) -> int:
        return self.least - self.gram + 1

    @property
    def context(self) -> int:
        return self.least - self.gram


def kept_places(grams: np.ndarray, window: int) -> np.ndarray:
    """Places of the least hash in every run of ``window``; the first of equal ones."""
    if len(grams) < window:
        return np.zeros(0, np.int64)
    runs = np.lib.stride_tricks.sliding_window_view(grams, window)
    out = []
    for at in range(0, len(runs), 65_536):
        part = runs[at : at + 65_536]
        out.append(np.unique(part.argmin(axis=1) + np.arange(at, at + len(part))))
    return np.unique(np.concatenate(out))


def _anchors(docs: DataFrame, params: SuffixParams) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordHashes()
        for batch in batches:
            places, runs, counts = [], [], []
            for t in batch.column("text").to_pylist():
                words = split_words(t)
                grams = gram_hashes(word_hashes(words, cache), params.gram) if len(words) >= params.least else np.zeros(0, np.uint64)
                at = kept_places(grams, params.window)
                places.append(at)
                runs.append(grams[at].view(np.int64))
                counts.append(len(at))
            owner = np.repeat(np.arange(len(counts)), counts)
            if len(owner):
                yield pa.RecordBatch.from_arrays([batch.column("key").take(pa.array(owner)), pa.array(np.concatenate(places).astype(np.int32)), pa.array(np.concatenate(runs))], ["key", "at", "run"])

    return docs.mapInArrow(run, f"key {docs.schema['key'].dataType.simpleString()}, at int, run long")


def _with_context(docs: DataFrame, params: SuffixParams) -> DataFrame:
    """Suffixes of the places in ``ats``, with both contexts; the left one is read backwards."""
    width = params.context

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordHashes()
        for batch in batches:
            owner, ats, runs, right, left = [], [], [], [], []
            for k, (t, places) in enumerate(zip(batch.column("text").to_pylist(), batch.column("ats").to_pylist(), strict=True)):
                hashes = word_hashes(split_words(t), cache)
                grams = gram_hashes(hashes, params.gram)
                # 0 is kept for places past either end, which match nothing
                small = ((hashes >> np.uint64(40)) % np.uint64(65_535) + np.uint64(1)).astype(">u2")
                padded = np.concatenate([np.zeros(width, ">u2"), small, np.zeros(width, ">u2")])
                for at in places:
                    if at >= len(grams):
                        continue  # of another text with the same id
                    owner.append(k)
                    ats.append(at)
                    runs.append(int(grams[at].view(np.int64)))
                    right.append(padded[width + at + params.gram :][:width].tobytes())
                    left.append(padded[at : at + width][::-1].tobytes())
            if owner:
                yield pa.RecordBatch.from_arrays(
                    [batch.column("key").take(pa.array(owner, pa.int64())), pa.array(ats, pa.int32()), pa.array(runs, pa.int64()), pa.array(right, pa.binary()), pa.array(left, pa.binary())],
                    ["key", "at", "run", "right", "left"],
                )

    return docs.mapInArrow(run, f"key {docs.schema['key'].dataType.simpleString()}, at int, run long, right binary, left binary")


def _words(batch: pa.RecordBatch, side: str, width: int) -> tuple[np.ndarray, np.ndarray]:
    """One side's contexts, and how many words of each lie within the text."""
    words = np.frombuffer(b"".join(batch.column(side).to_pylist()), ">u2").reshape(-1, width).astype(np.uint64)
    return words, np.where((words == 0).any(axis=1), (words == 0).argmax(axis=1), width)


def _most_shared(batch: pa.RecordBatch, side: str, width: int) -> np.ndarray:
    """Words of a context that a neighbour of the same run shares; all where a batch begins or ends."""
    words, within = _words(batch, side, width)
    runs = batch.column("run").to_numpy()
    differ = words[1:] != words[:-1]
    common = np.where(differ.any(axis=1), differ.argmax(axis=1), width)
    common[runs[1:] != runs[:-1]] = 0
    edge = np.full(1, width)
    return np.minimum(np.maximum(np.concatenate([edge, common]), np.concatenate([common, edge])), within)


def _ordered(kinds: DataFrame, *order: str) -> DataFrame:
    return kinds.repartitionByRange(*order).sortWithinPartitions(*order)


def _bounded_left(kinds: DataFrame, params: SuffixParams) -> DataFrame:
    """Adds ``l_most``: the most words on the left that another kind of the run shares, or more."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(_most_shared(batch, "left", params.context).astype(np.int32))], [*batch.schema.names, "l_most"])

    return _ordered(kinds, "run", "left", "right").mapInArrow(run, "run long, kind long, right binary, left binary, times long, l_most int")


def _split_rows(kinds: DataFrame, params: SuffixParams) -> DataFrame:
    """``k, kind, l, n``. Without ``k``: the kind has company at the split l. With both: it has none in its
    batch under the key k. With ``k`` alone: several have it."""
    width = params.context

    def rows_of(k: np.ndarray | None, kind: np.ndarray | None, l: np.ndarray | None, n: int, count: int) -> pa.RecordBatch:
        column = lambda v, t: pa.nulls(count, t) if v is None else pa.array(v, t)
        return pa.RecordBatch.from_arrays([column(k, pa.int64()), column(kind, pa.int64()), column(l, pa.int32()), pa.array(np.full(count, n, np.int64))], ["k", "kind", "l", "n"])

    def prefixes(words: np.ndarray) -> np.ndarray:
        out = np.zeros((width + 1, len(words)), np.uint64)
        for k in range(width):
            out[k + 1] = mix(out[k] + _STEP) + words[:, k]
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            kind, times = batch.column("kind").to_numpy(), batch.column("times").to_numpy()
            most, least = batch.column("l_most").to_numpy(), width - _most_shared(batch, "right", width)
            left, right = (prefixes(_words(batch, side, width)[0]) for side in ("left", "right"))
            seed = mix(batch.column("run").to_numpy().view(np.uint64))
            low, high = np.full(len(kind), width + 1), np.full(len(kind), -1)
            # a kind that stands for several places has company everywhere, as far as its text reaches
            several = np.flatnonzero(times > 1)
            if len(several):
                reach = [_words(batch, side, width)[1][several] for side in ("left", "right")]
                can = reach[0] + reach[1] >= width
                low[several[can]], high[several[can]] = (width - reach[1])[can], reach[0][can]
            for split in range(width + 1):
                rows = np.flatnonzero((least <= split) & (split <= most))
                if not len(rows):
                    continue
                keys = mix(mix(mix(seed[rows] + np.uint64(split)) + left[split, rows]) + right[width - split, rows])
                distinct, place, counts = np.unique(keys, return_inverse=True, return_counts=True)
                counts = np.maximum(counts, np.bincount(place, weights=np.minimum(times[rows], 2), minlength=len(distinct)).astype(np.int64))
                met = counts[place] > 1
                low[rows[met]] = np.minimum(low[rows[met]], split)
                high[rows[met]] = np.maximum(high[rows[met]], split)
                shared = distinct[counts > 1]
                if len(shared):
                    yield rows_of(shared.view(np.int64), None, None, 2, len(shared))
                alone = ~met
                if alone.any():
                    yield rows_of(keys[alone].view(np.int64), kind[rows[alone]], np.full(alone.sum(), split), 1, int(alone.sum()))
            found = np.flatnonzero(high >= 0)
            for ends in (low, high):
                yield rows_of(None, kind[found], ends[found], 0, len(found))

    return _ordered(kinds, "run", "right", "left").mapInArrow(run, "k long, kind long, l int, n long")


def _extents(kinds: DataFrame, params: SuffixParams) -> tuple[DataFrame, list[str]]:
    """``kind, before, after`` of the kinds with a match, and the tables that this reads."""
    bounded, bounded_at = stored(_bounded_left(kinds, params), "bounded")
    splits, splits_at = stored(_split_rows(bounded, params), "splits")
    met = splits.filter("k is not null").groupBy("k").agg(F.sum("n").alias("n")).filter("n > 1").select("k")
    apart = splits.filter("k is not null and kind is not null").join(met, "k", "left_semi")
    hits = splits.filter("k is null").select("kind", "l").union(apart.select("kind", "l"))
    return hits.groupBy("kind").agg(F.max("l").alias("before"), (F.lit(params.context) - F.min("l")).alias("after")), [bounded_at, splits_at]


@F.arrow_udf(T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType())])))
def joined_spans(spans: pa.Array) -> pa.Array:
    """Spans that overlap or touch, as one."""
    out = []
    for row in spans.to_pylist():
        done: list[dict] = []
        for s in sorted(row, key=lambda s: s["start"]):
            if done and s["start"] <= done[-1]["end"]:
                done[-1]["end"] = max(done[-1]["end"], s["end"])
            else:
                done.append(s)
        out.append(done)
    return pa.array(out, spans.type)


def repeated_passages(docs: DataFrame, key: str = "doc_id", text: str = "text", params: SuffixParams = SuffixParams()) -> DataFrame:
    """``key, spans``: for every document with passages that occur elsewhere, spans of word numbers.

    A span has its first word's number, from 0, and that of the word after its last.
    """
    rows = docs.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("string").alias("text")).filter("key is not null")
    anchors, anchors_at = stored(_anchors(rows, params), "anchors")
    often = store(anchors.groupBy("run").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "runs")
    # at most 100,000 are so frequent
    hot = F.col("n") > max(1000, anchors.count() / 100_000)
    places = join_frequent(anchors, often, "run", hot).groupBy("key").agg(F.collect_set("at").alias("ats"))
    suffixes, suffixes_at = stored(_with_context(rows.join(places, "key"), params), "suffixes")
    discard(docs.sparkSession, anchors_at)

    kind = F.xxhash64("run", "right", "left").alias("kind")
    kinds, kinds_at = stored(suffixes.groupBy("run", "right", "left").agg(F.count(F.lit(1)).alias("times")).select("run", kind, "right", "left", "times"), "contexts")
    extents, read = _extents(kinds, params)
    extents = store(extents.join(kinds.select("kind", "times"), "kind").dropDuplicates(["kind"]), "extents")

    hit = F.struct((F.col("at") - F.col("before")).alias("start"), (F.col("at") + params.gram + F.col("after")).alias("end"))
    hot = F.col("times") > max(1000, suffixes.count() / 100_000)
    found = join_frequent(suffixes.select("key", "at", kind), extents, "kind", hot)
    out = store(found.groupBy("key").agg(joined_spans(F.collect_set(hit)).alias("spans")), "spans")
    discard(docs.sparkSession, suffixes_at, kinds_at, *read)
    return out.withColumnRenamed("key", key)
