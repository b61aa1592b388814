"""Near-duplicate documents: b-bit MinHash with band candidates, confirmed on full shingle sets.

1. One Arrow pass turns a text into the hash of its shingle set, ``bands`` band keys and a sketch that
   keeps the low ``bits`` bits of every minimum, packed into words of 64 bits.
2. Documents with equal sets form a class; the smallest id stands for it from here on.
3. In every band bucket the member that shares buckets with the most documents is the hub and meets the
   others: a bucket of n gives n-1 pairs. Components of the confirmed links follow; buckets whose
   members are in one component by then are settled. In the others the next ``hubs - 1`` most central
   members meet those of other components in the same way. Pairs that are still in different components
   are all looked at, which is the exact way for what hubs leave open. Before that, shingles that no
   other document there has are counted, since none of them can be shared.
4. A pair is dropped if the set sizes rule the threshold out, or if the similarity estimated from
   the sketches (matching lanes, corrected for chance collisions) is ``margin`` standard errors below
   it. Of the pairs that hubs leave open those are dropped too whose sets differ in too many shingles by
   a parity sketch, which never shows more differences than there are. What remains is confirmed on full sets.

With the default 24 bands of 4 rows a pair at similarity 0.8 has no band in common with probability
0.59^24 = 3e-6, at 0.85 with 2e-8.

Results for odd rows: a null or empty text, or one of white space, has an empty set and is linked with
nothing. Rows with equal ids count as one document. A row without an id belongs to the component of
its exact copies, if they have ids, and is kept if not. Repeated rows each appear in the result. An
empty table gives an empty table. Only ``key`` and ``text`` are read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from math import sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from geoherald.llm.components import components
from geoherald.llm.scratch import discard, store, stored
from geoherald.llm.words import WordHashes, mix, shingle_set

_LOW = 0x5555555555555555
#: Ids up to which a choice of documents is broadcast to a scan of the texts; beyond, both are shuffled.
BROADCAST_IDS = 2_000_000


@dataclass(frozen=True)
class NearParams:
    """``num/den`` is the threshold as a fraction, so that the comparison stays in whole numbers."""

    shingle: int = 5
    num: int = 80
    den: int = 100
    bands: int = 24
    rows: int = 4
    bits: int = 2
    #: minima in a sketch, of which the first ``bands * rows`` also make the bands
    perms: int = 256
    margin: float = 3.5
    #: members of an unsettled bucket that meet all others of other components
    hubs: int = 6

    @property
    def lanes(self) -> int:
        """64-bit words of a sketch."""
        return -(-self.perms * self.bits // 64)

    @property
    def least_matches(self) -> int:
        """Matching lanes below which the threshold is ruled out."""
        chance, j = 2.0**-self.bits, self.num / self.den
        p = chance + (1 - chance) * j
        return int(self.perms * (p - self.margin * sqrt(p * (1 - p) / self.perms)))


class Signer:
    """Signatures of shingle sets."""

    BLOCK = 1024

    def __init__(self, params: NearParams):
        rng = np.random.default_rng(20_240_607)
        n = params.perms
        self.params = params
        # 32-bit words: four to eight of them are one vector instruction
        self.mult = rng.integers(0, 2**31, n, dtype=np.uint32)[:, None] * np.uint32(2) + np.uint32(1)
        self.flip = rng.integers(0, 2**32, n, dtype=np.uint32)[:, None]
        self.step = rng.integers(0, 2**63, params.rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)

    def minima(self, shingles: np.ndarray) -> np.ndarray:
        words = (shingles >> np.uint64(32)).astype(np.uint32)
        low = np.full(len(self.mult), 2**32 - 1, dtype=np.uint32)
        for at in range(0, len(words), self.BLOCK):
            x = words[None, at : at + self.BLOCK] ^ self.flip
            x *= self.mult
            np.minimum(low, x.min(axis=1), out=low)
        return low.astype(np.uint64)

    def bands(self, minima: np.ndarray) -> np.ndarray:
        grid = minima[: self.params.bands * self.params.rows].reshape(self.params.bands, self.params.rows)
        return mix((mix(grid) * self.step).sum(axis=1, dtype=np.uint64)).view(np.int64)

    def sketch(self, minima: np.ndarray) -> np.ndarray:
        b = self.params.bits
        lanes = mix(minima) & np.uint64((1 << b) - 1)
        per = 64 // b
        lanes = np.concatenate([lanes, np.zeros(-len(lanes) % per, np.uint64)]).reshape(-1, per)
        return (lanes << (np.arange(per, dtype=np.uint64) * np.uint64(b))).sum(axis=1, dtype=np.uint64).view(np.int64)


    def parities(self, shingles: np.ndarray) -> np.ndarray:
        """For each of 1024 classes of shingles whether the set has an odd number of them, packed."""
        odd = np.bincount((shingles & np.uint64(1023)).astype(np.int64), minlength=1024) & 1
        return np.packbits(odd.astype(np.uint8)).view(np.int64)


SIGNED = "key {key}, n_shingles long, h1 long, h2 long, bands array<long>, sketch array<long>, odd array<long>"


def sign(docs: DataFrame, key: str, text: str, params: NearParams) -> DataFrame:
    """One row per document: set size, 128-bit hash of the set, band keys and sketches (null for an empty set)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        signer, cache = Signer(params), WordHashes()
        for batch in batches:
            out = []
            for t in batch.column(1).to_pylist():
                s = shingle_set(t, params.shingle, cache)
                if not len(s):
                    out.append((0, None, None, None, None, None))
                    continue
                low = signer.minima(s)
                # two sums over a set of well mixed hashes: equal sets and no others, but for 2^-128
                h = np.array([mix(s).sum(dtype=np.uint64), mix(s ^ np.uint64(_LOW)).sum(dtype=np.uint64)]).view(np.int64)
                out.append((len(s), int(h[0]), int(h[1]), signer.bands(low), signer.sketch(low), signer.parities(s)))
            n, h1, h2, bands, sketch, odd = zip(*out, strict=True) if out else ((),) * 6
            longs = pa.list_(pa.int64())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(n, pa.int64()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(bands, longs), pa.array(sketch, longs), pa.array(odd, longs)],
                ["key", "n_shingles", "h1", "h2", "bands", "sketch", "odd"],
            )

    rows = docs.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("string").alias("text"))
    return rows.mapInArrow(run, SIGNED.format(key=rows.schema["key"].dataType.simpleString()))


def matching_lanes(a: Column, b: Column, params: NearParams) -> Column:
    """Lanes in which two packed sketches agree, by bit counts."""
    low = sum(1 << (i * params.bits) for i in range(64 // params.bits)) if params.bits > 1 else -1
    low -= (1 << 64) if low >= 1 << 63 else 0
    differ = None
    for k in range(params.lanes):
        x = a[k].bitwiseXOR(b[k])
        y = x
        for s in range(1, params.bits):
            y = y.bitwiseOR(F.shiftrightunsigned(x, s))
        n = F.bit_count(y.bitwiseAND(F.lit(low).cast("long")))
        differ = n if differ is None else differ + n
    return F.lit(params.perms) - differ


def estimated_similarity(a: Column, b: Column, params: NearParams) -> Column:
    """Jaccard similarity estimated from two sketches, corrected for chance collisions."""
    chance = 2.0**-params.bits
    return F.greatest(F.lit(0.0), (matching_lanes(a, b, params) / F.lit(params.perms) - F.lit(chance)) / F.lit(1 - chance))


def least_differences(a: Column, b: Column) -> Column:
    """Shingles that only one of two sets has, at least: classes whose parities differ."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.bit_count(x.bitwiseXOR(y))), F.lit(0), lambda n, k: n + k)


def _promising(pairs: DataFrame, classes: DataFrame, params: NearParams) -> DataFrame:
    """Of ``a, b`` those whose sizes and sketches allow the threshold."""
    left = classes.select(F.col("rep").alias("a"), F.col("n_shingles").alias("na"), F.col("sketch").alias("sa"))
    right = classes.select(F.col("rep").alias("b"), F.col("n_shingles").alias("nb"), F.col("sketch").alias("sb"))
    fit = (F.least("na", "nb") * params.den >= F.greatest("na", "nb") * params.num) & (matching_lanes(F.col("sa"), F.col("sb"), params) >= params.least_matches)
    return pairs.join(left, "a").join(right, "b").filter(fit).select("a", "b")


def _texts_of(ids: DataFrame, docs: DataFrame, key: str, text: str) -> DataFrame:
    """``id, t`` of the documents in ``ids``, a written table of distinct ids."""
    texts = docs.select(F.col(f"`{key}`").alias("id"), F.col(f"`{text}`").cast("string").alias("t"))
    return texts.join(F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids, "id", "left_semi")


def _confirmed(pairs: DataFrame, docs: DataFrame, key: str, text: str, params: NearParams) -> DataFrame:
    """Of ``a, b`` those whose full sets reach the threshold."""
    ids = store(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), "ids")
    texts = store(_texts_of(ids, docs, key, text), "texts")
    # first the side that is different in most pairs, so that the texts met often move once
    full = pairs.join(texts.select(F.col("id").alias("b"), F.col("t").alias("tb")), "b").join(texts.select(F.col("id").alias("a"), F.col("t").alias("ta")), "a")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, sets = WordHashes(), {}
        for batch in batches:
            keep = []
            for ta, tb in zip(batch.column("ta").to_pylist(), batch.column("tb").to_pylist(), strict=True):
                # a hub meets many, often in a row
                if ta not in sets:
                    if len(sets) > 64:
                        sets.clear()
                    sets[ta] = shingle_set(ta, params.shingle, cache)
                x, y = sets[ta], shingle_set(tb, params.shingle, cache)
                both = len(x) + len(y) - len(np.union1d(x, y))
                keep.append(params.den * both >= params.num * (len(x) + len(y) - both) and both > 0)
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return full.mapInArrow(run, pairs.select("a", "b").schema)


def _own_shingles(reps: DataFrame, docs: DataFrame, key: str, text: str, params: NearParams) -> DataFrame:
    """``rep, own``: how many shingles of each of ``reps`` no other of them has."""
    reps = store(reps, "reps")
    texts = _texts_of(reps.withColumnRenamed("rep", "id"), docs, key, text).withColumnRenamed("id", "rep")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = WordHashes()
        for batch in batches:
            sets = [shingle_set(t, params.shingle, cache).view(np.int64) for t in batch.column("t").to_pylist()]
            at = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
            for k in range(0, len(at), 200_000):
                part = at[k : k + 200_000]
                first, last = part[0], part[-1]
                grams = np.concatenate(sets[first : last + 1])
                skip = k - int(sum(len(s) for s in sets[:first]))
                yield pa.RecordBatch.from_arrays([batch.column("rep").take(pa.array(part)), pa.array(grams[skip : skip + len(part)])], ["rep", "g"])

    kind = reps.schema["rep"].dataType.simpleString()
    grams = texts.mapInArrow(run, f"rep {kind}, g long")
    alone = grams.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.min("rep").alias("rep")).filter("n = 1").groupBy("rep").agg(F.count(F.lit(1)).alias("own"))
    return reps.join(alone, "rep", "left").select("rep", F.coalesce("own", F.lit(0)).alias("own"))


def _unsettled(met: DataFrame, labels: DataFrame) -> DataFrame:
    """The members, with their ``component``, of the buckets whose members are in different components."""
    placed = met.join(labels, F.col("rep") == F.col("node"), "left").withColumn("component", F.coalesce("component", "rep")).drop("node")
    mixed = placed.groupBy("band", "bucket").agg(F.min("component").alias("low"), F.max("component").alias("high")).filter("low <> high").select("band", "bucket")
    return placed.join(mixed, ["band", "bucket"])


_FACTS = ("n_shingles", "common", "bands", "sketch", "odd")


def _possible(params: NearParams) -> Column:
    """Whether two members of different components, the second's columns ending in ``_b``, can be linked."""
    # an intersection holds none of either side's own shingles
    most = F.least("common", "common_b")
    sizes = F.col("n_shingles") + F.col("n_shingles_b")
    return (
        (F.col("component") != F.col("component_b"))
        & (most * params.den >= (sizes - most) * params.num)
        & (matching_lanes(F.col("sketch"), F.col("sketch_b"), params) >= params.least_matches)
        & (least_differences(F.col("odd"), F.col("odd_b")) * (params.den + params.num) <= sizes * (params.den - params.num))
    )


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", params: NearParams = NearParams()) -> DataFrame:
    """``key, n_shingles, component_id, kept`` for every row of ``docs``."""
    spark = docs.sparkSession
    signed = store(sign(docs, key, text, params), "signed")
    full = signed.filter("n_shingles > 0")
    # the columns besides the id are equal within a class, so any one row's will do
    first = full.groupBy("h1", "h2").agg(F.min("key").alias("rep"))
    classes = store(
        full.join(first.withColumnRenamed("h1", "g1").withColumnRenamed("h2", "g2"), (F.col("key") == F.col("rep")) & (F.col("h1") == F.col("g1")) & (F.col("h2") == F.col("g2")))
        .dropDuplicates(["rep", "h1", "h2"])
        .select("rep", "h1", "h2", "n_shingles", "bands", "sketch", "odd"),
        "classes",
    )

    members = classes.select("rep", F.posexplode("bands").alias("band", "bucket"))
    sizes = members.groupBy("band", "bucket").agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    met, met_at = stored(members.join(sizes, ["band", "bucket"]), "buckets")
    # who shares buckets with the most others is nearest to what its group has in common
    weight = met.groupBy("rep").agg(F.sum("n").alias("weight"))
    first_of = F.max(F.struct("weight", F.xxhash64("rep").alias("h"), F.col("rep").alias("hub"))).alias("first")
    hubs = met.join(weight, "rep").groupBy("band", "bucket").agg(first_of).select("band", "bucket", F.col("first.hub").alias("hub"))
    pair = [F.least("hub", "rep").alias("a"), F.greatest("hub", "rep").alias("b")]
    tested, tested_at = stored(_promising(met.join(hubs, ["band", "bucket"]).filter("hub <> rep").select(*pair).distinct(), classes, params), "pairs")
    links = store(_confirmed(tested, docs, key, text, params).distinct(), "links")
    labels = components(links)

    # what hubs leave open: members of one bucket in different components; a bucket of two has been looked at in full
    rest = _unsettled(met.filter("n > 2").select("band", "bucket", "rep"), labels)
    own = _own_shingles(rest.select("rep").distinct(), docs, key, text, params)
    traits = classes.select("rep", "n_shingles", "bands", "sketch", "odd").join(own, "rep").withColumn("common", F.col("n_shingles") - F.col("own"))
    # with too many shingles of its own a document can reach the threshold with nobody
    traits = traits.filter(F.col("common") * params.den >= F.col("n_shingles") * params.num).join(weight, "rep")
    rest, rest_at = stored(rest.join(traits, "rep").select("band", "bucket", "rep", "component", "weight", *_FACTS), "rest")
    other = rest.select("band", "bucket", "weight", *[F.col(c).alias(f"{c}_b") for c in ("rep", "component", *_FACTS)])

    order = Window.partitionBy("band", "bucket").orderBy(F.desc("weight"), F.xxhash64("rep_b"), "rep_b")
    central = other.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= params.hubs).drop("weight", "place")
    pair = [F.least("rep", "rep_b").alias("a"), F.greatest("rep", "rep_b").alias("b")]
    again = rest.join(central, ["band", "bucket"]).filter(_possible(params)).select(*pair).distinct().join(tested, ["a", "b"], "left_anti")
    again, again_at = stored(again, "pairs")
    if not again.isEmpty():
        links = store(links.union(_confirmed(again, docs, key, text, params)).distinct(), "links")
        labels = components(links)

    # a pair that shares several buckets is taken in the first; lambdas keep this out of the generated
    # method, which would grow too long to be compiled, and run for pairs that pass the rest only
    first = F.array_position(F.zip_with("bands", "bands_b", lambda x, y: x == y), F.lit(True)) == F.col("band") + 1
    rest, open_at = stored(_unsettled(rest.drop("component", "weight"), labels), "open")
    other = rest.select("band", "bucket", *[F.col(c).alias(f"{c}_b") for c in ("rep", "component", *_FACTS)])
    joined = rest.join(other, ["band", "bucket"]).filter((F.col("rep") < F.col("rep_b")) & _possible(params) & first)
    open_pairs, pairs_at = stored(joined.select(F.col("rep").alias("a"), F.col("rep_b").alias("b")).join(tested.union(again), ["a", "b"], "left_anti"), "pairs")
    if not open_pairs.isEmpty():
        more = store(_confirmed(open_pairs, docs, key, text, params).distinct(), "links")
        if not more.isEmpty():
            labels = components(links.union(more))
    discard(spark, met_at, tested_at, rest_at, again_at, open_at, pairs_at)

    # one row per class that is linked with another
    moved = classes.select("rep", "h1", "h2").join(labels, F.col("rep") == F.col("node"), "left").select(F.col("h1").alias("c1"), F.col("h2").alias("c2"), F.coalesce("component", "rep").alias("component_id"))
    rows = signed.select("key", "n_shingles", "h1", "h2")
    out = rows.join(moved, (rows["h1"] == moved["c1"]) & (rows["h2"] == moved["c2"]), "left")
    component = F.coalesce("component_id", "key")
    return out.select(F.col("key").alias(key), "n_shingles", component.alias("component_id"), F.col("key").eqNullSafe(component).alias("kept"))


def keep_one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text", params: NearParams = NearParams()) -> DataFrame:
    """The rows of ``docs`` that stand for their component; rows with equal ids stay or go together."""
    kept = near_duplicates(docs, key, text, params).filter("kept").select(F.col(key).alias("__kept")).distinct()
    return docs.join(kept, docs[key].eqNullSafe(kept["__kept"]), "left_semi")
