"""Media columns: local image descriptors that find cropped and edited copies.

1. An image (binary PGM or PPM) is brought to grey and to several scales. Corners are maxima, within
   ``apart`` places, of the smaller eigenvalue of the gradient matrix, so their number follows the
   image's area; a corner's direction is that from its place to the centre of grey mass around it; 256
   comparisons of smoothed grey values, turned by that direction, are its bits.
2. Each of ``tables`` tables picks ``word`` of the bits. Two descriptors that agree in a table's word meet, and
   stay if their Hamming distance is at most ``distance``.
3. A match of two corners implies a turn, a scale and a place of the one image's centre in the other.
   Matches of two images vote for them in coarse bins, each for the two nearest on every axis of the
   place; the images are linked if one bin gets ``votes`` votes from different corners of the query.

Images of equal bytes are one class, named by the smallest id; a class meets others once, whatever its
size. An image is read, decoded and described in one pass and passes no exchange. A search with at most
``BROADCAST_POINTS`` corners on the query side broadcasts their tables and finds the links of an image
where it is; with more, corners meet by a join on the words. Both give the same links.

Results for odd rows: a null, empty or undecodable image has no points and no links, a null one no class
either. A row without an id is named by its class only. Repeated rows belong to one class. Empty
tables give empty results. Only the named columns are read.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geoherald.llm.scratch import store

BROADCAST_POINTS = 200_000
HEADER = re.compile(rb"P([56])\s+(?:#[^\n]*\n\s*)*(\d+)\s+(\d+)\s+(\d+)\s")


@dataclass(frozen=True)
class ImageParams:
    scales: tuple[float, ...] = (1.0, 0.8, 0.64, 0.512)
    margin: int = 11
    apart: int = 4
    tables: int = 14
    word: int = 42
    distance: int = 30
    turns: int = 36
    votes: int = 6
    bin: float = 8.0


def decode(data: bytes | None) -> np.ndarray | None:
    """Grey values as floats, or None for what is no complete PGM or PPM of 8 bits."""
    m = HEADER.match(data) if data else None
    if m is None or int(m[4]) > 255:
        return None
    width, height, depth = int(m[2]), int(m[3]), 3 if m[1] == b"6" else 1
    body = data[m.end() :]
    if width * height == 0 or len(body) < width * height * depth:
        return None
    grid = np.frombuffer(body, np.uint8, width * height * depth).reshape(height, width, depth)
    return grid.astype(np.float32).mean(axis=2)


def encode(grid: np.ndarray) -> bytes:
    height, width = grid.shape
    return b"P5 %d %d 255\n" % (width, height) + np.clip(np.rint(grid), 0, 255).astype(np.uint8).tobytes()


def box(grid: np.ndarray, r: int) -> np.ndarray:
    """Sums over squares of side 2r+1, by running sums; the border repeats its last values."""
    padded = np.pad(grid, r, mode="edge")
    total = np.pad(padded.cumsum(axis=0).cumsum(axis=1), ((1, 0), (1, 0)))
    n = 2 * r + 1
    return total[n:, n:] - total[:-n, n:] - total[n:, :-n] + total[:-n, :-n]


def resized(grid: np.ndarray, height: int, width: int) -> np.ndarray:
    """Bilinear."""
    y = np.linspace(0, grid.shape[0] - 1, height)
    x = np.linspace(0, grid.shape[1] - 1, width)
    y0, x0 = np.floor(y).astype(int), np.floor(x).astype(int)
    y1, x1 = np.minimum(y0 + 1, grid.shape[0] - 1), np.minimum(x0 + 1, grid.shape[1] - 1)
    fy, fx = (y - y0)[:, None], (x - x0)[None, :]
    top = grid[y0][:, x0] * (1 - fx) + grid[y0][:, x1] * fx
    return top * (1 - fy) + (grid[y1][:, x0] * (1 - fx) + grid[y1][:, x1] * fx) * fy


@lru_cache
def _comparisons(turns: int) -> np.ndarray:
    """Offsets of the two places of each of 256 comparisons, for each direction: turns x 256 x 2 x 2."""
    rng = np.random.default_rng(4711)
    # spread evenly over a disc, so that what is around a corner counts as much as the corner
    far, way = 10.4 * np.sqrt(rng.random((256, 2))), 2 * np.pi * rng.random((256, 2))
    ends = np.stack([far * np.cos(way), far * np.sin(way)], -1)
    angles = np.arange(turns) * 2 * np.pi / turns
    turn = np.stack([np.stack([np.cos(angles), -np.sin(angles)], -1), np.stack([np.sin(angles), np.cos(angles)], -1)], -2)
    return np.rint(np.einsum("tij,ekj->teki", turn, ends)).astype(int)


def _highest(grid: np.ndarray, r: int) -> np.ndarray:
    """Maxima over squares of side 2r+1."""
    for axis in (0, 1):
        width = [(r, r) if k == axis else (0, 0) for k in (0, 1)]
        grid = np.lib.stride_tricks.sliding_window_view(np.pad(grid, width, constant_values=-np.inf), 2 * r + 1, axis=axis).max(axis=-1)
    return grid


def describe(data: bytes | None, params: ImageParams) -> list[tuple[float, float, float, float, list[int]]]:
    """Points as x and y from the image's centre, scale, direction and four words of 64 bits."""
    grid = decode(data)
    if grid is None:
        return []
    found = []
    r = params.margin
    for scale in params.scales:
        h, w = int(grid.shape[0] * scale), int(grid.shape[1] * scale)
        if min(h, w) <= 2 * r + 2:
            continue
        g = grid if scale == 1.0 else resized(grid, h, w)
        smooth = box(g, 1) / 9
        gy, gx = np.gradient(smooth)
        a, b, c = box(gx * gx, 2), box(gy * gy, 2), box(gx * gy, 2)
        strength = (a + b) / 2 - np.sqrt(((a - b) / 2) ** 2 + c * c)
        core = strength[r : h - r, r : w - r]
        y, x = np.nonzero((core >= _highest(core, params.apart)) & (core > 20.0))
        if not len(y):
            continue
        y, x = y + r, x + r
        ky, kx = np.mgrid[-5:6, -5:6]
        disc = ky * ky + kx * kx <= 27
        ky, kx = ky[disc], kx[disc]
        patch = smooth[y[:, None] + ky, x[:, None] + kx]
        patch = patch - patch.mean(axis=1, keepdims=True)
        angle = np.arctan2((patch * ky).sum(axis=1), (patch * kx).sum(axis=1))
        at = _comparisons(params.turns)[np.rint(angle / (2 * np.pi) * params.turns).astype(int) % params.turns]
        soft = box(g, 2)
        one = soft[y[:, None] + at[:, :, 0, 1], x[:, None] + at[:, :, 0, 0]]
        two = soft[y[:, None] + at[:, :, 1, 1], x[:, None] + at[:, :, 1, 0]]
        words = np.packbits(one < two, axis=1).view(">i8").astype(np.int64)
        x, y = (x - (w - 1) / 2) / scale, (y - (h - 1) / 2) / scale
        found += zip(x.tolist(), y.tolist(), [1 / scale] * len(x), angle.tolist(), words.tolist(), strict=True)
    return found


_NAMES = ("x", "y", "scale", "angle")
POINT = T.ArrayType(T.StructType([*[T.StructField(n, T.FloatType()) for n in _NAMES], T.StructField("bits", T.ArrayType(T.LongType()))]))
_POINT = pa.list_(pa.struct([*[(n, pa.float32()) for n in _NAMES], ("bits", pa.list_(pa.int64()))]))


def points_column(image: Column, params: ImageParams) -> Column:
    @F.arrow_udf(POINT)
    def points(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for images in batches:
            yield pa.array([[dict(zip((*_NAMES, "bits"), p, strict=True)) for p in describe(d, params)] for d in images.to_pylist()], _POINT)

    return points(image)


def find_copies(media: DataFrame, queries: Column, key: str = "id", image: str = "image", change=None, params: ImageParams = ImageParams()) -> DataFrame:
    """``key, class_id, n_points, copy_of`` for every row: ``copy_of`` lists the classes of the rows that
    ``queries`` picks whose image (after ``change``, if given) this image is linked with.

    A row's class is the smallest id with the same bytes; a row without an image has none, and no links.
    """
    asks = F.coalesce(queries, F.lit(False))
    rows = media.select(F.col(f"`{key}`").alias("id"), F.col(f"`{image}`").alias("image"), asks.alias("asks"))
    asked = F.when(F.col("asks"), F.col("image"))
    rows = rows.select("id", "asks", F.sha2("image", 256).alias("digest"), points_column(F.col("image"), params).alias("points"), points_column(change(asked) if change else asked, params).alias("asked"))
    rows = store(rows, "media")
    kinds = rows.filter("digest is not null and id is not null").groupBy("digest").agg(F.min("id").alias("class_id"), F.max("asks").alias("asks"))
    kinds = store(kinds, "image-classes")
    named = rows.join(kinds.select("digest", "class_id", F.col("asks").alias("sought")), "digest")
    described = named.filter("id = class_id").select("id", "points").dropDuplicates(["id"])
    # whichever row of a class asks, the image is the same
    asked = named.filter("asks and sought").select(F.col("class_id").alias("id"), F.col("asked").alias("points")).dropDuplicates(["id"])
    links = search(asked, described, params).groupBy(F.col("d").alias("found")).agg(F.array_sort(F.collect_set("q")).alias("copy_of"))
    facts = described.select("id", F.size("points").alias("n_points")).join(links, F.col("id") == F.col("found"), "left")
    facts = facts.join(kinds.select(F.col("class_id").alias("id"), F.col("digest").alias("of")), "id").select("of", F.col("id").alias("class_id"), "n_points", "copy_of")
    none = F.array().cast(T.ArrayType(rows.schema["id"].dataType))
    out = rows.select("id", "digest").join(facts, F.col("digest") == F.col("of"), "left")
    return out.select(F.col("id").alias(key), "class_id", F.coalesce("n_points", F.lit(0)).alias("n_points"), F.coalesce("copy_of", none).alias("copy_of"))


@lru_cache
def _picked(params: ImageParams) -> np.ndarray:
    """The bits that each table looks at."""
    rng = np.random.default_rng(1_969)
    return np.stack([rng.permutation(256)[: params.word] for _ in range(params.tables)])


def table_words(bits: np.ndarray, params: ImageParams) -> np.ndarray:
    """One row per table: the picked bits of each descriptor as a number under the table's."""
    single = np.unpackbits(bits.astype(">i8").view(np.uint8).reshape(len(bits), 32), axis=1)
    weights = np.int64(1) << np.arange(params.word, dtype=np.int64)
    return np.stack([single[:, pick] @ weights + (np.int64(t) << np.int64(params.word)) for t, pick in enumerate(_picked(params))])


def _columns(points: pa.ListArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of a column of point lists: where each list starts, the four numbers of each point, its bits."""
    flat = points.flatten()
    starts = np.concatenate([[0], np.cumsum(points.value_lengths().fill_null(0).to_numpy())])
    numbers = np.stack([flat.field(n).to_numpy(zero_copy_only=False) for n in _NAMES], axis=1).reshape(-1, 4)
    return starts, numbers.astype(np.float64), flat.field("bits").flatten().to_numpy(zero_copy_only=False).reshape(-1, 4)


def bins_of(query: np.ndarray, other: np.ndarray, params: ImageParams) -> np.ndarray:
    """Turn, ratio and the four places that matches vote for: matches x 4 x 4, in whole numbers."""
    angle = (other[:, 3] - query[:, 3]) % (2 * np.pi)
    ratio = other[:, 2] / query[:, 2]
    x = other[:, 0] - ratio * (np.cos(angle) * query[:, 0] - np.sin(angle) * query[:, 1])
    y = other[:, 1] - ratio * (np.sin(angle) * query[:, 0] + np.cos(angle) * query[:, 1])
    # eight turns, the first of which has 0 in its middle
    turn = np.floor(angle / (np.pi / 4) + 0.5) % 8
    out = np.empty((len(query), 4, 4), np.int64)
    out[:, :, 0], out[:, :, 1] = turn[:, None], np.rint(np.log2(ratio) * 2)[:, None]
    near = lambda v: (np.floor(v / params.bin), np.floor(v / params.bin + 0.5) + 1_000_000)
    for k, (bx, by) in enumerate((a, b) for a in near(x) for b in near(y)):
        out[:, k, 2], out[:, k, 3] = bx, by
    return out


def most_votes(corner: np.ndarray, bins: np.ndarray) -> int:
    """The most different corners that vote for one bin."""
    if len(corner) == 0:
        return 0
    # the four numbers of a bin as one, then as a rank; places are within 2^20 bins of each other
    low = bins - bins.min(axis=(0, 1))
    number = ((low[:, :, 0] * 64 + low[:, :, 1]) << 42) + (low[:, :, 2] << 21) + low[:, :, 3]
    rank = np.unique(number, return_inverse=True)[1].reshape(-1)
    voters = np.unique(rank * (int(corner.max()) + 1) + np.repeat(corner, 4)) // (int(corner.max()) + 1)
    return int(np.bincount(voters).max())


class QueryTables:
    """The corners of the query images, in sorted tables of words."""

    def __init__(self, ids: list, points: pa.ListArray, params: ImageParams):
        self.ids, self.params = ids, params
        starts, self.numbers, self.bits = _columns(points)
        self.owner = np.repeat(np.arange(len(ids)), np.diff(starts))
        self.words = table_words(self.bits, params) if len(self.bits) else np.zeros((params.tables, 0), np.int64)
        self.order = np.argsort(self.words, axis=1, kind="stable").astype(np.int32)
        self.words = np.take_along_axis(self.words, self.order, axis=1)

    def matches(self, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Corners of the queries and of one image that share a word and are near."""
        found = []
        for words, order, own in zip(self.words, self.order, table_words(bits, self.params), strict=True):
            first, last = np.searchsorted(words, own), np.searchsorted(words, own, side="right")
            n = last - first
            if n.any():
                at = np.repeat(first - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
                found.append(order[at].astype(np.int64) * len(bits) + np.repeat(np.arange(len(bits)), n))
        if not found:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        q, d = np.divmod(np.unique(np.concatenate(found)), len(bits))
        near = np.bitwise_count((self.bits[q] ^ bits[d]).view(np.uint64)).sum(axis=1) <= self.params.distance
        return q[near], d[near]

    def linked(self, numbers: np.ndarray, bits: np.ndarray) -> list[tuple[object, int]]:
        """Ids of the queries that one image is linked with, and the votes."""
        if not len(bits) or not len(self.bits):
            return []
        q, d = self.matches(bits)
        # the corners of a query stand together
        owners, first, n = np.unique(self.owner[q], return_index=True, return_counts=True)
        out = []
        for owner, at, count in zip(owners, first, n, strict=True):
            if count >= self.params.votes:
                part = slice(at, at + count)
                votes = most_votes(q[part], bins_of(self.numbers[q[part]], numbers[d[part]], self.params))
                if votes >= self.params.votes:
                    out.append((self.ids[owner], votes))
        return out


def search(queries: DataFrame, described: DataFrame, params: ImageParams = ImageParams()) -> DataFrame:
    """``q, d, votes`` for linked images; both sides have ``id`` and ``points``."""
    queries = store(queries.select("id", "points"), "query-points")
    if (queries.agg(F.sum(F.size("points"))).first()[0] or 0) > BROADCAST_POINTS:
        return _search_joined(queries, described, params)
    table = queries.toArrow()
    held = queries.sparkSession.sparkContext.broadcast((table.column("id").to_pylist(), table.column("points").combine_chunks()))
    kind, id_type = queries.schema["id"].dataType.simpleString(), table.schema.field("id").type

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = QueryTables(*held.value, params)
        for batch in batches:
            starts, numbers, bits = _columns(batch.column("points"))
            out = [(batch.column("id")[k].as_py(), *link) for k in range(batch.num_rows) for link in tables.linked(numbers[starts[k] : starts[k + 1]], bits[starts[k] : starts[k + 1]])]
            d, q, votes = zip(*out, strict=True) if out else ((),) * 3
            yield pa.RecordBatch.from_arrays([pa.array(q, id_type), pa.array(d, batch.schema.field("id").type), pa.array(votes, pa.int32())], ["q", "d", "votes"])

    return described.select("id", "points").mapInArrow(run, f"q {kind}, d {kind}, votes int")


def _search_joined(queries: DataFrame, described: DataFrame, params: ImageParams) -> DataFrame:
    """As :func:`search`, by a join of the corners of both sides on their words."""

    @F.arrow_udf(T.ArrayType(T.LongType()))
    def words_of(bits: pa.Array) -> pa.Array:
        grid = bits.flatten().to_numpy(zero_copy_only=False).reshape(-1, 4)
        return pa.array(list(table_words(grid, params).T) if len(grid) else [], pa.list_(pa.int64()))

    def spread(rows: DataFrame, side: str) -> DataFrame:
        corners = rows.select(F.col("id").alias(side), F.posexplode("points").alias(f"k_{side}", f"p_{side}"))
        return corners.select(side, f"k_{side}", f"p_{side}", F.explode(words_of(F.col(f"p_{side}.bits"))).alias("word"))

    unlike = sum((F.bit_count(F.col("p_q.bits")[i].bitwiseXOR(F.col("p_d.bits")[i])) for i in range(4)), F.lit(0))
    hits = spread(described, "d").join(spread(queries, "q"), "word").filter(unlike <= params.distance)
    numbers = lambda side: F.array(*[F.col(f"p_{side}.{n}") for n in _NAMES])
    # few pairs of images have more than a few hits; a pair has at most one for two of its corners and a table
    hits = hits.groupBy("q", "d").agg(F.collect_set(F.struct("k_q", "k_d", numbers("q").alias("a"), numbers("d").alias("b"))).alias("hits"))

    @F.arrow_udf("int")
    def votes_of(pairs: pa.Array) -> pa.Array:
        out = []
        for row in pairs.to_pylist():
            side = lambda n: np.array([h[n] for h in row], np.float64).reshape(-1, 4)  # noqa: B023, E731
            out.append(most_votes(np.array([h["k_q"] for h in row]), bins_of(side("a"), side("b"), params)))
        return pa.array(out, pa.int32())

    voted = hits.filter(F.size("hits") >= params.votes).select("q", "d", votes_of(F.col("hits")).alias("votes"))
    return voted.filter(F.col("votes") >= params.votes)


def rendered(vector: Column) -> Column:
    """A picture made of a vector: its numbers as a coarse grid of grey, under rectangles drawn from its
    hash. A stand-in for a media column, for tables that have vectors but no pictures."""

    @F.arrow_udf(T.BinaryType())
    def draw(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for vectors in batches:
            yield pa.array([None if v is None else picture(v) for v in vectors.to_pylist()], pa.binary())

    return draw(vector)


def picture(vector: list[float], side: int = 96) -> bytes:
    v = np.nan_to_num(np.array([x if x is not None else 0.0 for x in vector] or [0.0], dtype=np.float32))
    n = max(2, int(len(v) ** 0.5))
    grid = np.resize(v, (n, n)).astype(np.float64)
    grid = 128 + 60 * np.tanh(3 * grid)
    out = resized(grid, side, side)
    rng = np.random.default_rng(np.frombuffer(v.tobytes(), np.uint32))
    for _ in range(26):
        y, x = rng.integers(0, side - 8, 2)
        h, w = rng.integers(5, 26, 2)
        out[y : y + h, x : x + w] = 0.35 * out[y : y + h, x : x + w] + 0.65 * rng.integers(0, 256)
    return encode(out)


def edited(image: Column) -> Column:
    """A cropped copy with changed brightness and contrast."""

    @F.arrow_udf(T.BinaryType())
    def edit(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for images in batches:
            out = []
            for data in images.to_pylist():
                grid = decode(data)
                out.append(None if grid is None else encode(grid[grid.shape[0] // 10 :, grid.shape[1] // 8 :] * 0.8 + 20))
            yield pa.array(out, pa.binary())

    return edit(image)
