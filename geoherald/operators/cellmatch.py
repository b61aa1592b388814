"""Matching inside a cell: its lists in columns, and batches of objects that go through them.

What is looked at is what :func:`geoherald.operators.matching.match_once` looks at: a clause is listed under its
routing term, and a pair is found under the first clause that it satisfies, so it is found once. Nothing is capped:
pairs leave in batches as they are found, and of a tile of cells its subscriptions and the lists of one cell are held.
Rows go to their tiles in blocks: columns of numbers, each as the bytes that its values differ in, compressed, with terms by their place
in a shared table of codes. Without workers, a row goes to the tiles of its rectangle (:func:`packed`). Postings and objects that
have their workers go to these, tile by tile (:func:`placed`): a clause is listed in the cells, at the workers and under the terms
of its postings and nowhere else, and an object meets the lists of the workers that it was sent to. Tasks get this module by value,
so it imports nothing of the package.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from dataclasses import dataclass, fields
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: Entries that are looked at together, and places of the table of objects by words.
TOGETHER = 1 << 20
TABLE = 1 << 25
#: Rows that are dealt out to blocks together.
PACKED = 1 << 18
#: Columns, and rows, of cells that go through the exchange together, as one tile.
TILE = 2
#: More than the pieces of a tile.
PIECES = 1 << 10
FOUND = pa.schema([("sub_id", pa.int64()), ("obj_id", pa.int64())])


@dataclass
class Chart:
    """Whose a term is in a cell, as ``Assignment.place`` has it, by the terms' codes."""

    leaf_of: np.ndarray
    workers: list[np.ndarray]
    heads: list[tuple[np.ndarray, np.ndarray]]

    def worker(self, cell: int, codes: np.ndarray) -> np.ndarray:
        leaf = self.leaf_of[cell]
        workers, (known, parts) = self.workers[leaf], self.heads[leaf]
        part = codes % len(workers)
        if len(known):
            at = np.minimum(np.searchsorted(known, codes), len(known) - 1)
            part = np.where(known[at] == codes, parts[at], part)
        return workers[part]


@dataclass
class Words:
    """Codes of terms, the more frequent ones first, and so the rarest of a clause has the largest place."""

    codes: np.ndarray

    def __post_init__(self):
        self.order = np.argsort(self.codes)
        self.sorted = self.codes[self.order]

    def places(self, codes: np.ndarray) -> np.ndarray:
        """The place of each code; of one that is not there, the number of codes."""
        if not len(self.codes):
            return np.zeros(len(codes), dtype=np.int64)
        at = np.minimum(np.searchsorted(self.sorted, codes), len(self.codes) - 1)
        return np.where(self.sorted[at] == codes, self.order[at], len(self.codes))


def squeeze(columns: list[np.ndarray]) -> bytes:
    """Columns of 64-bit numbers in as few bytes as their ranges need, planes of bytes side by side."""
    parts = []
    for column in columns:
        low = column.min() if len(column) else np.int64(0)
        apart = (column - low).view(np.uint64)
        width = (int(apart.max(initial=0)).bit_length() + 7) // 8
        planes = np.ascontiguousarray(apart).view(np.uint8).reshape(-1, 8)[:, :width]
        parts += [struct.pack("<IqB", len(column), int(low), width), planes.T.tobytes()]
    raw = b"".join(parts)
    return struct.pack("<I", len(raw)) + pa.compress(raw, codec="zstd", asbytes=True)


def spread(block: bytes) -> list[np.ndarray]:
    """The columns of a block."""
    raw = pa.decompress(block[4:], decompressed_size=struct.unpack_from("<I", block)[0], codec="zstd", asbytes=True)
    at, columns = 0, []
    while at < len(raw):
        n, low, width = struct.unpack_from("<IqB", raw, at)
        at += 13
        planes = np.zeros((n, 8), dtype=np.uint8)
        planes[:, :width] = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
        at += n * width
        columns.append(planes.view(np.int64).ravel() + np.int64(low))
    return columns


def _gathered(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held, n = [], 0
    for batch in batches:
        held.append(batch)
        n += batch.num_rows
        if n >= PACKED:
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def _dealt(cell: np.ndarray, ids: np.ndarray, cuts: tuple, kind: int) -> tuple[np.ndarray, np.ndarray]:
    """The piece of its tile that a row is dealt to, -1 for each piece, and the number of pieces."""
    cells, pieces, by_object = cuts
    if not len(cells):
        return np.zeros(len(cell), dtype=np.int64), np.ones(len(cell), dtype=np.int64)
    at = np.minimum(np.searchsorted(cells, cell), len(cells) - 1)
    cut = cells[at] == cell
    n = np.where(cut, pieces[at], 1)
    mixed = (ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)
    one = (mixed % n.astype(np.uint64)).astype(np.int64)
    return np.where(cut & (by_object[at] != (kind == 1)), -1, one), n


def _nth(cx: np.ndarray, cy: np.ndarray) -> np.ndarray:
    """The place of a cell in its tile."""
    return cy % TILE * TILE + cx % TILE


class Columns:
    """Columns of rows that are to go into blocks, their terms by place."""

    NAMES = ("id", "x0", "x1", "y0", "y1", "since", "until")

    def __init__(self, rows: pa.Table, known: Words):
        self.rows, self.known = rows, known
        self.id, self.x0, self.x1, self.y0, self.y1, self.since, self.until = (self.numbers(c) for c in self.NAMES)
        keys = pa.concat_arrays(rows["keys"].chunks)
        clauses = keys.flatten()
        self.n_clauses, self.n_words, self.codes = _lengths(keys), _lengths(clauses), clauses.flatten().to_numpy()
        self.places = known.places(self.codes)
        self.new = bool((self.places == len(known.codes)).any())
        self.first_clause = _starts(self.n_clauses)
        first_word, many_words = np.concatenate([[0], np.cumsum(self.n_words)]), np.concatenate([[0], np.cumsum(self.n_clauses)])
        self.word_from, self.word_to = first_word[self.first_clause], first_word[many_words[1:]]

    def numbers(self, name: str) -> np.ndarray:
        return self.rows[name].combine_chunks().to_numpy(zero_copy_only=False).astype(np.int64)

    def block(self, r: np.ndarray, workers: np.ndarray, listed: np.ndarray, terms: np.ndarray) -> bytes:
        """Rows ``r``; ``workers`` by row, and ``listed`` and the codes of ``terms`` by clause, can be empty."""
        c = _each(self.first_clause[r], self.n_clauses[r])
        w = _each(self.word_from[r], self.word_to[r] - self.word_from[r])
        place, more = self.places[w], np.zeros(0, dtype=np.int64)
        if self.new and (other := place == len(self.known.codes)).any():
            more, back = np.unique(self.codes[w][other], return_inverse=True)
            place[other] += back
        n_words = self.n_words[c]
        clause = np.repeat(np.arange(len(c)), n_words)
        # words of a clause in the order of their places: what lies between them needs fewer bytes
        order = np.lexsort((place, clause))
        place = place[order]
        under = np.zeros(len(terms), dtype=np.int64)
        if len(terms):
            at = np.flatnonzero(self.codes[w][order] == np.repeat(terms, n_words))
            under[clause[at]] = at - _starts(n_words)[clause[at]]
        apart = np.diff(place, prepend=0)
        starts = _starts(n_words)[n_words > 0]
        apart[starts] = place[starts]
        width = self.x1[r] - self.x0[r]
        numbers = [np.diff(self.id[r], prepend=0), self.x0[r], width, self.y0[r], self.y1[r] - self.y0[r] - width, self.since[r], self.until[r], self.n_clauses[r], n_words]
        return squeeze([*numbers, place[starts], np.delete(apart, starts), more, workers, listed, under])


NONE = np.zeros(0, dtype=np.int64)


def _cut(*keys: np.ndarray) -> list[int]:
    """Where rows that are sorted by ``keys`` have another key than the row before, and the ends."""
    apart = np.zeros(max(len(keys[0]) - 1, 0), dtype=bool)
    for key in keys:
        apart |= np.diff(key) != 0
    return [0, *(np.flatnonzero(apart) + 1).tolist(), len(keys[0])] if len(keys[0]) else []


def packed(batches: Iterator[pa.RecordBatch], kind: int, side: int, words: np.ndarray, cuts: tuple) -> Iterator[pa.RecordBatch]:
    """Subscriptions (``kind`` 0) or objects (1) to blocks by tile and piece. A row with ``cx0, cx1, cy0, cy1`` is in all cells
    from the first to the last column and row of a grid with ``side`` columns, and goes once to each tile with such a cell.
    Blocks have their tile's first cell; those of objects are of one cell each, and their kind is 1 and its :func:`_nth`."""
    known = Words(words)
    for rows in _gathered(batches):
        columns = Columns(rows, known)
        cx0, cx1, cy0, cy1 = (columns.numbers(c) for c in ("cx0", "cx1", "cy0", "cy1"))
        tx0, ty0 = cx0 // TILE, cy0 // TILE
        wide = cx1 // TILE - tx0 + 1
        copies = wide * (cy1 // TILE - ty0 + 1)
        row = np.repeat(np.arange(rows.num_rows), copies)
        nth = np.arange(len(row)) - np.repeat(_starts(copies), copies)
        cell = ((ty0[row] + nth // wide[row]) * side + tx0[row] + nth % wide[row]) * TILE
        kinds = 1 + _nth(cx0, cy0)[row] if kind == 1 else np.zeros(len(row), dtype=np.int64)
        salt, pieces = _dealt(cell, columns.id[row], cuts, kind)
        order = np.lexsort((columns.id[row], kinds, salt, cell))
        row, cell, salt, kinds, pieces = row[order], cell[order], salt[order], kinds[order], pieces[order]
        bounds = _cut(cell, salt, kinds)
        yield from _blocks((int(cell[a]), s, int(kinds[a]), block) for a, b in zip(bounds, bounds[1:]) for block in (columns.block(row[a:b], NONE, NONE, NONE),) for s in _salts(salt[a], pieces[a]))


def placed(batches: Iterator[pa.RecordBatch], kind: int, side: int, words: np.ndarray, cuts: tuple, places: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """Postings (``kind`` 0) or objects at their workers (1) to blocks by tile, place and piece. Cells of one place have the same
    workers; ``places`` has it for each cell, and without it each worker is a place. A subscription, or an object, goes once to a
    tile of a place, with all postings that it has there, or all workers that it was sent to."""
    known = Words(words)
    for rows in _gathered(batches):
        columns = Columns(rows, known)
        at, worker = columns.numbers("cell"), columns.numbers("worker")
        cx, cy = at % side, at // side
        cell = (cy // TILE * side + cx // TILE) * TILE
        place = worker if places is None else places[at]
        slot = np.zeros(len(at), dtype=np.int64) if places is None else worker
        kinds = 1 + _nth(cx, cy) if kind == 1 else np.zeros(len(at), dtype=np.int64)
        salt, pieces = _dealt(cell, columns.id, cuts, kind)
        order = np.lexsort((columns.id, kinds, salt, place, cell))
        row = order
        cell, place, salt, kinds, pieces = cell[order], place[order], salt[order], kinds[order], pieces[order]
        ones = np.array(_cut(cell, place, salt, kinds, columns.id[order])[:-1], dtype=np.int64)
        row, n = order[ones], np.diff(ones, append=len(order))
        workers = listed = terms = NONE
        if kind == 1:
            workers = np.bitwise_or.reduceat(np.int64(1) << slot[order], ones) if len(ones) else NONE
        else:
            # of each clause, its cells in the tile, its worker and its term
            clauses = pa.concat_arrays(rows["clauses"].chunks).take(pa.array(order))
            many = _lengths(clauses)
            clause = clauses.flatten().to_numpy().astype(np.int64) + np.repeat(_starts(columns.n_clauses[row]), n).repeat(many)
            listed, terms = np.zeros(int(columns.n_clauses[row].sum()), dtype=np.int64), np.zeros(int(columns.n_clauses[row].sum()), dtype=np.int64)
            np.bitwise_or.at(listed, clause, np.repeat((np.int64(1) << _nth(cx, cy)[order]) | slot[order] << TILE * TILE, many))
            terms[clause] = np.repeat(columns.numbers("term")[order], many)
        cell, place, salt, kinds, pieces = cell[ones], place[ones], salt[ones], kinds[ones], pieces[ones]
        bounds, starts = _cut(cell, place, salt, kinds), np.concatenate([[0], np.cumsum(columns.n_clauses[row])])

        def block(a: int, b: int) -> bytes:
            part = slice(starts[a], starts[b])
            return columns.block(row[a:b], workers[a:b], listed[part], terms[part])  # noqa: B023

        yield from _blocks((int(cell[a]), int(place[a]) * PIECES + s, int(kinds[a]), bytes_) for a, b in zip(bounds, bounds[1:]) for bytes_ in (block(a, b),) for s in _salts(salt[a], pieces[a]))


def _salts(salt: int, pieces: int) -> list[int]:
    return list(range(int(pieces))) if salt < 0 else [int(salt)]


def _blocks(found: Iterator[tuple]) -> Iterator[pa.RecordBatch]:
    while held := list(islice(found, 1000)):
        yield _batch(held)


def _batch(found: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found), (pa.int32(), pa.int32(), pa.int32(), pa.binary()))], ["cell", "salt", "kind", "block"])


def _each(first: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The ``n`` numbers from each ``first`` on."""
    return np.arange(int(n.sum())) + np.repeat(first - _starts(n), n)


@dataclass
class Rows:
    """Rows of a block, or of several; ``codes`` are those of the clauses' words, ``places`` tell which are rarer. Of objects that were
    sent to workers, ``workers`` has a bit for each. Of postings, ``listed`` has the cells of a clause, a bit each, and beyond them its
    worker, and ``under`` which of its words it is listed under. All three are empty without workers."""

    id: np.ndarray
    x0: np.ndarray
    x1: np.ndarray
    y0: np.ndarray
    y1: np.ndarray
    since: np.ndarray
    until: np.ndarray
    n_clauses: np.ndarray
    n_words: np.ndarray
    places: np.ndarray
    codes: np.ndarray
    workers: np.ndarray
    listed: np.ndarray
    under: np.ndarray

    @staticmethod
    def of(block: bytes, words: np.ndarray) -> Rows:
        ids, x0, width, y0, taller, since, until, n_clauses, n_words, firsts, apart, more, workers, listed, under = spread(block)
        starts = _starts(n_words)[n_words > 0]
        later = np.ones(int(n_words.sum()), dtype=bool)
        later[starts] = False
        places = np.zeros(len(later), dtype=np.int64)
        places[later] = apart
        # running sums that begin anew with each clause
        places[starts] = firsts
        sums = np.cumsum(places)
        places = sums - np.repeat(sums[starts] - firsts, n_words[n_words > 0])
        codes = np.concatenate([words, more])[places] if len(more) else words[places]
        return Rows(np.cumsum(ids), x0, x0 + width, y0, y0 + width + taller, since, until, n_clauses, n_words, places, codes, workers, listed, under)

    @staticmethod
    def together(parts: list[Rows]) -> Rows:
        return Rows(*(np.concatenate([getattr(p, f.name) for p in parts]) for f in fields(Rows)))

    def within(self, cell: int, side: int, across: int) -> Rows:
        """Of rectangles, those with a point in a cell that is ``across`` wide; beyond the border of the world is in its outermost cells."""
        axis = lambda v: np.clip(v // across, 0, side - 1)
        cy, cx = divmod(cell, side)
        return self._only(np.flatnonzero((axis(self.x0) <= cx) & (axis(self.x1) >= cx) & (axis(self.y0) <= cy) & (axis(self.y1) >= cy)))

    def posted(self, nth: int) -> Rows:
        """Subscriptions with a posting in a cell of the tile, with these postings."""
        here = self.listed >> nth & 1
        sub = np.repeat(np.arange(len(self.id)), self.n_clauses)
        kept = np.zeros(len(self.id), dtype=bool)
        kept[sub[here > 0]] = True
        rows = self._only(np.flatnonzero(kept))
        rows.listed = rows.listed & ~np.int64((1 << TILE * TILE) - 1) | rows.listed >> nth & 1
        return rows

    def _only(self, kept: np.ndarray) -> Rows:
        clauses = _each(_starts(self.n_clauses)[kept], self.n_clauses[kept])
        words = _each(_starts(self.n_words)[clauses], self.n_words[clauses])
        rows = (column[kept] for column in (self.id, self.x0, self.x1, self.y0, self.y1, self.since, self.until, self.n_clauses))
        listed, under = (self.listed[clauses], self.under[clauses]) if len(self.listed) else (self.listed, self.under)
        return Rows(*rows, self.n_words[clauses], self.places[words], self.codes[words], self.workers, listed, under)


def _starts(lengths: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.cumsum(lengths)])[:-1]


def _lengths(lists: pa.Array) -> np.ndarray:
    return pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)


class Lists:
    """The subscriptions of a cell, or of a piece of it: entries by routing term and left border. Postings are listed as they
    are; without them each clause is listed under its rarest word."""

    def __init__(self, rows: Rows):
        self.sub_id, self.since, self.until = rows.id, rows.since, rows.until
        n_words, first = rows.n_words, _starts(rows.n_clauses)
        self.words, ids = np.unique(rows.codes, return_inverse=True)
        # words of clauses side by side; a place without one has a word that every object has
        self.clauses = np.full((len(n_words), int(n_words.max(initial=1))), len(self.words), dtype=np.int64)
        at = np.repeat(np.arange(len(n_words)), n_words)
        self.clauses[at, np.arange(len(at)) - np.repeat(_starts(n_words), n_words)] = ids
        posted = len(rows.listed) > 0
        listed = np.flatnonzero((rows.listed & 1 > 0) & (n_words > 0)) if posted else np.flatnonzero(n_words)
        sub = np.repeat(np.arange(len(self.sub_id)), rows.n_clauses)[listed]
        clause = (np.arange(len(n_words)) - np.repeat(first, rows.n_clauses))[listed]
        if posted:
            term = ids[_starts(n_words)[listed] + rows.under[listed]]
        else:
            term = ids[np.lexsort((rows.places, at))[np.cumsum(n_words)[listed] - 1]]
        self.least, self.widest = int(rows.x0.min()), int((rows.x1 - rows.x0).max())
        self.span = int(rows.x0.max()) - self.least + 1
        if self.span * (len(self.words) + 1) >= 1 << 62:
            raise OverflowError("borders too far apart for a cell")
        key = term * self.span + (rows.x0[sub] - self.least)
        order = np.argsort(key, kind="stable")
        self.key, self.sub, self.clause = key[order], sub[order], clause[order]
        self.first = first[self.sub]
        self.x1, self.y0, self.y1 = rows.x1[self.sub], rows.y0[self.sub], rows.y1[self.sub]
        self.sure = (self.clause == 0) & (n_words[self.first] == 1)
        # a term has one worker in a cell
        self.worker = np.zeros(len(self.words), dtype=np.int64)
        if posted:
            self.worker[term] = rows.listed[listed] >> TILE * TILE
        self.always = bool((self.since == np.iinfo(np.int64).min).all() and (self.until == np.iinfo(np.int64).max).all())

    def through(self, rows: Rows) -> Iterator[pa.RecordBatch]:
        """Pairs of these objects, whose terms are one clause."""
        if not len(self.words):
            return
        step = max(1, TABLE // (len(self.words) + 1))
        ends = np.concatenate([[0], np.cumsum(rows.n_words)])
        for a in range(0, len(rows.id), step):
            b = min(a + step, len(rows.id))
            yield from self._through(rows.id[a:b], rows.x0[a:b], rows.y0[a:b], rows.since[a:b], rows.n_words[a:b], rows.codes[ends[a] : ends[b]], rows.workers[a:b])

    def _through(self, obj_id, x, y, seq, n_words, codes, workers) -> Iterator[pa.RecordBatch]:
        obj = np.repeat(np.arange(len(obj_id)), n_words)
        term = np.minimum(np.searchsorted(self.words, codes), len(self.words) - 1)
        known = self.words[term] == codes
        obj, term = obj[known], term[known]
        has = np.zeros((len(obj_id), len(self.words) + 1), dtype=bool)
        has[obj, term], has[:, -1] = True, True
        if len(workers):
            sent = workers[obj] >> self.worker[term] & 1 > 0
            obj, term = obj[sent], term[sent]
        at, base = x[obj] - self.least, term * self.span
        low = np.searchsorted(self.key, base + np.clip(at - self.widest, 0, self.span))
        n = np.searchsorted(self.key, base + np.clip(at + 1, 0, self.span)) - low
        obj, low, n = obj[n > 0], low[n > 0], n[n > 0]
        ends = np.cumsum(n)
        a = 0
        while a < len(n):
            done = ends[a - 1] if a else 0
            b = max(a + 1, int(np.searchsorted(ends, done + TOGETHER, side="right")))
            yield from self._settled(obj[a:b], low[a:b], n[a:b], obj_id, x, y, seq, has)
            a = b

    def _settled(self, obj, low, n, obj_id, x, y, seq, has) -> Iterator[pa.RecordBatch]:
        """Of the ``n`` entries from ``low`` on for each object, those that it satisfies."""
        entry = np.arange(int(n.sum())) + np.repeat(low - _starts(n), n)
        inside = self.x1[entry] >= np.repeat(x[obj], n)
        here = np.repeat(y[obj], n)
        inside &= self.y0[entry] <= here
        inside &= self.y1[entry] >= here
        kept = np.flatnonzero(inside)
        entry, obj = entry[kept], np.repeat(obj, n)[kept]
        if not self.always:
            sub = self.sub[entry]
            living = (self.since[sub] < seq[obj]) & (seq[obj] < self.until[sub])
            entry, obj = entry[living], obj[living]
        open_ = np.flatnonzero(~self.sure[entry])
        e, o = entry[open_], obj[open_]
        good, last = np.ones(len(e), dtype=bool), self.clause[e]
        for c in range(int(last.max(initial=-1)) + 1):
            part = np.flatnonzero(good & (last >= c))
            words, who = self.clauses[self.first[e[part]] + c], o[part]
            holds = has[who, words[:, 0]]
            for w in range(1, words.shape[1]):
                holds &= has[who, words[:, w]]
            good[part] = holds == (last[part] == c)
        out = np.ones(len(entry), dtype=bool)
        out[open_] = good
        entry, obj = entry[out], obj[out]
        if len(entry):
            yield pa.RecordBatch.from_arrays([pa.array(self.sub_id[self.sub[entry]]), pa.array(obj_id[obj])], schema=FOUND)


def by_cell(batches: Iterator[pa.RecordBatch], words: np.ndarray, side: int, across: int) -> Iterator[pa.RecordBatch]:
    """Blocks in the order of cell, salt and kind, subscriptions (0) before objects, to pairs. Of a tile, its subscriptions
    are held, and lists of one cell after another are made of them; cells are ``across`` wide, ``side`` to a row."""
    place, parts, held, last, lists = None, [], None, 0, None
    for batch in batches:
        for cell, salt, kind, block in zip(*(batch.column(name) for name in ("cell", "salt", "kind", "block"))):
            if (cell.as_py(), salt.as_py()) != place:
                place, parts, held, last, lists = (cell.as_py(), salt.as_py()), [], None, 0, None
            if kind.as_py() == 0:
                parts.append(Rows.of(block.as_py(), words))
                continue
            if parts:
                held, parts = Rows.together(parts), []
            if held is not None and kind.as_py() != last:
                last = kind.as_py()
                at = place[0] + (last - 1) // TILE * side + (last - 1) % TILE
                near = held.posted(last - 1) if len(held.listed) else held.within(at, side, across)
                lists = Lists(near) if len(near.id) else None
            if lists is not None:
                yield from lists.through(Rows.of(block.as_py(), words))
