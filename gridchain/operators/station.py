"""What happens at a station: rows of all operands come by one exchange each, and local kernels run on what has met.

Every operand is dealt to its stations as rows (station, tag, i, j, v, x, cells): dense rows first
(tag 0 for the row side, 1 for the column side; j is the first column of the slab), nonzeros
(tag 2) after them. Nonzeros travel in chunks of one home station, packed into one row
(i is the chunk, j its home, v the visit). Operands are dealt alike, so their partitions are put side by side and
sorted, and no nonzero ever travels with a dense row. A kernel holds a station's dense
blocks and streams its nonzeros; partial results leave as dense rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import cache, reduce

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LEFT, RIGHT, CELLS = 0, 1, 2
DEALT = ["station", "tag", "i", "j", "v", "x"]
PACKED = "chunk bigint, home int, cells binary"
DOTS = "chunk bigint, home int, cells binary, part binary"
ENTRIES = "i bigint, j bigint, v double"
PARTIAL = "id bigint, start bigint, x array<double>"
#: Nonzeros handled in one NumPy step; partial rows gathered before they are summed up.
STEP, HELD = 1 << 14, 1 << 16
#: Ids of a slab are looked up in a table while it is at most so many times as long as they are.
SPARSE = 8
#: Nonzeros of a chunk at most, and those that a task gathers before it cuts them into chunks.
CHUNK, GATHERED = 1 << 13, 1 << 18
#: Rows of an Arrow batch at most, as a row may be a whole chunk.
BATCH, BATCH_ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", 1000


def _mixed(key: int, seed: int = 42) -> int:
    """Spark's hash of an INT (32-bit Murmur3), as an unsigned number."""
    word = 0xFFFFFFFF
    k = key * 0xCC9E2D51 & word
    k = (k << 15 | k >> 17) * 0x1B873593 & word
    h = seed ^ k
    h = ((h << 13 | h >> 19) & word) * 5 + 0xE6546B64 & word
    h ^= 4
    h = (h ^ h >> 16) * 0x85EBCA6B & word
    h = (h ^ h >> 13) * 0xC2B2AE35 & word
    return h ^ h >> 16


@cache
def station_keys(p: int) -> tuple[int, ...]:
    """A key for each of p stations, so that p hash partitions get one station each."""
    keys: dict[int, int] = {}
    key = 0
    while len(keys) < p:
        h = _mixed(key)
        keys.setdefault((h - (1 << 32) * (h >> 31)) % p, key)
        key += 1
    return tuple(keys[t] for t in range(p))


def deal(rows: DataFrame, p: int) -> DataFrame:
    """rows exchanged by station, one station in each of p partitions."""
    key = F.element_at(F.lit(list(station_keys(p))), F.col("station") + 1).cast("int")
    return rows.select(key.alias("station"), *rows.columns[1:]).repartition(p, "station")


def dense_rows(placed: DataFrame, tag: int, key: str, vector: str) -> DataFrame:
    return placed.select("station", F.lit(tag).alias("tag"), F.col(key).alias("i"), F.col("start").alias("j"), F.lit(0.0).alias("v"), F.col(vector).alias("x"), F.lit(None).cast("binary").alias("cells"))


def _narrow(x: np.ndarray) -> bytes:
    """Width and values of unsigned numbers in the fewest bytes."""
    most = int(x.max())
    width = next(w for w in (1, 2, 4, 8) if w == 8 or most < 1 << 8 * w)
    return bytes([width]) + x.astype(f"<u{width}").tobytes()


def pack(i: np.ndarray, j: np.ndarray, v: np.ndarray) -> bytes:
    """Nonzeros in the order of i: steps of i, j over its least, and the values."""
    base = int(j.min())
    head = np.array([len(i), i[0], base], "<i8").tobytes()
    steps = np.diff(i, prepend=i[:1]).astype(np.uint64)
    return head + _narrow(steps) + _narrow((j - base).astype(np.uint64)) + v.astype("<f8").tobytes()


def unpack(cells: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    n, first, base = np.frombuffer(cells, "<i8", 3).tolist()
    at, parts = 24, []
    for _ in range(2):
        width = cells[at]
        parts.append(np.frombuffer(cells, f"<u{width}", n, at + 1).astype(np.int64))
        at += 1 + width * n
    return np.cumsum(parts[0]) + first, parts[1] + base, np.frombuffer(cells, "<f8", n, at)


def packed(homed: DataFrame) -> DataFrame:
    """(chunk, home, cells) of nonzeros (home, i, j, v): chunks of one home, cut within each task before anything moves.

    Partial dots of a chunk meet by its number, so a task that runs again must see the same rows: s is stored, or dealt from what is.
    """

    def chunks(held: list[pa.RecordBatch], number: int) -> Iterator[tuple[int, int, bytes]]:
        table = pa.Table.from_batches(held)
        home, i, j, v = (np.asarray(table.column(c)) for c in ("home", "i", "j", "v"))
        order = np.lexsort((j, i, home))
        home, i, j, v = home[order], i[order], j[order], v[order]
        for station in np.unique(home).tolist():
            a, b = np.searchsorted(home, [station, station + 1]).tolist()
            for start in range(a, b, CHUNK):
                part = slice(start, min(start + CHUNK, b))
                yield number, station, pack(i[part], j[part], v[part])
                number += 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        number = TaskContext.get().partitionId() << 36
        held, rows = [], 0

        def out() -> Iterator[pa.RecordBatch]:
            nonlocal number
            for at, station, cells in chunks(held, number):
                number = at + 1
                yield pa.RecordBatch.from_arrays([pa.array([at], pa.int64()), pa.array([station], pa.int32()), pa.array([cells], pa.binary())], ["chunk", "home", "cells"])

        for batch in batches:
            if batch.num_rows:
                held.append(batch)
                rows += batch.num_rows
            if rows >= GATHERED:
                yield from out()
                held, rows = [], 0
        if rows:
            yield from out()

    return homed.select("home", "i", "j", "v").mapInArrow(run, PACKED)


def unpacked(cells: DataFrame) -> DataFrame:
    """(i, j, v) of packed nonzeros."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.column("cells"):
                parts = unpack(x.as_py())
                for a in range(0, len(parts[0]), STEP):
                    yield pa.RecordBatch.from_arrays([pa.array(c[a : a + STEP]) for c in parts], ["i", "j", "v"])

    return cells.select("cells").mapInArrow(run, ENTRIES)


def chunk_rows(visits: DataFrame) -> DataFrame:
    """Rows to deal of packed nonzeros with their stations and visits."""
    return visits.select("station", F.lit(CELLS).alias("tag"), F.col("chunk").alias("i"), F.col("home").cast("bigint").alias("j"), F.col("visit").cast("double").alias("v"), F.lit(None).cast("array<double>").alias("x"), "cells")


def cell_rows(placed: DataFrame) -> DataFrame:
    """The same of single nonzeros (station, i, j, v), packed by station."""
    return chunk_rows(packed(placed.withColumn("home", F.col("station"))).select("*", F.col("home").alias("station"), F.lit(0).alias("visit")))


def at_stations(dealt: list[DataFrame], kernel: Callable, schema: str) -> DataFrame:
    """kernel over each station's rows, dense rows first.

    The operands' exchanges are separate, so one that serves two kernels of a plan, or that
    is persisted, is made once.
    """
    conf = dealt[0].sparkSession.conf
    if not 0 < int(conf.get(BATCH)) <= BATCH_ROWS:
        conf.set(BATCH, str(BATCH_ROWS))
    met = reduce(DataFrame.unionAll, dealt)
    return met.sortWithinPartitions("station", "tag").groupBy("station").applyInArrow(kernel, schema)


class Slabs:
    """Dense rows of one side by their slab's first column: sorted ids and a matrix."""

    def __init__(self):
        self.parts: dict[int, list[tuple[np.ndarray, np.ndarray]]] = {}
        self.blocks: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        self.places: dict[int, np.ndarray] = {}

    def add(self, ids: np.ndarray, starts: np.ndarray, rows: pa.Array) -> None:
        offsets = np.asarray(rows.offsets)
        flat, sizes = np.asarray(rows.flatten(), float), np.diff(offsets)
        first = np.cumsum(sizes) - sizes
        for start in np.unique(starts).tolist():
            at = np.flatnonzero(starts == start)
            width = int(sizes[at[0]])
            self.parts.setdefault(start, []).append((ids[at], flat[first[at][:, None] + np.arange(width)]))

    def close(self) -> None:
        for start, parts in self.parts.items():
            ids, x = np.concatenate([i for i, _ in parts]), np.concatenate([x for _, x in parts])
            order = np.argsort(ids, kind="stable")
            self.blocks[start] = ids, _ = ids[order], x[order]
            if len(ids) and int(ids[-1]) - int(ids[0]) < SPARSE * len(ids):
                places = np.full(int(ids[-1]) - int(ids[0]) + 1, -1, np.int32)
                places[ids[::-1] - ids[0]] = np.arange(len(ids) - 1, -1, -1)
                self.places[start] = places
        self.parts = {}

    def find(self, start: int, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place of each id in the slab's block, whether it is there)."""
        held = self.blocks[start][0]
        if (places := self.places.get(start)) is not None:
            off = ids - held[0]
            inside = (off >= 0) & (off < len(places))
            at = places[off] if inside.all() else np.where(inside, places[np.where(inside, off, 0)], -1)
            return np.maximum(at, 0), at >= 0
        at = np.minimum(np.searchsorted(held, ids), len(held) - 1)
        return at, held[at] == ids


def station_chunks(batches: Iterator[pa.RecordBatch]) -> tuple[Slabs, Slabs, Iterator[tuple[int, int, int, bytes]]]:
    """Both dense sides, read in full, and the chunks (number, home, visit, cells)."""
    sides = Slabs(), Slabs()
    rest: list[pa.RecordBatch] = []
    stream = iter(batches)
    for batch in stream:
        tags = np.asarray(batch.column("tag"))
        cuts = np.searchsorted(tags, [LEFT, RIGHT, CELLS, CELLS + 1])
        for tag in (LEFT, RIGHT):
            if cuts[tag + 1] > cuts[tag]:
                part = batch.slice(int(cuts[tag]), int(cuts[tag + 1] - cuts[tag]))
                sides[tag].add(np.asarray(part.column("i")), np.asarray(part.column("j")), part.column("x"))
        if cuts[3] > cuts[2]:
            rest.append(batch.slice(int(cuts[2])))
            break
    for side in sides:
        side.close()

    def chunks() -> Iterator[tuple[int, int, int, bytes]]:
        for source in (rest, stream):
            for batch in source:
                for number, home, visit, cells in zip(*(batch.column(c) for c in ("i", "j", "v", "cells"))):
                    yield number.as_py(), home.as_py(), int(visit.as_py()), cells.as_py()

    return *sides, chunks()


def station_parts(batches: Iterator[pa.RecordBatch]) -> tuple[Slabs, Slabs, Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
    """Both dense sides, read in full, and the nonzeros (i, j, v) in steps."""
    *sides, chunks = station_chunks(batches)

    def cells() -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        for _, _, _, chunk in chunks:
            i, j, v = unpack(chunk)
            for a in range(0, len(i), STEP):
                yield i[a : a + STEP], j[a : a + STEP], v[a : a + STEP]

    return *sides, cells()


def _dots(left: Slabs, right: Slabs, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Dots over the slabs that both sides hold here, and where both rows are present."""
    total, there = np.zeros(len(i)), np.zeros(len(i), bool)
    for start in left.blocks.keys() & right.blocks.keys():
        (p, x), (q, y) = left.find(start, i), right.find(start, j)
        both = np.flatnonzero(x & y)
        total[both] += np.einsum("nr,nr->n", left.blocks[start][1][p[both]], right.blocks[start][1][q[both]])
        there[both] = True
    return total, there


def _ends(u: np.ndarray, v: np.ndarray) -> Callable:
    """Like _dots, for the pair u . a_i + v . b_j: each end's share of this station's slabs is taken once."""

    def run(left: Slabs, right: Slabs, i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        total, there = np.zeros(len(i)), np.zeros(len(i), bool)
        for start in left.blocks.keys() & right.blocks.keys():
            (p, x), (q, y) = left.find(start, i), right.find(start, j)
            both = np.flatnonzero(x & y)
            sides = [(block[1] @ part[start : start + block[1].shape[1]])[at[both]] for block, part, at in ((left.blocks[start], u, p), (right.blocks[start], v, q))]
            total[both] += sides[0] + sides[1]
            there[both] = True
        return total, there

    return run


def masked_kernel(pair: tuple[list[float], list[float]] | None = None) -> Callable:
    """Each chunk with the dots (or u . a_i + v . b_j for a pair u, v) over this station's slabs; its nonzeros go on from the first visit only."""
    value = _dots if pair is None else _ends(*(np.array(x, float) for x in pair))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        left, right, chunks = station_chunks(batches)
        for number, home, visit, cells in chunks:
            i, j, _ = unpack(cells)
            steps = [value(left, right, i[a : a + STEP], j[a : a + STEP]) for a in range(0, len(i), STEP)]
            part, there = (np.concatenate(x) for x in zip(*steps))
            found = part.tobytes() + (b"" if there.all() else there.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), pa.array([home], pa.int32()), pa.array([None if visit else cells], pa.binary()), pa.array([found], pa.binary())], ["chunk", "home", "cells", "part"])

    return run


def finished(dots: DataFrame, scaled: bool, partial: bool) -> DataFrame:
    """Packed masked product of chunks with dots; partial ones of several stations meet by chunk in one exchange. Nonzeros without both dense rows go."""

    def value(cells: bytes, parts: list[bytes]) -> bytes | None:
        i, j, v = unpack(cells)
        n = len(i)
        total, there = np.zeros(n), np.zeros(n, bool)
        for part in parts:
            total += np.frombuffer(part, "<f8", n)
            there |= np.frombuffer(part, bool, n, 8 * n) if len(part) > 8 * n else True
        total = v * total if scaled else total
        return pack(i[there], j[there], total[there]) if there.any() else None

    def batch(number: int, home: int, cells: bytes | None) -> Iterator[pa.RecordBatch]:
        if cells is not None:
            yield pa.RecordBatch.from_arrays([pa.array([number], pa.int64()), pa.array([home], pa.int32()), pa.array([cells], pa.binary())], ["chunk", "home", "cells"])

    def single(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            for number, home, cells, part in zip(*(x.column(c).to_pylist() for c in ("chunk", "home", "cells", "part"))):
                yield from batch(number, home, value(cells, [part]))

    def met(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [row for x in batches for row in zip(*(x.column(c).to_pylist() for c in ("chunk", "home", "cells", "part")))]
        first = next(x for x in rows if x[2] is not None)
        yield from batch(first[0], first[1], value(first[2], [x[3] for x in rows]))

    return dots.groupBy("chunk").applyInArrow(met, PACKED) if partial else dots.mapInArrow(single, PACKED)


class Sums:
    """Weighted dense rows summed by id, for one slab."""

    def __init__(self):
        self.held: list[tuple[np.ndarray, np.ndarray]] = []
        self.rows = 0

    def add(self, ids: np.ndarray, rows: np.ndarray) -> None:
        if len(ids):
            if (ids[1:] < ids[:-1]).any():
                order = np.argsort(ids, kind="stable")
                ids, rows = ids[order], rows[order]
            first = np.flatnonzero(np.concatenate([[True], ids[1:] != ids[:-1]]))
            self.held.append((ids[first], np.add.reduceat(rows, first, axis=0)))
            self.rows += len(first)
            # as many new rows as there are sums, so that the sums are not gone through again for each few
            if self.rows > max(HELD, len(self.held[0][0])) and len(self.held) > 1:
                done = self.total()
                self.held, self.rows = [done], 0

    def total(self) -> tuple[np.ndarray, np.ndarray]:
        if len(self.held) == 1:
            return self.held[0]
        both = Sums()
        both.add(np.concatenate([i for i, _ in self.held]), np.concatenate([x for _, x in self.held]))
        return both.held[0]

    def batches(self, start: int) -> Iterator[pa.RecordBatch]:
        if not self.held:
            return
        ids, x = self.total()
        for a in range(0, len(ids), 4096):
            part = x[a : a + 4096]
            offsets = np.arange(len(part) + 1, dtype=np.int32) * part.shape[1]
            rows = pa.ListArray.from_arrays(pa.array(offsets), pa.array(part.ravel()))
            yield pa.RecordBatch.from_arrays([pa.array(ids[a : a + 4096]), pa.array(np.full(len(part), start, np.int64)), rows], ["id", "start", "x"])


def gather_kernel(side: int) -> Callable:
    """Sums of v times the dense rows of `side`, by the nonzeros' other end, in each slab."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        *sides, cells = station_parts(batches)
        dense, sums = sides[side], {start: Sums() for start in sides[side].blocks}
        for i, j, v in cells:
            key, out = (i, j) if side == LEFT else (j, i)
            for start, total in sums.items():
                at, there = dense.find(start, key)
                total.add(out[there], dense.blocks[start][1][at[there]] * v[there][:, None])
        for start, total in sums.items():
            yield from total.batches(start)

    return run


def chain_kernel(side: int) -> Callable:
    """Both kernels for whole rows: dots weight the dense rows of `side` at once, and the masked product is never stored."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        *sides, cells = station_parts(batches)
        dense, total = sides[side], Sums()
        for i, j, v in cells:
            part, there = _dots(*sides, i, j)
            key, out = (i[there], j[there]) if side == LEFT else (j[there], i[there])
            if len(key):
                at, _ = dense.find(0, key)
                total.add(out, dense.blocks[0][1][at] * (v * part)[there][:, None])
        yield from total.batches(0)

    return run


def reduced(partial: DataFrame, complete: bool) -> DataFrame:
    """Long form (id, k, x) of partial dense rows; unless each is complete, those of an id and slab meet in one exchange, one from each station at most."""
    if not complete:
        zero = F.transform(F.element_at("rows", 1), lambda _: F.lit(0.0))
        total = F.aggregate("rows", zero, lambda have, row: F.zip_with(have, row, lambda p, q: p + q))
        partial = partial.groupBy("id", "start").agg(F.collect_list("x").alias("rows")).select("id", "start", total.alias("x"))
    return partial.select("id", "start", F.posexplode("x").alias("pos", "x")).select("id", (F.col("start") + F.col("pos")).cast("bigint").alias("k"), "x")
