"""Attention over a near graph on a station grid: each station makes its edges from the rows that meet there.

In every family the nonzeros that visit a station are those between the row-side and the
column-side rows that it holds. So the vectors that decide about an edge travel with the
rows that they join, and no edge is dealt. Many rows come in turns, some starts and some
ends of edges at a time, and what a turn dealt is deleted before the next. What would meet by nonzero meets by row: the pair
u . a_i + v . b_j splits into its two ends, and a station sums its edges under its own
greatest score of each row, so that partial rows meet by id.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridchain.functions.vectors import mat_row
from gridchain.operators.blocks import HELD, NearGraph, _leaky, _lists, _matrix, _met
from gridchain.operators.station import at_stations, deal
from gridchain.plans.grid import Grid, place_left, place_right
from gridchain.sources.scratch import delete, stored

#: Kinds of rows at a station: vectors of the edges' starts, scores of both ends, dense rows and vectors of the edges' ends.
START, FROM, TO, DENSE, END = 0, 1, 2, 3, 4
#: Starts and ends of edges whose rows are at the stations in one turn, about.
TURN = 40_000
#: Rows and columns of a tile that is worked on at once.
ROWS, COLUMNS = 256, 2048
PARTIAL = "id bigint, start bigint, top array<double>, y array<double>"


def _dealt(d: DataFrame, grid: Grid, side: str, tag: int, slabs: bool, near: bool, ends: bool, home: bool = False) -> DataFrame:
    """Rows (station, tag, i, j, own, x, near32, near, ends) of d; what isn't asked for is null, and what no slab tells apart comes to a station once.

    With home only the rows at their own station go, where the kernel reads no others.
    """
    placed = (place_left if side == "left" else place_right)(d if slabs else d.withColumn("x", F.array().cast("array<array<double>>")), grid)
    first = F.col("slab") < grid.c if grid.family == "rs" else F.lit(True)
    key, x = ("i", "ax") if side == "left" else ("j", "bx")
    if not slabs:
        placed = placed.filter(first)
    if home:
        placed = placed.filter("station = home")
    part = lambda there, what, kind: (what if there else F.lit(None)).cast(kind)
    return deal(
        placed.select(
            "station", F.lit(tag).alias("tag"), F.col(key).alias("i"), F.col("start").alias("j"), (F.col("station") == F.col("home")).alias("own"),
            part(slabs, F.flatten(x) if slabs else None, "array<double>").alias("x"), part(near, F.when(first, F.col("near32")) if near else None, "array<float>").alias("near32"),
            part(near, F.when(first, F.col("near")) if near else None, "array<double>").alias("near"),
            part(ends, F.col("ends") if ends else None, "array<double>").alias("ends"),
        ),
        grid.p,
    )


def _blocks(batch: pa.RecordBatch, heads: int) -> np.ndarray:
    """Dense rows of one slab as (row, column, head)."""
    return _matrix(batch.column("x"), batch.num_rows).reshape(batch.num_rows, -1, heads)


def _vectors(batch: pa.RecordBatch) -> np.ndarray:
    """The rows' vectors, of which some travelled in single precision."""
    short, n = np.asarray(batch.column("near32").is_valid()), batch.num_rows
    kinds = [(at, name) for at, name in ((short, "near32"), (~short, "near")) if at.any()]
    parts = [_matrix(batch.column(name).filter(pa.array(at)), int(at.sum())) for at, name in kinds]
    if len(parts) < 2:
        return parts[0] if parts else np.zeros((0, 0))
    out = np.empty((n, parts[0].shape[1]))
    for (at, _), part in zip(kinds, parts):
        out[at] = part
    return out


def _by_start(batch: pa.RecordBatch) -> Iterator[tuple[int, pa.RecordBatch]]:
    starts = np.asarray(batch.column("j"))
    for start in np.unique(starts).tolist():
        yield start, batch.filter(pa.array(starts == start))


def ends_kernel(ends: dict[int, np.ndarray]) -> Callable:
    """What a row's slab adds to its scores as a start or an end of edges, from its home; ends: (column, head) by tag."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = batch.filter(batch.column("own"))
            for tag, vectors in ends.items():
                for start, part in _by_start(own.filter(pa.array(np.asarray(own.column("tag")) == tag))):
                    x = _blocks(part, vectors.shape[1])
                    found = np.einsum("nkh,kh->nh", x, vectors[start : start + x.shape[1]])
                    yield pa.RecordBatch.from_arrays([part.column("i"), pa.array(np.full(len(x), tag, np.int32)), _lists(found)], ["id", "tag", "part"])

    return run


class _Rows:
    """What rows of one kind bring along, in the order of their ids."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        if len(ids):
            self.parts.append((ids, x))

    def close(self) -> tuple[np.ndarray, np.ndarray]:
        ids, x = (np.concatenate(k) for k in zip(*self.parts))
        self.parts = []
        order = np.argsort(ids, kind="stable")
        return ids[order], x[order]


def attention_kernel(least: float, heads: int, softmax: bool, slope: float) -> Callable:
    """Partial rows of all heads in each slab, under this station's greatest scores; `ends` holds the scores of a row as a start, then as an end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = {kind: _Rows() for kind in ("start", "from", "to", "end")}
        slabs: dict[int, _Rows] = {}
        for batch in batches:
            tags = np.asarray(batch.column("tag"))
            for tag in np.unique(tags).tolist():
                part = batch.filter(pa.array(tags == tag))
                ids = np.asarray(part.column("i"))
                if tag in (FROM, TO):
                    at = 0 if tag == FROM else heads
                    kept["from" if tag == FROM else "to"].add(ids, _matrix(part.column("ends"), len(ids))[:, at : at + heads])
                    continue
                if tag == DENSE:
                    for start, rows in _by_start(part):
                        slabs.setdefault(start, _Rows()).add(np.asarray(rows.column("i")), _blocks(rows, heads))
                    continue
                kept["start" if tag == START else "end"].add(ids, _vectors(part))
        if not all(x.parts for x in (*kept.values(), *slabs.values())):
            return
        (ids, x), (_, froms), (_, tos), (others, y) = (kept[kind].close() for kind in ("start", "from", "to", "end"))
        dense = {start: rows.close()[1] for start, rows in sorted(slabs.items())}
        values = [np.concatenate([*[rows[:, :, k] for rows in dense.values()], np.ones((len(others), 1))], axis=1) for k in range(heads)]
        for a in range(0, len(ids), ROWS):
            part = slice(a, a + ROWS)
            some, tops, sums = _tiles(ids[part], x[part], froms[part], others, y, tos, values, least, softmax, slope)
            if some.any():
                at = 0
                for start, rows in dense.items():
                    width = rows.shape[1]
                    found = np.concatenate([np.concatenate([s[:, at : at + width], s[:, -1:]], axis=1) for s in sums], axis=1)
                    at += width
                    yield pa.RecordBatch.from_arrays([pa.array(ids[part][some]), pa.array(np.full(some.sum(), start)), _lists(tops[some]), _lists(found[some])], ["id", "start", "top", "y"])

    return run


def _tiles(ids: np.ndarray, x: np.ndarray, froms: np.ndarray, others: np.ndarray, y: np.ndarray, tos: np.ndarray, values: list[np.ndarray], least: float, softmax: bool, slope: float) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """(rows with an edge, their greatest scores by head, weighted sums of each head) over all ends of edges, a tile of them at a time."""
    n, heads = len(ids), len(values)
    some, tops = np.zeros(n, bool), np.full((n, heads), -np.inf if softmax else 0.0)
    sums = [np.zeros((n, v.shape[1])) for v in values]
    for b in range(0, len(others), COLUMNS):
        dots = x @ y[b : b + COLUMNS].T
        flat = np.flatnonzero(dots > least)
        p, q = np.divmod(flat, dots.shape[1])
        other = ids[p] != others[b + q]
        if not other.all():
            flat, p, q = flat[other], p[other], q[other]
        if not len(flat):
            continue
        first = np.flatnonzero(np.concatenate([[True], p[1:] != p[:-1]]))
        rows = p[first]
        some[rows] = True
        weights = np.zeros(dots.shape)
        for k in range(heads):
            e = _leaky(froms[p, k] + tos[b + q, k], slope)
            if softmax:
                top = tops[:, k].copy()
                top[rows] = np.maximum(top[rows], np.maximum.reduceat(e, first))
                sums[k][rows] *= np.exp(tops[rows, k] - top[rows])[:, None]
                e = np.exp(e - top[p])
                tops[:, k] = top
            weights.reshape(-1)[flat] = e
            sums[k] += weights @ values[k][b : b + COLUMNS]
    return some, tops, sums


def _merged(partial: DataFrame, grid: Grid, heads: int, out: str, softmax: bool, buckets: int, turns: int) -> DataFrame:
    """(id, start, x) of partial rows, heads side by side; those of several stations or turns meet by id in one exchange."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, waiting, start = [], 0, 0
        for batch in batches:
            n = batch.num_rows
            if n:
                start = batch.column("start")[0].as_py()
                held.append((np.asarray(batch.column("id")), *(_matrix(batch.column(c), n) for c in ("top", "y"))))
                waiting += n
            if waiting > HELD and len(held) > 1:
                held = [_met(held, _spans(held[0][2]))]
                waiting = 0
        if held:
            ids, _, sums = _met(held, _spans(held[0][2]))
            yield from done(ids, start, sums)

    def _spans(sums: np.ndarray) -> list[tuple[int, int]]:
        width = sums.shape[1] // heads
        return [(k * width, (k + 1) * width) for k in range(heads)]

    def done(ids: np.ndarray, start: int, sums: np.ndarray) -> Iterator[pa.RecordBatch]:
        x = np.concatenate([sums[:, a : b - 1] / sums[:, b - 1 : b] if softmax else sums[:, a : b - 1] for a, b in _spans(sums)], axis=1)
        for a in range(0, len(ids), 4096):
            part = ids[a : a + 4096]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(np.full(len(part), start, np.int64)), _lists(x[a : a + 4096])], ["id", "start", "x"])

    def single(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, part in _by_start(batch.rename_columns(["id", "j", "top", "y"])):
                yield from done(np.asarray(part.column("id")), start, _matrix(part.column("y"), part.num_rows))

    schema = "id bigint, start bigint, x array<double>"
    if grid.holders(out) == 1 and turns == 1:
        return partial.mapInArrow(single, schema)
    bucket = F.pmod(F.xxhash64("id"), F.lit(buckets)).cast("int")
    return partial.select(bucket.alias("bucket"), "id", "start", "top", "y").groupBy("bucket", "start").applyInArrow(merge, schema)


def near_heads(graph: NearGraph, a: DataFrame, heads: list[tuple[list[list[float]], list[float]]], grid: Grid, elision: str, softmax: bool, slope: float) -> DataFrame:
    """(id, x): heads over projected rows side by side, grid.r columns each, in one pass over the edges of each station.

    none    scores of the ends, stored; then the gather, which gets its dense operand again.
    reuse   the copied operand is dealt to its fiber once and serves both kernels.

    The vectors, which stand for the edges, are dealt in turns: TURN starts by TURN ends of edges, about.
    """
    at, r = range(len(heads)), grid.r
    if any(len(w[0]) != r for w, _ in heads):
        raise ValueError(f"on a grid of {r} columns every head needs {r}")
    columns = F.transform(F.sequence(F.lit(0), F.lit(r - 1)), lambda k: F.array(*[F.get(F.col(f"x{h}"), k) for h in at]))
    nodes = graph.d.filter("x is not null").select("id", F.col("x").alias("near"))
    rows = nodes.join(a.select("id", *[mat_row("x", w).alias(f"x{h}") for h, (w, _) in enumerate(heads)]), "id")
    # vectors that single precision holds exactly travel in it
    short = F.col("near").cast("array<float>")
    rows = rows.withColumn("near32", F.when(short.cast("array<double>").eqNullSafe(F.col("near")), short))
    rows = stored(rows.select("id", "near32", F.when(F.col("near32").isNull(), F.col("near")).alias("near"), columns.alias("x")), "near")
    u, v = (np.array([vector[half] for _, vector in heads]).T for half in (slice(r), slice(r, None)))
    # with reuse roles change: the rows of the transposed grid's left side are the ends that are gathered
    reuse = elision == "reuse"
    on = grid.turned if reuse else grid
    starts, gathered = ("right", "left") if reuse else ("left", "right")
    moving = _dealt(rows, on, starts, START, True, False, False, home=True)
    copied = _dealt(rows, on, gathered, DENSE, True, False, False, home=not reuse)
    turns = max(-(-rows.count() // TURN), 1)
    if reuse and turns > 1:
        copied = copied.persist(StorageLevel.DISK_ONLY)
    parts = at_stations([moving, copied], ends_kernel({START: u, DENSE: v}), "id bigint, tag int, part array<double>")
    share = lambda tag, h: F.sum(F.when(F.col("tag") == tag, F.get("part", F.lit(h))))
    ends: DataFrame = parts.groupBy("id").agg(F.array(*[share(tag, h) for tag in (START, DENSE) for h in at]).alias("ends"))
    if not reuse or turns > 1:
        ends = stored(ends, "scores")

    def some(d: DataFrame, turn: int, key: str = "id") -> DataFrame:
        return d if turns == 1 else d.filter(F.pmod(F.xxhash64(key), F.lit(turns)) == turn)

    def partial(first: int, second: int) -> DataFrame:
        dense = some(copied, second, "i") if reuse else _dealt(some(rows, second), on, gathered, DENSE, True, False, False)
        met = [_dealt(some(rows, first), on, starts, START, False, True, False), _dealt(some(ends, first), on, starts, FROM, False, False, True)]
        met += [_dealt(some(ends, second), on, gathered, TO, False, False, True), dense, _dealt(some(rows, second), on, gathered, END, False, True, False)]
        return at_stations(met, attention_kernel(graph.least, len(heads), softmax, slope), PARTIAL)

    merged = lambda d: _merged(d, on, len(heads), starts, softmax, grid.p, turns)
    if turns == 1:
        done = merged(partial(0, 0))
    else:
        found = []
        for first in range(turns):
            held = [stored(partial(first, second), "partial") for second in range(turns)]
            found.append(stored(merged(reduce(DataFrame.unionAll, held)), "heads"))
            for d in held:
                delete(d.sparkSession, d._gridchain_path)
        done = reduce(DataFrame.unionAll, found)
        if reuse:
            copied.unpersist()
    if grid.slabs == 1:
        return done.select("id", "x")
    # slabs of an id meet as rows, and each head takes its columns from all of them
    met = done.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("start", "x"))).alias("slabs"))
    share = lambda h: F.flatten(F.transform("slabs", lambda s: F.slice(s.x, (F.size(s.x) / len(heads)).cast("int") * h + 1, (F.size(s.x) / len(heads)).cast("int"))))
    return met.select("id", F.concat(*[share(h) for h in at]).alias("x"))
