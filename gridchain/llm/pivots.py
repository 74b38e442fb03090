"""Exact top-k inner products through a pivot-distance index.

Inner products become distances by one more component: with M the largest squared norm, v
gets sqrt(M - |v|^2) and a query gets 0, so the nearest vectors are those of largest product.
Vectors are keyed by their nearest pivot and sorted by the distance to it, in chunks of a
bounded size, each an annulus of a cell. Queries are rows too, in blocks. A block first
searches the one chunk nearest to it, which gives each query a k-th score; the triangle inequality
then leaves few chunks open, and within each the sorted annuli are opened ring by ring, outwards
from the query, until the bound rules out the rest.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from gridchain.llm.shared import binary_array, partitions, stage, tidy

#: Fewest and most pivots (between, one for each 16 of the root of the number of vectors), and sampled vectors for each.
PIVOTS, SAMPLE = (64, 1024), 64
#: Vectors in one chunk of the index, queries in one block, vectors in one ring.
CHUNK, QUERY_BLOCK, RING = 4096, 256, 256
#: Sums of products below this are exact in 64-bit floats.
EXACT = 2.0**53
#: No score: below every product.
NEVER = np.iinfo(np.int64).min
#: Share by which a bound has to fail before it rules anything out.
SLACK = 1e-6

CHUNKS = "chunk long, cell int, low double, high double, n int, ids binary, radius binary, x binary"
BLOCKS = "block long, cell int, radius double, ids binary, x binary, floor binary"
FOUND = "query_id long, vec_id long, score long"


def integer_vectors(rows: DataFrame, id_name: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """id, x: floor(256 v) of each finite component; vectors that are null or hold a null or non-finite one are left out."""
    x = F.transform(F.col(vector).cast("array<double>"), lambda v: F.floor(v * 256.0).cast("double"))
    fine = F.col(vector).isNotNull() & ~F.exists(F.col(vector).cast("array<double>"), lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    return rows.filter(F.coalesce(fine, F.lit(False)) & F.col(id_name).isNotNull()).select(F.col(id_name).cast("long").alias("id"), x.alias("x"))


def _matrix(column: pa.Array, width: int) -> np.ndarray:
    return np.asarray(column.flatten(), float).reshape(len(column), width)


def _numbers(value: pa.Scalar, kind=float) -> np.ndarray:
    return np.frombuffer(value.as_buffer(), kind)


def _lifted(x: np.ndarray, top: float) -> np.ndarray:
    return np.hstack([x, np.sqrt(np.maximum(top - (x**2).sum(1), 0))[:, None]])


def _distances(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum((x**2).sum(1)[:, None] + (y**2).sum(1)[None, :] - 2 * x @ y.T, 0))


def products(queries: np.ndarray, x: np.ndarray, top: float) -> np.ndarray:
    """Inner products as whole numbers; beyond the exact range of floats by Python's integers, cut to 64 bits."""
    if top < EXACT:
        return (queries @ x.T).astype(np.int64)
    whole = lambda m: [[int(v) for v in row] for row in m.tolist()]
    most = 2**63 - 1
    left, right = whole(queries), whole(x)
    return np.array([[max(-most, min(most, sum(p * q for p, q in zip(a, b)))) for b in right] for a in left], np.int64).reshape(len(left), len(right))


def _keyed(pivots: np.ndarray, top: float, query: bool) -> Callable:
    """id, cell, radius, x: the nearest pivot and the distance to it, of vectors or of queries."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 4096):
                part = batch.slice(start, 4096)
                x = _matrix(part.column("x"), pivots.shape[1] - 1)
                d = _distances(np.hstack([x, np.zeros((len(x), 1))]) if query else _lifted(x, top), pivots)
                cell = d.argmin(1)
                yield pa.RecordBatch.from_arrays([part.column("id"), pa.array(cell.astype(np.int32)), pa.array(d[np.arange(len(x)), cell]), part.column("x")], ["id", "cell", "radius", "x"])

    return tidy(run)


def _packed(size: int, width: int, whole_cells: bool) -> Callable:
    """Rows sorted by cell and radius, as packed rows of at most `size`, numbered from the task's number on.

    A chunk lies in one cell. A block of queries may go on into the next cell; it counts as one of its first.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number = TaskContext.get().partitionId() << 32
        held: list[tuple] = []
        count = 0

        def close() -> pa.RecordBatch:
            nonlocal held, count, number
            ids, cells, radius, x = (np.concatenate([h[k] for h in held]) for k in range(4))
            held, count, number = [], 0, number + 1
            key = pa.array([number], pa.int64()), pa.array(cells[:1].astype(np.int32))
            blobs = [binary_array([c.tobytes()]) for c in (ids, radius, x)]
            if whole_cells:
                return pa.RecordBatch.from_arrays([*key, pa.array(radius[:1]), pa.array(radius[-1:]), pa.array([len(ids)], pa.int32()), *blobs], ["chunk", "cell", "low", "high", "n", "ids", "radius", "x"])
            floor = binary_array([np.full(len(ids), -np.inf).tobytes()])
            return pa.RecordBatch.from_arrays([*key, pa.array([float(np.median(radius[cells == cells[0]]))]), blobs[0], blobs[2], floor], ["block", "cell", "radius", "ids", "x", "floor"])

        for batch in batches:
            ids, cells, radius = np.asarray(batch.column("id")), np.asarray(batch.column("cell")), np.asarray(batch.column("radius"))
            x = _matrix(batch.column("x"), width)
            at = 0
            while at < len(ids):
                if count and (count == size or whole_cells and held[-1][1][-1] != cells[at]):
                    yield close()
                end = min(at + size - count, len(ids))
                if whole_cells:
                    end = min(end, at + int(np.searchsorted(cells[at:], cells[at], side="right")))
                held.append((ids[at:end], cells[at:end], radius[at:end], x[at:end]))
                count, at = count + end - at, end
        if count:
            yield close()

    return tidy(run)


class _Chunk:
    """A chunk's sorted vectors, searched by a block of queries at once."""

    def __init__(self, row: pa.RecordBatch, pivots: np.ndarray, top: float, ring: int):
        value = lambda name, kind=float: _numbers(row.column(name)[0], kind)
        self.ids, self.radius = value("ids", np.int64), value("radius")
        self.x = value("x").reshape(len(self.ids), -1)
        self.pivot, self.top = pivots[row.column("cell")[0].as_py()][None, :], top
        self.starts = np.arange(0, len(self.ids), ring)
        self.ends = np.append(self.starts[1:], len(self.ids))
        self.low, self.high = self.radius[self.starts], self.radius[self.ends - 1]

    def search(self, queries: np.ndarray, own: np.ndarray, floor: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(scores, ids, k-th scores): the best k of each query that reach its floor; scores are NEVER where there are fewer."""
        n = len(queries)
        d = _distances(np.hstack([queries, np.zeros((n, 1))]), self.pivot)[:, 0]
        norm = (queries**2).sum(1)
        gap = np.maximum(np.maximum(self.low[None, :] - d[:, None], d[:, None] - self.high[None, :]), 0)
        order = np.argsort(gap, axis=1, kind="stable")  # rings outwards from each query
        best, found = np.full((n, k), NEVER), np.zeros((n, k), np.int64)
        floor, alive = floor.copy(), np.ones(n, bool)
        for step in range(len(self.starts)):
            rings = order[:, step]
            bound = (norm + self.top - gap[np.arange(n), rings] ** 2) / 2
            alive &= bound >= floor - SLACK * (np.abs(floor) + self.top + 1)
            if not alive.any():
                break
            for r in np.unique(rings[alive]).tolist():
                q = np.flatnonzero(alive & (rings == r))
                a, b = self.starts[r], self.ends[r]
                score = products(queries[q], self.x[a:b], self.top)
                good = (score >= floor[q, None]) & (self.ids[a:b][None, :] != own[q, None])
                some = np.flatnonzero(good.any(1))
                for i in some.tolist():
                    s = np.concatenate([best[q[i]], score[i, good[i]]])
                    ids = np.concatenate([found[q[i]], self.ids[a:b][good[i]]])
                    first = np.lexsort((ids, ~s))[:k]  # ~s falls as s grows, without overflow
                    best[q[i]], found[q[i]] = s[first], ids[first]
                    if best[q[i], -1] > NEVER:
                        floor[q[i]] = max(floor[q[i]], np.nextafter(float(best[q[i], -1]), -np.inf))
        return best, found, floor


def _met(pivots: np.ndarray, top: float, k: int, ring: int, seed: bool) -> Callable:
    """A chunk's search by the blocks that come to it, one after another.

    With seed the blocks go out again with their floors, else what was found.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        chunk = None
        for batch in batches:
            for at in range(batch.num_rows):
                row = batch.slice(at, 1)
                if row.column("tag")[0].as_py() == 0:
                    chunk = _Chunk(row, pivots, top, ring)
                    continue
                own = _numbers(row.column("ids")[0], np.int64)
                queries, floor = _numbers(row.column("x")[0]).reshape(len(own), -1), _numbers(row.column("floor")[0])
                best, ids, floor = chunk.search(queries, own, floor, k)
                if seed:
                    kept = [row.column(c) for c in ("block", "home", "low", "ids", "x")]
                    yield pa.RecordBatch.from_arrays([*kept, binary_array([floor.tobytes()])], ["block", "cell", "radius", "ids", "x", "floor"])
                    continue
                q, place = np.nonzero(best > NEVER)
                yield pa.RecordBatch.from_arrays([pa.array(own[q]), pa.array(ids[q, place]), pa.array(best[q, place])], ["query_id", "vec_id", "score"])

    return tidy(run)


def _reaches(pivots: np.ndarray, top: float) -> Callable:
    """block, cell, from, to: the distances to each pivot between which a vector may still count for some query of the block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(batch.num_rows):
                floor = _numbers(batch.column("floor")[at])
                queries = _numbers(batch.column("x")[at]).reshape(len(floor), -1)
                d = _distances(np.hstack([queries, np.zeros((len(floor), 1))]), pivots)
                room = (queries**2).sum(1) + top - 2 * floor
                ball = np.sqrt(np.maximum(room, 0) + 4 * SLACK * (np.abs(floor) + top + 1))[:, None]
                cells = len(pivots)
                low, high = (d - ball).min(0), (d + ball).max(0)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(cells, batch.column("block")[at].as_py())), pa.array(np.arange(cells, dtype=np.int32)), pa.array(low), pa.array(high)], ["block", "cell", "from", "to"])

    return tidy(run)


def _meet(chunks: DataFrame, blocks: DataFrame, pairs: DataFrame, kernel: Callable, schema: str) -> DataFrame:
    """kernel over each chunk and the blocks of its pairs (block, chunk); blocks stream past the chunk that is held."""
    none = lambda kind: F.lit(None).cast(kind)
    used = chunks.join(pairs.select("chunk").distinct(), "chunk", "left_semi")
    sides = [
        used.select("chunk", F.lit(0).alias("tag"), none("long").alias("block"), "cell", none("int").alias("home"), "low", "ids", "radius", "x", none("binary").alias("floor")),
        pairs.join(blocks, "block").select("chunk", F.lit(1).alias("tag"), "block", F.lit(0).alias("cell"), F.col("cell").alias("home"), F.col("radius").alias("low"), "ids", none("binary").alias("radius"), "x", "floor"),
    ]
    rows = sides[0].unionByName(sides[1])
    dealt = rows.repartition(partitions(chunks.sparkSession), "chunk").sortWithinPartitions("chunk", "tag")
    return dealt.groupBy("chunk").applyInArrow(kernel, schema)


def chosen_pivots(pool: np.ndarray, count: int) -> np.ndarray:
    """Farthest first: pivots spread over the sample."""
    chosen, nearest = [0], _distances(pool, pool[:1])[:, 0]
    while len(chosen) < min(count, len(pool)) and nearest.max() > 0:
        chosen.append(int(nearest.argmax()))
        nearest = np.minimum(nearest, _distances(pool, pool[chosen[-1:]])[:, 0])
    return pool[chosen]


def top_products(rows: DataFrame, k: int = 5, every: int = 50, pivots: int | None = None, sample: int | None = None, ring: int = RING, chunk: int = CHUNK, block: int = QUERY_BLOCK, id_name: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k largest integer inner products of each query.

    Queries are the rows whose id is divisible by `every`; candidates are all rows but those
    of the query's own id. Equal scores go to the smaller id; rows that repeat an id count
    once each as candidates, and the smallest vector of an id that repeats is the query. Fewer than k
    candidates give as many rows. Null ids, unusable and empty vectors take no part, nor
    do vectors that are not of the commonest length (of two as common, the longer). Pivots come from
    a bounded sample; every vector is indexed and the bounds are exact, so no result depends on them.
    """
    spark = rows.sparkSession
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    usable = stage(integer_vectors(rows, id_name, vector).filter(F.size("x") > 0), "vectors")
    length = usable.groupBy(F.size("x").alias("width")).count().orderBy(F.desc("count"), F.desc("width")).first()
    if length is None:
        return empty
    width, total = int(length["width"]), int(length["count"])
    vectors = usable.filter(F.size("x") == width)
    top = float(vectors.agg(F.max(F.aggregate("x", F.lit(0.0), lambda a, v: a + v * v))).first()[0])
    count = pivots or max(PIVOTS[0], min(PIVOTS[1], math.isqrt(total) // 16))
    drawn = vectors.orderBy(F.xxhash64("id"), "id", "x").limit(sample or count * SAMPLE).toPandas()
    points = chosen_pivots(_lifted(np.stack(drawn["x"].to_numpy()), top), count)
    dealt = lambda df, query: df.mapInArrow(_keyed(points, top, query), "id long, cell int, radius double, x array<double>").repartitionByRange("cell", "radius", "id").sortWithinPartitions("cell", "radius", "id")
    # sorted annuli: a hot cell is many chunks, spread over tasks by their radius
    chunks = stage(dealt(vectors, False).mapInArrow(_packed(chunk, width, True), CHUNKS), "pivot-index")
    queries = vectors.filter(F.pmod("id", F.lit(every)) == 0).groupBy("id").agg(F.min("x").alias("x"))
    blocks = stage(dealt(queries, True).mapInArrow(_packed(block, width, False), BLOCKS), "queries")
    directory = chunks.select("chunk", "cell", "low", "high")
    # first each block's nearest chunk, of its own cell if that holds any vector
    away = F.greatest(F.col("low") - F.col("radius"), F.col("radius") - F.col("high"), F.lit(0.0))
    own = blocks.select("block", "cell", "radius").join(directory, "cell").groupBy("block").agg(F.min_by("chunk", F.struct(away, "chunk")).alias("chunk"))
    seeded = stage(_meet(chunks, blocks, own, _met(points, top, k, ring, True), BLOCKS), "seeded")
    lost = blocks.join(seeded.select("block"), "block", "left_anti")  # their cells are empty: every chunk stays open
    blocks = seeded.unionByName(lost)
    reaches = blocks.select("block", "x", "floor").mapInArrow(_reaches(points, top), "block long, cell int, from double, to double")
    pairs = stage(reaches.join(directory, "cell").filter("low <= to and high >= from").select("block", "chunk"), "open")
    best = _meet(chunks, blocks, pairs, _met(points, top, k, ring, False), FOUND)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return best.withColumn("rank", F.row_number().over(order).cast("int")).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
