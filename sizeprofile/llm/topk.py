"""Exact top-k search by inner product with a uniform threshold, in three phases.

The components of the vectors are cut into `lists` blocks; a block's inner product is a partial score, and a score is
the sum of its partial scores.

1. Each tile of rows gathers, for every query and block, its local list of the best partial scores, and completes the
   scores of what is on the lists. The k-th best of these, over all tiles, is a score that k rows are known to reach:
   the query's safe cutoff.
2. The cutoff goes to all tiles. A row whose score reaches it must reach cutoff / lists in one block at least, so the
   entries at or above that uniform threshold are sufficient.
3. The remaining partial scores of those entries are resolved exactly; rows below the cutoff drop out, and the best k of
   each tile are merged.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import batches_of, rows_of, written

#: Rows in a tile, queries in a tile, and queries scored against a tile at once (bounds a task's memory).
TILE_ROWS, TILE_QUERIES, AT_ONCE = 4096, 1024, 128
#: Query tiles up to this size (measured) travel with the tasks; beyond, they are joined to the tiles by salted keys.
BROADCAST_BYTES = 8 << 20
#: Bytes of query tiles and of row tiles that meet in one cell of the grid.
CELL_BYTES = 32 << 20
LISTS = 4
_LEAST, _MOST = -(2**63), 2**63 - 1

_TILES = pa.schema([("tile", pa.int64()), ("width", pa.int32()), ("ids", pa.binary()), ("parts", pa.binary())])


def _matrix(col: pa.Array, scale: float) -> tuple[np.ndarray, np.ndarray]:
    """(which rows take part, their integer vectors as doubles). Shorter vectors are filled with zeros."""
    sizes = np.array([-1 if n is None else n for n in pa.compute.list_value_length(col).to_pylist()], dtype=np.int64)
    flat = col.flatten().cast(pa.float64()).to_numpy(zero_copy_only=False)  # null components become NaN
    with np.errstate(over="ignore", invalid="ignore"):
        flat = np.floor(flat * scale)
    held = np.maximum(sizes, 0)
    row = np.repeat(np.arange(len(sizes)), held)
    fit = sizes >= 0
    fit[row[~np.isfinite(flat)]] = False
    out = np.zeros((len(sizes), int(held.max(initial=0))))
    out[row, np.arange(len(flat)) - np.repeat(np.cumsum(held) - held, held)] = np.where(np.isfinite(flat), flat, 0)
    return fit, out[fit]


def _packed(rows: DataFrame, scale: float, most: int) -> DataFrame:
    """Tiles of at most `most` vectors: a number of their own, their width, ids and components."""

    def pack(batches):
        def tiles():
            tile = TaskContext.get().partitionId() << 32
            for b in batches:
                for at in range(0, b.num_rows, most):
                    part = b.slice(at, most)
                    fit, vectors = _matrix(part.column(1), scale)
                    ids = part.column(0).to_numpy(zero_copy_only=False)[fit]
                    if len(ids):
                        yield tile, vectors.shape[1], ids.astype("<i8").tobytes(), vectors.astype("<f8").tobytes()
                        tile += 1

        yield from batches_of(_TILES, tiles(), most=8)

    return rows.mapInArrow(pack, "tile long, width int, ids binary, parts binary")


def _tile(width: int, ids: bytes, parts: bytes) -> tuple[np.ndarray, np.ndarray]:
    ids = np.frombuffer(ids, dtype="<i8")
    return ids, np.frombuffer(parts, dtype="<f8").reshape(len(ids), width)


def _aligned(q: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both on their common components; Python integers where doubles can't hold the sums exactly."""
    d = min(q.shape[1], c.shape[1])
    q, c = q[:, :d], c[:, :d]
    if np.abs(q).max(initial=0) * np.abs(c).max(initial=0) * max(1, d) >= 2**53:
        whole = np.frompyfunc(int, 1, 1)
        q, c = whole(q), whole(c)
    return q, c


def _blocks(d: int, lists: int) -> list[slice]:
    cuts = [round(d * k / lists) for k in range(lists + 1)]
    return [slice(a, b) for a, b in zip(cuts, cuts[1:]) if b > a] or [slice(0, d)]


def _completed(q: np.ndarray, c: np.ndarray, qi: np.ndarray, ci: np.ndarray) -> np.ndarray:
    """Whole scores of the pairs, as 64-bit integers (saturated)."""
    if q.dtype == object:
        return np.array([min(_MOST, max(_LEAST, sum(x * y for x, y in zip(q[a], c[b])))) for a, b in zip(qi, ci)], dtype=np.int64)
    out = np.empty(len(qi), dtype=np.int64)
    for at in range(0, len(qi), 1 << 16):
        s = slice(at, at + (1 << 16))
        out[s] = np.einsum("ij,ij->i", q[qi[s]], c[ci[s]]).astype(np.int64)
    return out


def gathered(q_ids, q, c_ids, c, k: int, lists: int):
    """Phase 1 for one pair of tiles: (query's place, its best complete scores among the local lists)."""
    q, c = _aligned(q, c)
    blocks = _blocks(q.shape[1], lists)
    most = min(k + 1, len(c_ids))  # one more, as the query's own row may be on the list
    for begin in range(0, len(q_ids), AT_ONCE):
        part = q[begin : begin + AT_ONCE]
        found = []
        for b in blocks:
            scores = part[:, b] @ c[:, b].T
            found.append(np.argsort(-scores, axis=1)[:, :most] if scores.dtype == object else np.argpartition(scores, len(c_ids) - most, axis=1)[:, -most:])
        for i, row in enumerate(np.concatenate(found, axis=1)):
            row = np.unique(row)
            row = row[c_ids[row] != q_ids[begin + i]]
            best = np.sort(_completed(part, c, np.full(len(row), i), row))[::-1][:k]
            if len(best):
                yield begin + i, best.tolist()


def collected(q_ids, q, floors, c_ids, c, k: int, lists: int):
    """Phases 2 and 3 for one pair of tiles: (query's place, row id, score), the best k of the tile."""
    q, c = _aligned(q, c)
    blocks = _blocks(q.shape[1], lists)
    sizes = [None if c.dtype == object else np.linalg.norm(c[:, b], axis=1) for b in blocks]
    for begin in range(0, len(q_ids), AT_ONCE):
        part, least = q[begin : begin + AT_ONCE], floors[begin : begin + AT_ONCE]
        enough = np.zeros((len(part), len(c_ids)), dtype=bool)
        known = least > _LEAST
        cut = np.where(known, least.astype(object) if q.dtype == object else least.astype(float), -np.inf)[:, None]
        for b, size in zip(blocks, sizes):
            if size is None:
                enough |= (part[:, b] @ c[:, b].T) * len(blocks) >= cut
                continue
            own = np.linalg.norm(part[:, b], axis=1)
            with np.errstate(divide="ignore", invalid="ignore"):
                reach = np.where(cut[:, 0] <= 0, 0, np.where(own > 0, cut[:, 0] / (own * len(blocks)), np.inf)).min()
            rows = np.flatnonzero(size * (1 + 1e-9) >= reach)  # a shorter part can't reach the threshold with any of these queries
            enough[:, rows] |= (part[:, b] @ c[rows, b].T) * len(blocks) >= cut
        enough &= c_ids[None, :] != q_ids[begin : begin + AT_ONCE, None]
        qi, ci = np.nonzero(enough)
        score = _completed(part, c, qi, ci)
        stays = score >= least[qi]
        qi, ci, score = qi[stays], ci[stays], score[stays]
        order = np.lexsort((c_ids[ci], ~score, qi))  # ~score: descending without overflow
        qi, ci, score = qi[order], ci[order], score[order]
        place = np.arange(len(qi)) - np.searchsorted(qi, qi)
        for a, b, s in zip(*(x[place < k].tolist() for x in (qi, ci, score))):
            yield begin + a, int(c_ids[b]), s


def _cells(tiles: DataFrame, queries: DataFrame, n_bytes: int, row_bytes: int, kernel, arrow: pa.Schema, schema: str) -> DataFrame:
    """Apply the kernel to each pair of a query tile and a row tile.

    Query tiles up to BROADCAST_BYTES travel with the tasks. Beyond, both sides are dealt over a grid whose cells hold
    about CELL_BYTES of each, so a row tile is shuffled once for CELL_BYTES of queries, and no task holds more than a cell.
    """
    fields = queries.columns
    if n_bytes <= BROADCAST_BYTES:
        held = [tuple(r) for r in queries.collect()]

        def run(batches):
            yield from batches_of(arrow, (out for b in batches for t in zip(*(c.to_pylist() for c in b.columns)) for q in held for out in kernel(q, t)))

        return tiles.mapInArrow(run, schema)

    def cell(left: pa.Table, right: pa.Table) -> pa.Table:
        own = list(zip(*(left.column(f"q_{c}").to_pylist() for c in fields)))
        rows = (out for t in zip(*(right.column(c).to_pylist() for c in _TILES.names)) for q in own for out in kernel(q, t))
        return pa.Table.from_batches(batches_of(arrow, rows), schema=arrow)

    across, down = math.ceil(n_bytes / CELL_BYTES), math.ceil(max(1, row_bytes) / CELL_BYTES)
    place = lambda tile, n: F.pmod(F.xxhash64(tile), F.lit(n))
    every = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    left = queries.select(*[F.col(c).alias(f"q_{c}") for c in fields], place("tile", across).alias("column"), every(down).alias("row"))
    right = tiles.select("*", every(across).alias("column"), place("tile", down).alias("row"))
    return left.groupBy("column", "row").cogroup(right.groupBy("column", "row")).applyInArrow(cell, schema)


def top_k(vectors: DataFrame, queries: DataFrame, k: int = 5, scale: float = 256.0, lists: int = LISTS, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """query_id, rank (from 1), vec_id, score: each query's k highest integer inner products, ties to the smaller id.

    Components become floor(scale * x). Rows without an id, or whose vector is null or holds a null or non-finite
    component, take no part. Vectors of unequal length are compared on their common components (as if filled with
    zeros). Rows that share the query's id count as the query's own. Repeated query rows are one query; a repeated
    row of `vectors` is a candidate each time. Scores beyond 64 bits saturate. No queries or no rows: no result.

    Query tiles (measured) up to BROADCAST_BYTES are sent along; larger sets meet the rows in the cells of a grid, so
    neither side has to fit in one place. What is shuffled besides is k numbers a query and row tile in phase 1 and the entries above the
    cutoff, k at most, in phase 3.
    """
    spark = vectors.sparkSession
    clean = {"id": F.col(f"`{id_col}`").cast("long"), "vec": vector_col}
    rows = rows_of(vectors, **clean).where(F.col("id").isNotNull() & F.col("vec").isNotNull())
    asked = rows_of(queries, **clean).where(F.col("id").isNotNull() & F.col("vec").isNotNull()).dropDuplicates(["id", "vec"])
    n_asked = asked.count()
    tiles = _packed(rows, scale, TILE_ROWS)
    packed = written(_packed(asked.repartition(max(1, math.ceil(n_asked / TILE_QUERIES))), scale, TILE_QUERIES), "query-tiles")
    n_bytes, width = packed.agg(F.coalesce(F.sum(F.octet_length("parts")), F.lit(0)), F.max("width")).first()
    row_bytes = 8 * max(1, width) * rows.count() if n_bytes > BROADCAST_BYTES else 0
    if width is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    lists_schema = pa.schema([("tile", pa.int64()), ("place", pa.int32()), ("best", pa.list_(pa.int64()))])

    def first(q, t):
        for place, best in gathered(*_tile(*q[1:4]), *_tile(*t[1:]), k, lists):
            yield q[0], place, best

    local = _cells(tiles, packed, n_bytes, row_bytes, first, lists_schema, "tile long, place int, best array<long>")
    by_score = Window.partitionBy("tile", "place").orderBy(F.desc("score"))
    best = local.select("tile", "place", F.explode("best").alias("score")).withColumn("n", F.row_number().over(by_score)).where(F.col("n") <= k)
    floors = best.groupBy("tile", "place").agg(F.when(F.count(F.lit(1)) == k, F.min("score")).otherwise(F.lit(_LEAST)).alias("floor"))
    by_tile = floors.groupBy("tile").agg(F.map_from_entries(F.collect_list(F.struct("place", "floor"))).alias("floors"))  # one tile's queries
    ready = written(packed.join(by_tile, "tile", "left").select("tile", "width", "ids", "parts", "floors"), "query-cutoffs")
    result = pa.schema([("query_id", pa.int64()), ("tile", pa.int64()), ("place", pa.int32()), ("vec_id", pa.int64()), ("score", pa.int64())])

    def second(q, t):
        ids, parts = _tile(*q[1:4])
        floors = np.full(len(ids), _LEAST, dtype=np.int64)
        for place, floor in dict(q[4] or {}).items():
            floors[place] = floor
        for place, vec_id, score in collected(ids, parts, floors, *_tile(*t[1:]), k, lists):
            yield int(ids[place]), q[0], place, vec_id, score

    entries = _cells(tiles, ready, n_bytes, row_bytes, second, result, "query_id long, tile long, place int, vec_id long, score long")
    order = Window.partitionBy("query_id", "tile", "place").orderBy(F.desc("score"), "vec_id")
    return entries.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op7_top_k(spark, sf_dir: str) -> DataFrame:
    vectors = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding")
    return top_k(vectors, vectors.where("vec_id % 50 = 0"))


OP7_SQL = """
with v as (
  select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)) as e from embeddings
  where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
), s as (
  select q.vec_id as query_id, c.vec_id as vec_id, list_sum(list_transform(range(1, len(q.e) + 1), lambda i: q.e[i] * c.e[i]))::bigint as score
  from v q join v c on q.vec_id % 50 = 0 and c.vec_id <> q.vec_id
), r as (
  select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score from s
)
select query_id, rank, vec_id, score from r where rank <= 5
"""
