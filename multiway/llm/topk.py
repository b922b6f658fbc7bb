"""Exact top-k by inner product with a Voronoi join.

Vectors are lifted so that the largest inner product becomes the nearest point: a data vector x gets one more component
sqrt(M^2 - |x|^2) and a query gets 0 there, so |q'-x'|^2 = |q|^2 + M^2 - 2 q.x with M the largest norm. Pivots (a
sample of about the square root of the rows, at most PIVOTS) cut the lifted space into cells; one aggregation gives each cell its
size and radius. From these summaries alone each group of queries gets a radius that must hold its k best,
and a data row is sent to a query group only if the triangle inequality can't exclude it. Both sides are cut into pieces of
bounded size before they meet, so a hot cell is many tasks; each piece is solved by one matrix product. What is broadcast has a
row for a pair of cells, PIVOTS squared at most, however many rows and queries there are.

Defined results: vectors that are null, or hold a null, NaN or infinite component, take no part, nor do rows without an id;
lengths that differ are padded by zeros; scores tie to the smaller id; rows that repeat an id are candidates each, never for a
query of that id, and queries that repeat an id share one list of k; with fewer candidates than k all are returned; an empty
table gives no rows; other columns are not read, so their names cannot clash.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stored, table

#: Rows that serve as pivots, at most (and about the square root of the rows).
PIVOTS = 512
#: Queries that meet in a task, and about as many data rows, at most.
QUERY_ROWS, DATA_ROWS = 1024, 16384


def _matrix(column, width: int) -> np.ndarray:
    """Integer vectors of a column, padded to one width."""
    values = [np.asarray(x, np.int64) for x in column]
    if values and all(len(v) == width for v in values):
        return np.stack(values)
    out = np.zeros((len(values), width), np.int64)
    for i, v in enumerate(values):
        out[i, : len(v)] = v
    return out


def _arrow_matrix(column: pa.ListArray, width: int) -> np.ndarray:
    flat = column.flatten().to_numpy()
    return flat.reshape(len(column), width) if len(flat) == len(column) * width and (np.diff(column.offsets.to_numpy()) == width).all() else _matrix(column.to_pylist(), width)


def quantised(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 256) -> DataFrame:
    """vec_id and the integer vector; rows that take no part are gone."""
    x = F.col(vec_col).cast("array<double>")
    bad = F.exists(x, lambda c: c.isNull() | F.isnan(c) | (F.abs(c) == float("inf")))
    return vectors.filter(F.col(id_col).isNotNull() & x.isNotNull() & ~bad).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c * scale)).alias("vec"))


def products(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Exact integer inner products: by floating point where no sum can leave 2^53, else in integers of any size."""
    top = float(np.abs(q).max(initial=0)) * float(np.abs(x).max(initial=0)) * max(1, q.shape[1])
    if top < 2**53:
        return (q.astype(np.float64) @ x.astype(np.float64).T).astype(np.int64)
    if top < 2**63:
        return q @ x.T
    wide = q.astype(object) @ x.astype(object).T
    return np.clip(wide, -(2**63), 2**63 - 1).astype(np.int64)


def best(scores: np.ndarray, ids: np.ndarray, own: np.ndarray, k: int) -> list[np.ndarray]:
    """Positions of each row's k best, ties to the smaller id, without the query's own id."""
    out = []
    for row, me in zip(scores, own, strict=True):
        allowed = np.flatnonzero(ids != me)
        s = row[allowed]
        if len(s) > k:
            floor = np.partition(s, len(s) - k)[len(s) - k]
            allowed = allowed[s >= floor]
            s = row[allowed]
        out.append(allowed[np.lexsort((ids[allowed], -s))[:k]])
    return out


def voronoi_top_k(vectors: DataFrame, is_query, k: int = 5, pivots: int = PIVOTS, query_rows: int = QUERY_ROWS, data_rows: int = DATA_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k best; `vectors` as from quantised(), is_query a Column over it."""
    vectors = stored(vectors.select("vec_id", "vec"))
    spark = vectors.sparkSession
    square = F.aggregate("vec", F.lit(0.0), lambda total, c: total + c.cast("double") * c.cast("double"))
    seen = vectors.agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("width"), F.max(square).alias("most")).first()
    out_schema = "query_id long, rank int, vec_id long, score long"
    if not seen["n"]:
        return spark.createDataFrame([], out_schema)
    picked = vectors.orderBy(F.xxhash64("vec_id", "vec")).limit(max(8, min(pivots, math.isqrt(seen["n"])))).collect()
    width, top_norm = max(1, seen["width"]), math.sqrt(seen["most"])
    centre = _matrix([r["vec"] for r in picked], width).astype(np.float64)
    centre = np.unique(np.hstack([centre, np.sqrt(np.maximum(0, top_norm**2 - (centre**2).sum(1)))[:, None]]), axis=0)
    slack = 1e-6 * (1 + top_norm)

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x = _arrow_matrix(batch.column("vec"), width).astype(np.float64)
            squares = (x**2).sum(1)
            lift = np.sqrt(np.maximum(0, top_norm**2 - squares))
            square_d = np.maximum(0, (squares + lift**2)[:, None] + (centre**2).sum(1)[None] - 2 * (x @ centre[:, :-1].T + lift[:, None] * centre[:, -1][None]))
            near = square_d.argmin(1)
            flat = np.maximum(0, squares[:, None] + (centre**2).sum(1)[None] - 2 * x @ centre[:, :-1].T)
            near_q = flat.argmin(1)
            rows = np.arange(len(x))
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), batch.column("vec"), pa.array(near, pa.int32()), pa.array(np.sqrt(square_d[rows, near])), pa.array(near_q, pa.int32()), pa.array(np.sqrt(flat[rows, near_q])), batch.column("_query")], ["vec_id", "vec", "cell", "far", "query_cell", "query_far", "_query"])

    placed = stored(vectors.withColumn("_query", F.coalesce(is_query.cast("boolean"), F.lit(False))).mapInArrow(cells, "vec_id long, vec array<long>, cell int, far double, query_cell int, query_far double, _query boolean"))
    summary = placed.groupBy("cell").agg(F.count("*").alias("n"), F.max("far").alias("far")).collect()
    sides = placed.filter("_query").groupBy("query_cell").agg(F.count("*").alias("n"), F.max("query_far").alias("far")).collect()
    if not sides:
        return spark.createDataFrame([], out_schema)
    # No more than so many rows have a query's own id and are no candidates of it.
    own = placed.join(placed.filter("_query").select("vec_id").distinct(), "vec_id", "left_semi").groupBy("vec_id").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
    between = np.sqrt(np.maximum(0, ((centre[:, None] - centre[None]) ** 2).sum(2)))
    cell, count, far = (np.array([h[c] for h in sorted(summary, key=lambda h: h["cell"])]) for c in ("cell", "n", "far"))
    # Query cells of few queries are merged into groups; a cell of many is cut into parts. Both follow from the counts.
    groups: list[list] = []
    for s in sorted(sides, key=lambda s: s["query_cell"]):
        if groups and groups[-1][1] + s["n"] <= query_rows:
            groups[-1][0].append(s)
            groups[-1][1] += s["n"]
        else:
            groups.append([[s], s["n"]])
    wanted, owners = [], []
    for g, (cells_of, n) in enumerate(groups):
        least = np.full(len(cell), math.inf)  # distance to its pivot that a row of a cell must have to be needed
        for s in cells_of:
            u, d = s["far"], between[s["query_cell"], cell]
            reach = np.argsort(u + d + far)
            holds = np.flatnonzero(np.cumsum(count[reach]) >= k + own)
            theta = (u + d + far)[reach[holds[0]]] if len(holds) else math.inf
            possible = d - u - far <= theta + slack
            least = np.where(possible, np.minimum(least, d - u - theta - slack), least)
        needed = np.flatnonzero(least < math.inf)
        pieces, parts = max(1, -(-int(count[needed].sum()) // data_rows)), -(-n // query_rows)
        wanted += [(int(cell[c]), g, pieces, parts, float(max(least[c], -1.0))) for c in needed]
        owners += [(s["query_cell"], g, pieces, parts) for s in cells_of]
    wanted_rows = spark.createDataFrame(wanted, "cell int, grp int, pieces int, parts int, least double")
    owner_rows = spark.createDataFrame(owners, "query_cell int, grp int, pieces int, parts int")
    upto = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    # The place among the stored rows deals repeated rows over pieces too.
    piece, part = F.pmod(F.xxhash64("_place"), F.col("pieces")).cast("int"), F.pmod(F.xxhash64("_place", F.lit(1)), F.col("parts")).cast("int")
    placed = placed.withColumn("_place", F.monotonically_increasing_id())
    data = placed.join(F.broadcast(wanted_rows), "cell").filter("far >= least").select("grp", upto("parts").alias("part"), piece.alias("piece"), "vec_id", "vec")
    asked = placed.filter("_query").join(F.broadcast(owner_rows), "query_cell").select("grp", part.alias("part"), upto("pieces").alias("piece"), F.col("vec_id").alias("query_id"), F.col("vec").alias("query"))

    def solve(q: pd.DataFrame, x: pd.DataFrame) -> pd.DataFrame:
        if not len(q) or not len(x):
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype("int64")
        a, b, ids = _matrix(q["query"], width), _matrix(x["vec"], width), x["vec_id"].to_numpy()
        found, asked_ids = [], q["query_id"].to_numpy()
        for start in range(0, len(a), 256):
            s = products(a[start : start + 256], b)
            for i, pos in enumerate(best(s, ids, asked_ids[start : start + 256], k)):
                found.append((np.full(len(pos), asked_ids[start + i]), ids[pos], s[i, pos]))
        return pd.DataFrame({n: np.concatenate(c) for n, c in zip(("query_id", "vec_id", "score"), zip(*found, strict=True), strict=True)})

    asked = asked.toDF("_grp", "_part", "_piece", "query_id", "query")
    local = asked.groupBy("_grp", "_part", "_piece").cogroup(data.groupBy("grp", "part", "piece")).applyInPandas(solve, "query_id long, vec_id long, score long")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return local.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op5_voronoi_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return voronoi_top_k(quantised(table(spark, sf_dir, "embeddings")), F.col("vec_id") % 50 == 0, 5)


SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS DOUBLE)) AS e FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), pairs AS (
  SELECT q.vec_id AS query_id, x.vec_id AS vec_id, CAST(list_dot_product(q.e, x.e) AS BIGINT) AS score
  FROM v q JOIN v x ON q.vec_id % 50 = 0 AND q.vec_id <> x.vec_id
), ranked AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM pairs
)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score FROM ranked WHERE r <= 5
"""
