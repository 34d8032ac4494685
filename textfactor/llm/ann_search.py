"""Approximate nearest neighbours by shifted Hilbert orderings.

Each ordering projects the unit vectors to a few dimensions with its own seeded matrix, spreads every coordinate evenly over a
grid with its own shift, and sorts all rows by their place on the Hilbert curve: rows are range-partitioned, numbered, and cut into
blocks of equal length, so no block is larger than another however often a vector is repeated. A query looks at the rows whose
rank is within a window of its own, in every ordering that is used; candidates are scored exactly and merged.

How many orderings are used, and how wide the window is, is measured, not guessed: for at most `calibrate` queries (smallest hash of id) the true
neighbours are found by a pass over all rows. For c = 1 .. `curves` orderings the window is the rank distance within which the `recall` share of them lies
in the best of c; the c with the fewest rows to score is taken. On clustered vectors that is a small share of the table; on vectors without any structure
no window is small, and close to all rows are scored. Every row is in every ordering used.

Cases: vectors that are null, zero, hold a null or non-finite component, or have another length than most valid rows take no
part, as query or candidate; ties go to the smaller id; repeated vectors are separate candidates; fewer candidates than k are all returned; empty tables give no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from textfactor.llm.common import Scratch


def hilbert_place(cells: np.ndarray, bits: int) -> np.ndarray:
    """Place on the Hilbert curve of integer cells (rows, dims), bits per dimension; bits * dims <= 62."""
    x = cells.astype(np.int64).T.copy()
    dims = len(x)
    q = 1 << (bits - 1)
    while q > 1:  # undo the rotations from the coarsest level down
        low = q - 1
        for i in range(dims):
            inverted = (x[i] & q) != 0
            swap = np.where(inverted, 0, (x[0] ^ x[i]) & low)
            x[0] ^= np.where(inverted, low, swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, dims):  # Gray code across the dimensions
        x[i] ^= x[i - 1]
    turn, q = np.zeros_like(x[0]), 1 << (bits - 1)
    while q > 1:
        turn = np.where((x[dims - 1] & q) != 0, turn ^ (q - 1), turn)
        q >>= 1
    x ^= turn
    place = np.zeros_like(x[0])
    for bit in range(bits - 1, -1, -1):
        for i in range(dims):
            place = (place << 1) | ((x[i] >> bit) & 1)
    return place


def curve_keys(unit: np.ndarray, curve: int, dims: int, bits: int) -> np.ndarray:
    rng = np.random.default_rng(1000 + curve)
    matrix = rng.standard_normal((unit.shape[1], dims))
    spread = np.vectorize(math.erf)(unit @ (matrix / np.linalg.norm(matrix, axis=0)) * math.sqrt(unit.shape[1] / 2)) / 2 + 0.5
    cells = ((spread + rng.random(dims)) / 2 * (1 << bits)).astype(np.int64)
    return hilbert_place(np.clip(cells, 0, (1 << bits) - 1), bits)


def valid_rows(batch: pa.RecordBatch, dim: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(ids, vectors in double precision) of the rows that take part."""
    ids, out = [], []
    for i, v in zip(batch.column("vec_id").to_pylist(), batch.column("vec").to_pylist(), strict=True):
        if i is None or not v or (dim and len(v) != dim) or None in v:
            continue
        a = np.array(v, np.float64)
        if np.isfinite(a).all() and a.any():
            ids.append(i)
            out.append(a)
    return np.array(ids, np.int64), (np.stack(out) if out and dim else out)


def cosines(q: np.ndarray, rows: np.ndarray) -> np.ndarray:
    return (rows * q).sum(1) / (np.sqrt((q * q).sum()) * np.sqrt((rows * rows).sum(1)))


def best(query_ids, queries, ids, rows, k: int, asked=None, ranks=None, window: int = 0):
    """Yields (query id, row id, score): each query's k nearest rows here, ties to smaller ids; with ranks only rows within the window of the query's."""
    unit = rows / np.linalg.norm(rows, axis=1, keepdims=True)
    for at in range(0, len(query_ids), 256):
        some = queries[at : at + 256]
        near = (some / np.linalg.norm(some, axis=1, keepdims=True)) @ unit.T
        for j, q in enumerate(query_ids[at : at + 256]):
            line = np.where(ids == q, -2.0, near[j])
            if ranks is not None:
                line[np.abs(ranks - asked[at + j]) > window] = -2.0
            least = np.partition(line, len(line) - k)[len(line) - k] if len(line) > k else -1.5
            pick = np.flatnonzero((line >= least - 1e-9) & (line > -1.5))
            exact = cosines(some[j], rows[pick])
            for n in np.lexsort((ids[pick], -exact))[:k]:
                yield int(q), int(ids[pick[n]]), float(exact[n])


def _table(rows) -> list[pa.Array]:
    a, b, c = zip(*rows, strict=True) if rows else ((), (), ())
    return [pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.float64())]


def nearest(embeddings: DataFrame, is_query, k: int = 5, curves: int = 6, dims: int = 8, bits: int = 7, block: int = 2048, calibrate: int = 64, recall: float = 0.97, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest rows found for every row that is_query (a column over vec_id) selects."""
    spark = embeddings.sparkSession
    scratch = Scratch(spark, "ann")
    rows = embeddings.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("vec"))
    valid = F.col("vec_id").isNotNull() & F.forall("vec", lambda x: F.coalesce(F.abs(x) < float("inf"), F.lit(False))) & F.exists("vec", lambda x: x != 0)
    commonest = rows.where(valid).groupBy(F.size("vec").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).first()
    dim = commonest.n if commonest else 1

    def place(batches):
        for batch in batches:
            ids, v = valid_rows(batch, dim)
            if not len(ids):
                continue
            unit = v / np.linalg.norm(v, axis=1, keepdims=True)
            raw = pa.array([x.tobytes() for x in v], pa.binary())
            for c in range(curves):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), c, np.int32)), pa.array(curve_keys(unit, c, dims, bits)), pa.array(ids), raw], ["curve", "key", "vec_id", "vec"])

    def number(batches):
        seen: dict[int, int] = {}
        for batch in batches:
            curve = batch.column("curve").to_numpy()
            at = np.empty(len(curve), np.int64)
            for c in np.unique(curve):
                mine = np.flatnonzero(curve == c)
                at[mine] = seen.get(int(c), 0) + np.arange(len(mine))
                seen[int(c)] = seen.get(int(c), 0) + len(mine)
            yield pa.RecordBatch.from_arrays([*(batch.column(x) for x in ("curve", "vec_id", "vec", "part")), pa.array(at)], ["curve", "vec_id", "vec", "part", "at"])

    keyed = rows.mapInArrow(place, "curve int, key long, vec_id long, vec binary")
    ordered = keyed.repartitionByRange("curve", "key", "vec_id").sortWithinPartitions("curve", "key", "vec_id").withColumn("part", F.spark_partition_id())
    placed = scratch.write(ordered.mapInArrow(number, "curve int, vec_id long, vec binary, part int, at long"), "ordered")
    sizes = sorted((r.curve, r.part, r.n) for r in placed.groupBy("curve", "part").agg(F.count(F.lit(1)).alias("n")).collect())
    bases, run = [], {}
    for curve, part, n in sizes:  # a row per partition
        bases.append((curve, part, run.get(curve, 0)))
        run[curve] = run.get(curve, 0) + n
    bases = spark.createDataFrame(bases, "curve int, part int, base long")
    ranked = placed.join(F.broadcast(bases), ["curve", "part"]).select("curve", "vec_id", "vec", (F.col("base") + F.col("at")).alias("rank"))
    count = max(run.values(), default=0)
    used, window = _measured(ranked, ranked.where(is_query), k, curves, calibrate, recall, dim, count)
    ranked = ranked.where(F.col("curve") < used)
    queries = ranked.where(is_query)
    low, high = F.greatest(F.col("rank") - window, F.lit(0)), F.least(F.col("rank") + window, F.lit(max(0, count - 1)))
    asked = queries.select("curve", F.explode(F.sequence(F.floor(low / block), F.floor(high / block))).alias("block"), F.col("vec_id").alias("q_id"), F.col("vec").alias("q_vec"), F.col("rank").alias("q_rank"))
    blocks = ranked.select(F.col("curve").alias("of_curve"), F.floor(F.col("rank") / block).alias("of_block"), F.col("vec_id").alias("row_id"), F.col("vec").alias("row_vec"), F.col("rank").alias("row_rank"))

    def rerank(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        read = lambda t, c: np.frombuffer(b"".join(t.column(c).to_pylist()), np.float64).reshape(-1, dim)
        found = []
        if left.num_rows and right.num_rows:
            found = list(best(left.column("q_id").to_numpy(), read(left, "q_vec"), right.column("row_id").to_numpy(), read(right, "row_vec"), k, left.column("q_rank").to_numpy(), right.column("row_rank").to_numpy(), window))
        return pa.Table.from_arrays(_table(found), ["query_id", "vec_id", "score"])

    near = asked.groupBy("curve", "block").cogroup(blocks.groupBy("of_curve", "of_block")).applyInArrow(rerank, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.distinct().withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def fewest_rows(gaps: np.ndarray, recall: float, count: int) -> tuple[int, int]:
    """(orderings, window) with the fewest rows to score; gaps: rank distances of true neighbours, a column per ordering."""
    found = []
    for c in range(1, gaps.shape[1] + 1):
        least = np.sort(gaps[:, :c].min(1))
        window = int(least[min(len(least) - 1, math.ceil(recall * len(least)) - 1)])
        found.append((c * min(count, 2 * window + 1), c, min(count, window)))
    _, c, window = min(found)
    return c, window


def _measured(ranked: DataFrame, queries: DataFrame, k: int, curves: int, calibrate: int, recall: float, dim: int, count: int) -> tuple[int, int]:
    sample = queries.where("curve = 0").select("vec_id", "vec").orderBy(F.xxhash64("vec_id"), "vec_id").limit(calibrate).collect()
    if not sample:
        return 1, 0
    ids = np.array([r.vec_id for r in sample], np.int64)
    vectors = np.stack([np.frombuffer(bytes(r.vec), np.float64) for r in sample])

    def scan(batches):
        for batch in batches:
            rows = np.frombuffer(b"".join(batch.column("vec").to_pylist()), np.float64).reshape(-1, dim)
            if len(rows):
                yield pa.RecordBatch.from_arrays(_table(list(best(ids, vectors, batch.column("vec_id").to_numpy(), rows, k))), ["q", "v", "score"])

    order = Window.partitionBy("q").orderBy(F.desc("score"), "v")
    truth = ranked.where("curve = 0").select("vec_id", "vec").mapInArrow(scan, "q long, v long, score double").withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).select("q", "v").collect()
    if not truth:
        return 1, 0
    wanted = ranked.sparkSession.createDataFrame([(int(x),) for x in {y for t in truth for y in (t.q, t.v)}], "vec_id long")
    rank = {(r.vec_id, r.curve): r["rank"] for r in ranked.join(F.broadcast(wanted), "vec_id").select("vec_id", "curve", "rank").collect()}  # calibrate * (k + 1) ids at most
    return fewest_rows(np.array([[abs(rank[t.q, c] - rank[t.v, c]) for c in range(curves)] for t in truth]), recall, count)
