"""Approximate nearest neighbours on shifted space-filling curves.

Vectors are scaled to length one and projected on groups of axes: first the principal
ones (fitted on a bounded sample, the parameter ``sample``; every vector is indexed),
then random rotations of them. Each group, shifted at random, gives a Hilbert ordering,
cut by quantiles into blocks; a query's window is the blocks about its own place.

Plan. (1) Rows are stored once with their places on all curves, in chunks of at most
``CHUNK`` rows, numbered in each. (2) Only places travel to the blocks of the curves; a
block answers for each chunk with its rows' numbers and the queries that visit it, so
the product of the two is never written out. (3) Vectors travel once, by chunk; queries
come in groups of bounded size. There the windows of all curves merge into one set of
rows for each query, these rows alone are compared (exact cosine of the original
vectors in double precision), and the chunks' best lists merge.

Many narrow windows find more than few wide ones: on the given vectors (nearly uniform
in 64 dimensions, so that no ordering tells much) 32 curves with windows of 1/43 of the
rows find 0.94 of the true five among 0.5 of the rows; random blocks of the same
number of rows find 0.5. Clustered vectors need fewer curves. Blocks hold ``BLOCK``
rows at most and ``LEAST`` at least, so the windows of small tables are a larger share.
Equal keys are told apart by a hash of the id, so a vector that a third of all rows
share spreads over blocks.

Defined results: vectors null, zero, of another than the commonest length, or with
null or non-finite components take no part; rows without an id neither; if there are
fewer than k candidates in the windows, all of these are returned; equal scores go to
the smaller id; rows that repeat an id are one candidate (their best score).
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .durable import stored

CURVES, DIMENSIONS, BITS, WINDOW, SAMPLE, SEED = 32, 8, 4, 3 / 128, 5_000, 11
BLOCK, LEAST, CHUNK = 8192, 32, 4096


def hilbert_keys(cells: np.ndarray, bits: int) -> np.ndarray:
    """Place on the Hilbert curve of each row of integer cells (Gray-code transposition)."""
    x = cells.astype(np.uint64).copy()
    n, one = x.shape[1], np.uint64(1)
    level = one << np.uint64(bits - 1)
    while level > one:
        low = level - one
        for i in range(n):
            high = (x[:, i] & level) != 0
            swap = np.where(high, np.uint64(0), (x[:, 0] ^ x[:, i]) & low)
            x[:, 0] ^= np.where(high, low, np.uint64(0))
            x[:, 0] ^= swap
            x[:, i] ^= swap
        level >>= one
    for i in range(1, n):
        x[:, i] ^= x[:, i - 1]
    turn = np.zeros(len(x), dtype=np.uint64)
    level = one << np.uint64(bits - 1)
    while level > one:
        turn ^= np.where((x[:, n - 1] & level) != 0, level - one, np.uint64(0))
        level >>= one
    x ^= turn[:, None]
    key = np.zeros(len(x), dtype=np.uint64)
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << one) | ((x[:, i] >> np.uint64(b)) & one)
    return key


def _curves(sample: np.ndarray, curves: int, dimensions: int, seed: int):
    """(axes, centre, scale, shift) of each ordering."""
    rng, n = np.random.default_rng(seed), sample.shape[1]
    axes = np.linalg.svd(sample - sample.mean(0), full_matrices=False)[2] if len(sample) else np.eye(n)
    axes = np.linalg.qr(np.vstack([axes, rng.normal(size=(n, n))]).T)[0].T[:n]  # completed to all dimensions
    d, out, turned = min(dimensions, n), [], axes
    for c in range(curves):
        first = c * d % n
        if c and first < d:
            turned = np.linalg.qr(rng.normal(size=(n, n)))[0] @ axes
        own = turned[(np.arange(d) + first) % n]
        y = sample @ own.T
        out.append((own, y.mean(0), np.maximum(y.std(0), 1e-12), rng.random(d)))
    return out


def layout(total: int, window: float = WINDOW, block: int = BLOCK) -> tuple[int, int]:
    """Blocks of an ordering of ``total`` rows, and how many a query visits on either side of its own."""
    blocks = max(1, min(round(3 / window), total // LEAST), -(-total // block))
    return blocks, min(max(1, int(np.ceil((window * blocks - 1) / 2 - 1e-9))), blocks - 1)


def cosine(query: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Cosines in double precision; a pair's value does not depend on other rows."""
    return (rows * query).sum(1) / (np.sqrt((rows * rows).sum(1)) * np.sqrt((query * query).sum()))


def nearest(vectors: DataFrame, is_query, k: int = 5, id_col: str = "vec_id", vector_col: str = "embedding", curves: int = CURVES, dimensions: int = DIMENSIONS, bits: int = BITS,
            window: float = WINDOW, sample: int = SAMPLE, block: int = BLOCK, seed: int = SEED) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest rows found for each row with ``is_query``;
    rows_seen: how many rows the query was compared with."""
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    sound = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), v.alias("v"), F.coalesce(is_query, F.lit(False)).alias("is_query")).where(F.col("id").isNotNull() & F.col("v").isNotNull())
    rows = rows.where(sound & F.exists("v", lambda x: x != 0))
    lengths = rows.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n"), F.count_if("is_query").alias("q")).orderBy(F.desc("n"), "d").first()
    if lengths is None:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double, rows_seen long")
    rows, total = rows.where(F.size("v") == lengths["d"]), lengths["n"]
    blocks, reach = layout(total, window, block)
    groups = max(1, -(-lengths["q"] // CHUNK))  # queries come to a chunk in groups of about CHUNK
    drawn = rows.select("v").orderBy(F.xxhash64("id", F.lit(seed)), "id").limit(sample).toPandas()["v"]
    spaces = _curves(_unit(np.array([list(x) for x in drawn]).reshape(-1, lengths["d"])), curves, dimensions, seed)

    def keys(batches):
        chunk = TaskContext.get().partitionId() << 32
        for batch in batches:
            for at in range(0, batch.num_rows, CHUNK):
                part = batch.slice(at, CHUNK)
                unit, out = _unit(np.array(part.column(1).to_pylist(), dtype=np.float64).reshape(part.num_rows, -1)), []
                for own, centre, scale, shift in spaces:
                    y = 1 / (1 + np.exp(-1.6 * (unit @ own.T - centre) / scale))
                    cells = np.minimum((y * 0.5 + shift * 0.5) * 2**bits, 2**bits - 1).astype(np.uint64)
                    out.append(hilbert_keys(cells, bits).astype(np.int64))
                own_numbers = [pa.array(np.full(part.num_rows, chunk)), pa.array(np.arange(part.num_rows, dtype=np.int32))]
                places = pa.array(np.array(out).T.tolist(), type=pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays([*part.columns, *own_numbers, places], names=["id", "v", "is_query", "chunk", "number", "places"])
                chunk += 1

    placed = rows.mapInArrow(keys, "id long, v array<double>, is_query boolean, chunk long, number int, places array<long>")
    # 31 bits of a hash below the key: rows with equal keys have an order of their own.
    tie = F.shiftrightunsigned(F.xxhash64("id"), 33)
    placed = stored(placed.withColumn("places", F.transform("places", lambda p: F.shiftleft(p, 31).bitwiseOR(tie))), "placed")
    cuts = placed.agg(*(F.percentile_approx(F.element_at("places", c + 1), [i / blocks for i in range(1, blocks)], 20 * blocks).alias(f"c{c}") for c in range(curves))).first() if blocks > 1 else [()] * curves
    bounds = F.array(*(F.array(*map(F.lit, sorted(set(cuts[c])) or [None])).cast("array<long>") for c in range(curves)))
    at = placed.select("id", "is_query", "chunk", "number", F.posexplode("places").alias("curve", "place")).withColumn("cuts", F.get(bounds, F.col("curve")))
    steps = F.array(*(F.lit(2**i) for i in range((blocks - 1).bit_length(), -1, -1)))
    search = F.aggregate(steps, F.lit(0), lambda acc, s: F.when(F.get("cuts", acc + s - 1) <= F.col("place"), acc + s).otherwise(acc))
    dealt = at.select("id", "is_query", "chunk", "number", "curve", search.alias("block"))
    visited = F.sequence(F.greatest(F.col("block") - reach, F.lit(0)), F.least(F.col("block") + reach, F.lit(blocks - 1)))
    visits = dealt.where("is_query").select("curve", F.explode(visited).alias("block"), F.lit(-1).cast("long").alias("chunk"), _group(F.col("id"), groups).alias("number"), "id")
    meetings = dealt.select("curve", "block", "chunk", "number", F.lit(None).cast("long").alias("id")).unionByName(visits)
    windows = stored(meetings.groupBy("curve", "block").applyInPandas(_window_of, "chunk long, grp int, numbers binary, queries binary"), "windows")

    asked = placed.where("is_query").select(F.col("id").alias("q"), F.col("v").alias("qv"))
    asked = asked.withColumn("grp", _group(F.col("q"), groups)).dropDuplicates(["q", "qv"])
    tasks = windows.select(F.col("chunk").alias("at"), F.col("grp").alias("of")).distinct()
    here = placed.join(tasks, F.col("chunk") == F.col("at")).select("at", "of", "number", "id", "v")
    queries = asked.join(tasks, F.col("grp") == F.col("of")).select("at", "of", F.lit(-1).alias("number"), F.col("q").alias("id"), F.col("qv").alias("v"))

    def rerank(vectors: pd.DataFrame, lists: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame(_nearest_in_chunk(vectors, lists, k), columns=["query_id", "vec_id", "score", "seen"]).astype({"query_id": "int64", "vec_id": "int64", "score": "float64", "seen": "int64"})

    found = here.unionByName(queries).groupBy("at", "of").cogroup(windows.groupBy("chunk", "grp")).applyInPandas(rerank, "query_id long, vec_id long, score double, seen long")
    best = found.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"), F.sum("seen").alias("seen"))
    own = Window.partitionBy("query_id")
    best = best.withColumn("rank", F.row_number().over(own.orderBy(F.desc("score"), "vec_id")).cast("int")).withColumn("rows_seen", F.sum("seen").over(own))
    return best.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", "rows_seen")


def _unit(x):
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _group(key, groups):
    return F.pmod(F.xxhash64(key), F.lit(groups)).cast("int")


def _window_of(rows: pd.DataFrame) -> pd.DataFrame:
    """For a block: the numbers of its rows in each chunk, with the queries (by group) that visit
    the block; these have chunk -1 and their group as number."""
    chunk, number = rows["chunk"].to_numpy(np.int64), rows["number"].to_numpy(np.int32)
    mine, out = chunk >= 0, []
    if mine.any() and not mine.all():
        asking, group = rows["id"][~mine].to_numpy(np.int64), number[~mine]
        by = np.lexsort((number[mine], chunk[mine]))
        c, n = chunk[mine][by], number[mine][by]
        edge = np.concatenate([[0], np.flatnonzero(c[1:] != c[:-1]) + 1, [len(c)]])
        lists = [(int(c[a]), n[a:b].astype("<u2").tobytes()) for a, b in zip(edge[:-1], edge[1:])]
        for g in np.unique(group):
            own = np.unique(asking[group == g]).astype("<i8").tobytes()
            out.extend((place, int(g), numbers, own) for place, numbers in lists)
    return pd.DataFrame(out, columns=["chunk", "grp", "numbers", "queries"])


def _nearest_in_chunk(vectors, lists, k):
    """(query, row, score, rows seen: with the query's first row only) of one chunk and group of queries."""
    number = vectors["number"].to_numpy(np.int64)
    if lists.empty or not (number >= 0).any() or (number >= 0).all():
        return
    ids, rows = vectors["id"].to_numpy(np.int64), np.stack(vectors["v"].to_numpy()).astype(np.float64)
    own = np.argsort(number, kind="stable")[np.count_nonzero(number < 0) :]
    q_ids, q_rows, ids, rows, number = ids[number < 0], rows[number < 0], ids[own], rows[own], number[own]
    at = np.full(number.max() + 1, -1)
    at[number] = np.arange(len(number))
    near = np.zeros((len(q_ids), len(ids)), dtype=bool)
    order = np.argsort(q_ids, kind="stable")
    for numbers, asking in zip(lists["numbers"], lists["queries"]):
        asking = np.frombuffer(asking, dtype="<i8")
        first, last = np.searchsorted(q_ids[order], asking), np.searchsorted(q_ids[order], asking, side="right")
        spots = np.concatenate([order[a:b] for a, b in zip(first, last)]) if len(asking) else order[:0]
        near[np.ix_(spots, at[np.frombuffer(numbers, dtype="<u2")])] = True
    unit, asked = _unit(rows), _unit(q_rows)
    for i, own_id in enumerate(q_ids.tolist()):
        seen = np.flatnonzero(near[i] & (ids != own_id))
        if not len(seen):
            continue
        rough = unit[seen] @ asked[i]
        least = np.partition(rough, -k)[-k] if len(seen) > k else -np.inf
        while True:  # rows that repeat an id count once, so more rows may be wanted
            close = seen[rough >= least - 1e-9]
            if len(np.unique(ids[close])) >= min(k, len(seen)) or len(close) == len(seen):
                break
            least = np.sort(rough)[-min(len(seen), 2 * len(close))]
        exact = cosine(q_rows[i], rows[close])
        done, count = set(), len(seen)
        for j in np.lexsort((ids[close], -exact)):
            if int(ids[close[j]]) not in done:
                done.add(int(ids[close[j]]))
                yield own_id, int(ids[close[j]]), float(exact[j]), count
                count = 0
                if len(done) == k:
                    break
