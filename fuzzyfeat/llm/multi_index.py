"""Nearest neighbours by largest inner product, through an inverted multi-index.

Both halves of the vectors have a codebook each, fitted by k-means on a bounded sample, with more centroids for more
vectors; every vector is indexed in the cell of its pair of centroids. A query walks the pairs by summed distance (the
negative inner product of each half with its centroid) with a heap, until the cells met hold a share of all vectors, and
the entries of those cells are reranked by their inner products with the query in double precision.

The share is measured: it is the least at which queries of the sample find RECALL of their true neighbours in the sample.
Neighbours among more vectors are nearer, and nearer ones are met earlier, so the share errs on the side of a higher recall.
Vectors in clusters need a small share; vectors without any structure need about half of all, whatever the index.

The walk needs the cell sizes only (the square of the centroids in numbers). Queries travel to the first-half lists that
they visit. A list is split into blocks of at most BLOCK_ROWS rows, so one that holds a third of all vectors is many tasks,
and the queries of a block into chunks of about CHUNK_QUERIES, so a task holds a bounded number of both.

Vectors that are null, zero, of another dimension than most of the sample, or that hold a null or non-finite component take
no part. Rows with equal ids count as one entry if their vectors are equal. Queries whose cells hold fewer than k entries
walk on until they have k, or all. An empty table gives an empty result.
"""

from __future__ import annotations

import heapq
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzyfeat.session import materialise, prepare

SAMPLE, BLOCK_ROWS, CHUNK_QUERIES = 8192, 4096, 32_768
LEAST_CENTROIDS, MOST_CENTROIDS = 32, 256
RECALL, TRIED = 0.95, 256


def usable(vector: Column) -> Column:
    """Neither null nor zero, and all components finite."""
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return vector.isNotNull() & F.coalesce(finite, F.lit(False)) & F.coalesce(F.exists(vector, lambda x: x != 0), F.lit(False))


def codebook(points: np.ndarray, k: int, rounds: int = 12, seed: int = 1) -> np.ndarray:
    """k-means centroids of the distinct points; fewer points than k are their own centroids."""
    points = np.unique(points, axis=0)
    g = np.random.default_rng(seed)
    centroids = points[g.permutation(len(points))[:k]].copy()
    for _ in range(rounds):
        nearest = np.argmin((centroids**2).sum(1) - 2 * points @ centroids.T, axis=1)
        for j in range(len(centroids)):
            own = points[nearest == j]
            if len(own):
                centroids[j] = own.mean(axis=0)
    return centroids


def cells_of(vectors: np.ndarray, books: tuple[np.ndarray, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    half = books[0].shape[1]
    return tuple(np.argmin((b**2).sum(1) - 2 * x @ b.T, axis=1) for x, b in ((vectors[:, :half], books[0]), (vectors[:, half:], books[1])))


def centroids_for(n: int) -> int:
    """Centroids of a half: a power of two that grows with the square root of the vectors, within bounds."""
    return int(2 ** np.clip(round(math.log2(max(n, 1)) / 2 - 4), math.log2(LEAST_CENTROIDS), math.log2(MOST_CENTROIDS)))


def needed_share(points: np.ndarray, books: tuple[np.ndarray, np.ndarray], k: int, recall: float = RECALL, tried: int = TRIED) -> float:
    """The least share of the points, in the order of the walk, that holds `recall` of the k nearest of `tried` queries among them."""
    half, queries = books[0].shape[1], points[:tried]
    a, b = cells_of(points, books)
    met = (queries[:, :half] @ books[0].T)[:, a] + (queries[:, half:] @ books[1].T)[:, b]
    true = queries @ points.T
    own = np.arange(len(queries))
    true[own, own] = met[own, own] = -np.inf
    k = min(k, len(points) - 1)
    if k <= 0:
        return 1.0
    near = np.argpartition(-true, k - 1, axis=1)[:, :k]
    place = (-met).argsort(axis=1, kind="stable").argsort(axis=1)
    depth = np.sort(np.take_along_axis(place, near, axis=1).reshape(-1))
    return float(min(1.0, (depth[math.ceil(recall * len(depth)) - 1] + 1) / len(points)))


def walk(first: np.ndarray, second: np.ndarray, sizes: np.ndarray, enough: float) -> list[tuple[int, int]]:
    """Pairs (i, j) in order of first[i] + second[j] until their sizes add up to `enough`: a heap holds the frontier of the sorted grid."""
    a, b = np.argsort(first, kind="stable"), np.argsort(second, kind="stable")
    heap, out, held = [(first[a[0]] + second[b[0]], 0, 0)], [], 0
    while heap and held < enough:
        _, i, j = heapq.heappop(heap)
        if sizes[a[i], b[j]]:
            out.append((int(a[i]), int(b[j])))
            held += sizes[a[i], b[j]]
        if j + 1 < len(b):
            heapq.heappush(heap, (first[a[i]] + second[b[j + 1]], i, j + 1))
        if j == 0 and i + 1 < len(a):
            heapq.heappush(heap, (first[a[i + 1]] + second[b[0]], i + 1, 0))
    return out


def nearest(vectors: DataFrame, query_of: Column, k: int = 20, id_col: str = "vec_id", vector_col: str = "embedding", centroids: int | None = None, probed: float | None = None, sample: int = SAMPLE) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest entries found for each row that query_of selects, its own id excepted.

    centroids, probed: of each half, and the share of the vectors to meet; None: by the number of vectors, and as measured.
    """
    spark = prepare(vectors.sparkSession)
    centroids = centroids or centroids_for(vectors.count())
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v"), query_of.alias("q")).filter(F.col("vec_id").isNotNull() & usable(F.col("v")))
    rows = rows.dropDuplicates(["vec_id", "v"])
    ids = rows.select("vec_id").orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample).distinct()  # tasks send ids, not vectors
    some = rows.join(F.broadcast(ids), "vec_id").limit(2 * sample).collect()
    some.sort(key=lambda r: (r["vec_id"], r["v"]))
    schema = "query_id long, rank int, vec_id long, score double"
    if not some:
        return spark.createDataFrame([], schema)
    widths = [len(r["v"]) for r in some]
    dim = max(set(widths), key=lambda d: (widths.count(d), -d))
    rows = rows.filter(F.size("v") == dim)
    points = np.array([r["v"] for r in some if len(r["v"]) == dim])
    half = max(1, dim // 2)
    books = (codebook(points[:, :half], centroids), codebook(points[:, half:], centroids) if dim > half else np.zeros((1, 0)))
    probed = needed_share(points, books, k) if probed is None else probed
    shared = spark.sparkContext.broadcast(books)

    def index(batches):
        for batch in batches:
            for at in range(0, len(batch), 8192):
                part = batch.slice(at, 8192)
                x = np.asarray(part.column(1).flatten(), np.float64).reshape(-1, dim)
                a, b = cells_of(x, shared.value)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(a.astype(np.int32)), pa.array(b.astype(np.int32))], [*part.schema.names, "a", "b"])

    entries = materialise(rows.mapInArrow(index, "vec_id long, v array<double>, q boolean, a int, b int"))
    sizes = np.zeros((len(books[0]), len(books[1])), np.int64)
    for r in entries.groupBy("a", "b").count().collect():  # centroids ** 2 rows at most
        sizes[r["a"], r["b"]] = r["count"]
    blocks = np.maximum(1, -(-sizes.sum(axis=1) // BLOCK_ROWS))
    enough = max(k + 1, math.ceil(probed * sizes.sum()))
    chunks = max(1, math.ceil(entries.filter("q").count() * probed / CHUNK_QUERIES))

    def route(batches):
        """A query for each block of each first-half list that it visits, with the second-half cells wanted there as bits."""
        for batch in batches:
            ids, vs, lists, numbers, bits = [], [], [], [], []
            for id_, v in zip(batch.column(0), batch.column(1), strict=True):
                x = np.asarray(v.values, np.float64)
                wanted: dict[int, np.ndarray] = {}
                for a, b in walk(-(shared.value[0] @ x[:half]), -(shared.value[1] @ x[half:]), sizes, enough):
                    wanted.setdefault(a, np.zeros(len(books[1]), bool))[b] = True
                for a, mask in wanted.items():
                    packed = np.packbits(mask).tobytes()
                    for block in range(blocks[a]):
                        ids.append(id_)
                        vs.append(v)
                        lists.append(a)
                        numbers.append(block)
                        bits.append(packed)
                if len(ids) > 2000:
                    yield rows_of(ids, vs, lists, numbers, bits)
                    ids, vs, lists, numbers, bits = [], [], [], [], []
            yield rows_of(ids, vs, lists, numbers, bits)

    def rows_of(ids, vs, lists, numbers, bits):
        return pa.RecordBatch.from_arrays(
            [pa.array([x.as_py() for x in ids], pa.int64()), pa.array([x.values.to_numpy() for x in vs], pa.list_(pa.float64())), pa.array(lists, pa.int32()), pa.array(numbers, pa.int32()), pa.array(bits, pa.binary())],
            ["query_id", "qv", "a", "block", "bits"],
        )

    def scan(key, left, right):
        """The best k of a block for each query that visits it. Inner products of equal vectors are equal, in whatever order they come."""
        out = [[], [], []]
        if len(left) and len(right):
            x = np.asarray(left.column("v").combine_chunks().flatten(), np.float64).reshape(-1, dim)
            ids, b = left.column("vec_id").to_numpy(), left.column("b").to_numpy()
            for at in range(0, len(right), 256):
                part = right.slice(at, 256)
                queries = np.asarray(part.column("qv").combine_chunks().flatten(), np.float64).reshape(-1, dim)
                masks = np.unpackbits(np.frombuffer(b"".join(y.as_py() for y in part.column("bits")), np.uint8).reshape(len(part), -1), axis=1).astype(bool)
                rough = queries @ x.T
                rough[~masks[:, b]] = -np.inf
                for i, query_id in enumerate(part.column("query_id").to_numpy()):
                    line = rough[i]
                    line[ids == query_id] = -np.inf
                    least = np.partition(line, len(line) - k)[len(line) - k] if len(line) > k else -np.inf
                    near = np.flatnonzero((line >= least - 1e-9 * (1 + abs(least))) & (line > -np.inf)) if least > -np.inf else np.flatnonzero(line > -np.inf)
                    exact = (x[near] * queries[i]).sum(axis=1)
                    best = np.lexsort((ids[near], -exact))[:k]
                    out[0] += [query_id] * len(best)
                    out[1] += ids[near][best].tolist()
                    out[2] += exact[best].tolist()
        return pa.table({"query_id": pa.array(out[0], pa.int64()), "vec_id": pa.array(out[1], pa.int64()), "score": pa.array(out[2], pa.float64())})

    of_list = F.array(*(F.lit(int(n)) for n in blocks))
    blocked = entries.select("vec_id", "v", "a", "b", F.pmod(F.xxhash64("vec_id"), F.get(of_list, F.col("a"))).cast("int").alias("block"))
    blocked = blocked.withColumn("chunk", F.explode(F.sequence(F.lit(0), F.lit(chunks - 1))) if chunks > 1 else F.lit(0))
    routed = entries.filter("q").select("vec_id", "v").mapInArrow(route, "query_id long, qv array<double>, a int, block int, bits binary")
    routed = routed.withColumn("chunk", F.pmod(F.xxhash64("query_id", F.lit(1)), F.lit(chunks)).cast("int"))
    found = blocked.groupBy("a", "block", "chunk").cogroup(routed.groupBy("a", "block", "chunk")).applyInArrow(scan, "query_id long, vec_id long, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
