"""Nearest neighbours by inner product with a forest of random-projection trees.

Every tree splits space by random hyperplanes: of a few random directions the one along
which a bounded sample spreads most, cut at the sample's median.  The depth follows the
number of rows.  Vectors get one extra component that lifts them onto a sphere, so the
largest inner product becomes the smallest angle.  All rows are filed under their leaf
in each tree.  A query opens leaves of all trees in one order, by the summed squares of
the margins crossed on the way, until they hold enough different vectors; the sample,
filed like the rows, tells how many.  Leaf candidates are then reranked with exact inner
products.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from .frames import Workspace, tidied
from .warc import _filesystem


@dataclass(frozen=True)
class Forest:
    """Hyperplanes of complete binary trees, node k having children 2k + 1 and 2k + 2."""

    normals: np.ndarray  # trees, nodes, dim + 1
    offsets: np.ndarray  # trees, nodes
    depth: int
    largest_norm: float
    sample: tuple[tuple[np.ndarray, ...], ...] = ()  # by tree and leaf: numbers of the sample's different vectors
    sample_size: int = 0

    def lifted(self, vectors: np.ndarray) -> np.ndarray:
        rest = np.sqrt(np.maximum(0.0, self.largest_norm**2 - (vectors * vectors).sum(axis=1)))
        return np.hstack([vectors, rest[:, None]])

    def leaves(self, vectors: np.ndarray) -> np.ndarray:
        """Leaf of every vector in every tree, as rows by trees."""
        lifted = self.lifted(vectors)
        out = np.empty((len(vectors), len(self.normals)), dtype=np.int64)
        for t in range(len(self.normals)):
            node = np.zeros(len(vectors), dtype=np.int64)
            for _ in range(self.depth):
                side = (lifted * self.normals[t][node]).sum(axis=1) > self.offsets[t][node]
                node = 2 * node + 1 + side
            out[:, t] = node - (2**self.depth - 1)
        return out

    def opened(self, queries: np.ndarray, share: float) -> np.ndarray:
        """Bits by leaf (of all trees in turn) and query: the leaves that its search opens.

        One queue over all trees, ordered by the summed squares of the margins crossed,
        opens leaves in the order of that sum until they hold a share of the sample's
        different vectors.  So it opens all leaves up to the sum at which the sample's
        vectors, each taken where it is nearest, make up that share.
        """
        places = np.empty((len(self.normals), self.sample_size), dtype=np.int64)
        for t, leaves in enumerate(self.sample):
            for leaf, members in enumerate(leaves):
                places[t, members] = leaf
        wanted = int(np.ceil(share * self.sample_size))
        out = []
        for low in range(0, len(queries), 256):
            part = queries[low : low + 256]
            lifted = np.hstack([part, np.zeros((len(part), 1))])
            scale = np.maximum(np.linalg.norm(part, axis=1, keepdims=True), 1e-300)
            sums, nearest_sum = [], np.full((len(part), self.sample_size), np.inf)
            for t in range(len(self.normals)):
                margins = lifted @ self.normals[t].T / scale - self.offsets[t] / self.largest_norm
                crossed = np.zeros((len(part), 1))
                for level in range(self.depth):
                    margin = margins[:, 2**level - 1 : 2 ** (level + 1) - 1]
                    square, right = margin * margin, margin > 0
                    crossed = np.stack([crossed + np.where(right, square, 0.0), crossed + np.where(right, 0.0, square)], axis=2).reshape(len(part), -1)
                sums.append(crossed)
                np.minimum(nearest_sum, crossed[:, places[t]], out=nearest_sum)
            most = np.full(len(part), np.inf) if share >= 1 or wanted < 1 else np.partition(nearest_sum, wanted - 1, axis=1)[:, wanted - 1]
            out.append(np.packbits((np.hstack(sums) <= most[:, None]).T, axis=1))
        return np.hstack(out)


def usable(df: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(vec_id, v) of the vectors that take part.

    Left out: null ids; vectors that are null, empty or zero or hold null or
    non-finite components; vectors of another length than the most frequent one.
    """
    fine = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    v = F.col("v")
    rows = df.select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector_col, lambda x: x.cast("double")).alias("v"))
    rows = rows.where(F.col("vec_id").isNotNull() & v.isNotNull() & F.forall(v, fine) & F.exists(v, lambda x: x != 0))
    first = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).first()
    return rows.where(F.size("v") == (first["n"] if first else 0))


def _matrix(column) -> np.ndarray:
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(len(column), -1) if len(column) else np.zeros((0, 0))


def fit_forest(vectors: DataFrame, rows: int, *, trees: int = 4, leaf_rows: int = 160, deepest: int = 12, directions: int = 4, sample_rows: int = 16384, seed: int = 7) -> Forest | None:
    """A forest for ``rows`` vectors, fitted on at most ``sample_rows`` of them, taken by a hash of the id.

    The depth leaves about ``leaf_rows`` rows in a leaf, up to ``deepest`` levels, which
    bound what every task is sent.
    """
    largest = vectors.agg(F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x))).first()[0]
    if largest is None:
        return None
    sample = vectors.orderBy(F.xxhash64("vec_id"), "vec_id").limit(sample_rows).select("v").toArrow().column("v").combine_chunks()
    points = np.unique(_matrix(sample), axis=0)
    depth = int(np.clip(round(np.log2(max(rows, 1) / leaf_rows)), 1, deepest))
    rng = np.random.default_rng(seed)
    nodes = 2**depth - 1
    normals, offsets = np.zeros((trees, nodes, points.shape[1] + 1)), np.zeros((trees, nodes))
    forest = Forest(normals, offsets, depth, float(np.sqrt(largest)))
    lifted, filed = forest.lifted(points), []
    for t in range(trees):
        members = {0: np.arange(len(lifted))}
        for node in range(nodes):
            own = members.pop(node)
            tried = rng.normal(size=(directions, lifted.shape[1]))
            tried /= np.linalg.norm(tried, axis=1, keepdims=True)
            at = lifted[own] @ tried.T
            best = int(np.argmax(at.std(axis=0))) if len(own) else 0
            normals[t, node], offsets[t, node] = tried[best], np.median(at[:, best]) if len(own) else 0.0
            right = at[:, best] > offsets[t, node]
            members[2 * node + 1], members[2 * node + 2] = own[~right], own[right]
        filed.append(tuple(members[nodes + leaf] for leaf in range(2**depth)))
    return Forest(normals, offsets, depth, forest.largest_norm, tuple(filed), len(points))


_INDEX = "vec_id long, v binary, leaves binary"


def _file_rows(vectors: DataFrame, forest: Forest, width: str) -> DataFrame:
    """The index: every vector once, in the width that its table has (which loses nothing), with its leaf in each tree."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                points = _matrix(batch.column(1))
                cells = [pa.array([r.tobytes() for r in x], pa.binary()) for x in (points.astype(width), forest.leaves(points).astype("<i4"))]
                yield pa.RecordBatch.from_arrays([batch.column(0), *cells], names=["vec_id", "v", "leaves"])

    return vectors.select("vec_id", "v").mapInArrow(run, _INDEX)


def _read_index(folder: str, rows: int, dim: int, trees: int, width: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, vectors, leaves) of the whole index, about ``rows`` at a time."""
    fs, base = _filesystem(folder)
    held: list[pa.RecordBatch] = []

    def block() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        whole = pa.Table.from_batches(held)
        flat = lambda name, kind, n: np.frombuffer(b"".join(whole.column(name).to_pylist()), dtype=kind).reshape(-1, n)
        return whole.column("vec_id").to_numpy(), flat("v", width, dim), flat("leaves", "<i4", trees)

    for info in sorted(fs.get_file_info(pafs.FileSelector(base)), key=lambda i: i.path):
        if info.base_name.startswith(("_", ".")):
            continue
        with fs.open_input_file(info.path) as file:
            for batch in pq.ParquetFile(file, buffer_size=1 << 20).iter_batches(batch_size=rows, columns=["vec_id", "v", "leaves"]):
                held.append(batch)
                if sum(b.num_rows for b in held) >= rows:
                    yield block()
                    held = []
    if held and sum(b.num_rows for b in held):
        yield block()


def _best(query: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The k best rows of each query, every id once with its best score, ties to smaller ids."""
    order = np.lexsort((-scores, ids, query))
    query, ids, scores = query[order], ids[order], scores[order]
    once = np.ones(len(ids), dtype=bool)
    once[1:] = (ids[1:] != ids[:-1]) | (query[1:] != query[:-1])
    query, ids, scores = query[once], ids[once], scores[once]
    order = np.lexsort((ids, -scores, query))
    query, ids, scores = query[order], ids[order], scores[order]
    place = np.arange(len(query)) - np.searchsorted(query, query)
    return query[place < k], ids[place < k], scores[place < k]


def _least_copies(points: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Numbers of the rows without those that k + 1 equal vectors with other, smaller ids keep out of every answer."""
    raw = np.ascontiguousarray(points).view(np.uint8).reshape(len(points), -1).view("<u4").astype(np.uint64)
    with np.errstate(over="ignore"):
        code = (raw * np.random.default_rng(1).integers(1, 2**63, raw.shape[1], dtype=np.uint64)).sum(axis=1)
    _, group, size = np.unique(code, return_inverse=True, return_counts=True)
    crowded = size[group] > k + 1
    many = np.flatnonzero(crowded)
    if not len(many):
        return np.arange(len(points))
    whole = np.ascontiguousarray(points[many])
    same = np.unique(whole.view(np.dtype((np.void, whole.itemsize * whole.shape[1]))).ravel(), return_inverse=True)[1].ravel()
    order = np.lexsort((ids[many], same))
    group, own = same[order], ids[many][order]
    once = np.ones(len(order), dtype=bool)
    once[1:] = (group[1:] != group[:-1]) | (own[1:] != own[:-1])
    order, group = order[once], group[once]
    place = np.arange(len(order)) - np.searchsorted(group, group)
    return np.sort(np.concatenate([np.flatnonzero(~crowded), many[order[place <= k]]]))


def _scan(index: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]], forest: Forest, asked: np.ndarray, wants: np.ndarray, share: float, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(query's number, id, score) of the k best rows of each query in the leaves that it opens.

    Leaf by leaf, a block's rows meet the queries that open the leaf; what may be among a
    query's k is scored exactly.
    """
    opened, leaves = forest.opened(wants, share), 2**forest.depth
    least = np.full(len(asked), -np.inf)
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
    size = 0

    def best() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return _best(*(np.concatenate([h[i] for h in held]) for i in range(3)), k)

    # bits by leaf are padded where a part has no whole bytes; only the last part may
    at_query = [np.flatnonzero(np.unpackbits(row, count=len(asked))).astype(np.int32) for row in opened]
    del opened
    for ids, points, places in index:
        stays = _least_copies(points, ids, k)
        ids, points, places = ids[stays], points[stays], places[stays]
        for t in range(places.shape[1]):
            order = np.argsort(places[:, t], kind="stable")
            found, starts = np.unique(places[order, t], return_index=True)
            for leaf, members in zip(found.tolist(), np.split(order, starts[1:]), strict=True):
                queries = at_query[t * leaves + leaf]
                step = max(1, (1 << 21) // len(members))
                own, mine = points[members].astype(np.float64), ids[members]
                for low in range(0, len(queries), step):
                    q = queries[low : low + step]
                    rough = wants[q] @ own.T
                    # matrix products round by position; keep all that may be among the k, and multiply those anew
                    slack = 1e-9 * np.maximum(1.0, np.abs(rough).max(axis=1))
                    bound = least[q]
                    if len(members) > k + 1:
                        bound = np.maximum(bound, np.partition(rough, -k - 1, axis=1)[:, -k - 1])
                    row, col = np.nonzero(rough >= (bound - slack)[:, None])
                    for a in range(0, len(row), 1 << 15):
                        i, j = row[a : a + (1 << 15)], col[a : a + (1 << 15)]
                        other = mine[j] != asked[q[i]]
                        i, j = i[other], j[other]
                        held.append((q[i], mine[j], (own[j] * wants[q[i]]).sum(axis=1)))
                        size += len(i)
                    if size > 400_000:
                        held = [best()]
                        number, _, score = held[0]
                        size = 0  # what is held is bounded by k a query
                        last = np.flatnonzero(np.bincount(number, minlength=len(asked)) == k)
                        least[last] = score[np.searchsorted(number, last, side="right") - 1]
    return best() if held else (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))


def opened_share(rows: int, scale: float, power: float) -> float:
    """The share of the different vectors that a query opens: scale * rows ** (power - 1), 1 at most."""
    return min(1.0, scale * max(rows, 1) ** (power - 1))


def nearest(df: DataFrame, queries: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", *, k: int = 20, open_scale: float = 1.85, open_power: float = 0.886, block_rows: int = 1 << 17, block_queries: int = 1 << 13, **forest_settings) -> DataFrame:
    """(query_id, rank, vec_id, score): the k rows of ``df`` found nearest to each query.

    A query opens leaves until they hold about ``open_scale * N ** open_power`` of N
    different vectors, whatever N is; copies of one vector count once.  A row with the
    query's id is its own and left out; rows that repeat an id count once, with their
    best score.  Scores are double inner products of the original vectors, ties go to
    the smaller id.  Vectors that are null, empty, zero or hold null or non-finite
    components take no part, nor do null ids; no usable vector or query gives no row.
    Other columns, whatever their names, are not read.

    Every row lies once in the index, in the folder that all machines share; a task holds
    ``block_queries`` queries and their best rows, and goes through the index in blocks
    of ``block_rows``.  So disk is the index, the queries and the answers, whatever
    number of leaves is opened.  Workers read through ``pyarrow.fs``.
    """
    kind = df.schema[vector_col].dataType.elementType
    width = "<f4" if isinstance(kind, T.FloatType) and queries.schema[vector_col].dataType.elementType == kind else "<f8"
    rows = usable(df, id_col, vector_col)
    total = rows.count()
    forest = fit_forest(rows, total, **forest_settings)
    schema = "query_id long, rank int, vec_id long, score double"
    if forest is None:
        return df.sparkSession.createDataFrame([], schema)
    dim, trees = forest.normals.shape[2] - 1, len(forest.normals)
    work = Workspace(df.sparkSession, "forest")
    work.keep(_file_rows(rows, forest, width), "index")
    folder, share = f"{work.base}/index", opened_share(total, open_scale, open_power)
    asking = usable(queries, id_col, vector_col).where(F.size("v") == dim)
    number = asking.count()
    parts = max(1, -(-number // block_queries), min(df.sparkSession.sparkContext.defaultParallelism, -(-number // 64)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def answers() -> pa.RecordBatch:
            asked, wants = np.concatenate([b.column(0).to_numpy() for b in held]), np.vstack([_matrix(b.column(1)) for b in held])
            at, ids, scores = _scan(_read_index(folder, block_rows, dim, trees, width), forest, asked, wants, share, k)
            return pa.RecordBatch.from_arrays([pa.array(asked[at]), pa.array(ids), pa.array(scores)], names=["query_id", "vec_id", "score"])

        for batch in batches:
            for low in range(0, batch.num_rows, block_queries):
                held.append(batch.slice(low, block_queries))
                if sum(b.num_rows for b in held) >= block_queries:
                    yield answers()
                    held = []
        if held:
            yield answers()

    found = asking.select("vec_id", "v").repartition(parts, "vec_id").mapInArrow(tidied(run), "query_id long, vec_id long, score double")
    # ids may repeat among the queries: the best answers of an id count
    once = found.repartition("query_id").groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return once.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
