"""Approximate nearest neighbours over learned partitions, by largest inner product.

Fit, on a bounded sample: the graph of each vector's nearest neighbours is cut into balanced parts, by halving along its
slowest eigenvector and swapping pairs that lower the cut; a small network then learns to name the parts of a vector and
its neighbours. There are as many parts as give ``part_rows`` rows each, two at least, and one for every ``SAMPLE_PART``
sample vectors at most. Index: every vector goes to the network's most probable part. Search: a query goes to its most
probable parts and is scored exactly, in double precision, against all vectors there. How many parts a query visits is
measured on the whole table: ``probe_rows`` sample vectors, held out of the graph, are compared with every row, and the
fewest parts that hold ``target`` of their true neighbours are visited. A query whose parts hold fewer than ``k`` others
goes on to its next parts. On vectors without structure that is most of the parts; recall comes first.

Scale: the sample (``sample_rows``), the held-out vectors and the network are the only things of fixed size and the only
broadcast. Parts are cut into blocks of candidates that a worker holds, by a hash of the id; queries are sent to the blocks
of their parts and stream past them, so a candidate moves once for every ``QUERIES_A_BLOCK`` blocks' worth of queries and a
query once for every block. A part, or a vector with a third of all rows as copies, is as many tasks as it needs. Each
block keeps ``k`` per query before anything moves on. The query set against all rows, in blocks, is the stated search, not a
cross join.

Defined results: vectors that are null, zero, of another length than most, or hold null or non-finite components take no part,
as queries or candidates; a query never finds its own id; ties go to the smaller id; with fewer than ``k`` candidates all are
returned; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common


#: Sample vectors for each part, at least, bytes of a block of candidates, and blocks' worth of queries that stream past one.
SAMPLE_PART, BLOCK_BYTES, QUERIES_A_BLOCK = 64, 32 << 20, 4
RESULT = "query_id bigint, rank int, vec_id bigint, score double"


@dataclass
class Router:
    """Network weights and number of parts."""

    weights: list[np.ndarray]
    parts: int

    def scores(self, x: np.ndarray) -> np.ndarray:
        w1, b1, w2, b2 = self.weights
        return np.maximum(x @ w1 + b1, 0) @ w2 + b2

    def ranked(self, x: np.ndarray) -> np.ndarray:
        """All parts, most probable first."""
        return np.argsort(-self.scores(x), axis=1, kind="stable")


@dataclass
class PartitionIndex:
    """``rows``: id, v, asks, part of every usable vector. ``counts``: rows of each part. ``probes``: parts a query visits,
    which hold the share ``recall`` of the true neighbours of the held-out vectors."""

    rows: DataFrame
    router: Router
    counts: np.ndarray
    length: int
    probes: int
    recall: float


def neighbour_lists(x: np.ndarray, k: int) -> np.ndarray:
    s = x @ x.T
    np.fill_diagonal(s, -np.inf)
    return np.argpartition(-s, min(k, len(x) - 1), axis=1)[:, : min(k, len(x) - 1)]


def halve(links: np.ndarray, seed: int) -> np.ndarray:
    """Balanced two-way cut of a symmetric 0/1 matrix: True for one half."""
    n = len(links)
    degree = np.maximum(links.sum(1), 1e-9)
    root = np.sqrt(degree)
    first = root / np.linalg.norm(root)
    v = np.random.default_rng(seed).normal(size=n)
    for _ in range(60):  # second eigenvector of the normalised links
        v -= first * (first @ v)
        v = (links @ (v / root)) / root + v
        v /= np.linalg.norm(v) + 1e-12
    side = np.zeros(n, bool)
    side[np.argsort(v / root, kind="stable")[n // 2 :]] = True
    for _ in range(10):  # swap the pairs that gain most
        to_true = links @ side
        gain = np.where(side, degree - 2 * to_true, 2 * to_true - degree)
        a = np.flatnonzero(side)[np.argsort(-gain[side], kind="stable")]
        b = np.flatnonzero(~side)[np.argsort(-gain[~side], kind="stable")]
        m = min(len(a), len(b), max(1, n // 50))
        good = gain[a[:m]] + gain[b[:m]] - 2 * links[a[:m], b[:m]] > 0
        if not good.any():
            break
        a, b, before = a[:m][good], b[:m][good], side.copy()
        side[a], side[b] = False, True
        if side @ links @ ~side >= before @ links @ ~before:
            side = before
            break
    return side


def cut(links: np.ndarray, parts: int, seed: int = 0) -> np.ndarray:
    """Part of each node, by repeated halving; ``parts`` is a power of two."""
    out = np.zeros(len(links), int)
    step = parts
    while step > 1:
        for p in range(0, parts, step):
            own = np.flatnonzero(out == p)
            if len(own) > 1:
                out[own[halve(links[np.ix_(own, own)], seed + p)]] = p + step // 2
        step //= 2
    return out


def learn(x: np.ndarray, target: np.ndarray, hidden: int, seed: int, epochs: int = 80, batch: int = 128) -> list[np.ndarray]:
    """Adam on the cross entropy to soft targets."""
    rng = np.random.default_rng(seed)
    d, p = x.shape[1], target.shape[1]
    w = [rng.normal(size=(d, hidden)) * np.sqrt(2 / d), np.zeros(hidden), rng.normal(size=(hidden, p)) * np.sqrt(2 / hidden), np.zeros(p)]
    m, s, t = [np.zeros_like(a) for a in w], [np.zeros_like(a) for a in w], 0
    for _ in range(epochs):
        order = rng.permutation(len(x))
        for at in range(0, len(x), batch):
            b = order[at : at + batch]
            h = np.maximum(x[b] @ w[0] + w[1], 0)
            z = h @ w[2] + w[3]
            q = np.exp(z - z.max(1, keepdims=True))
            g = (q / q.sum(1, keepdims=True) - target[b]) / len(b)
            gh = (g @ w[2].T) * (h > 0)
            t += 1
            for i, grad in enumerate((x[b].T @ gh, gh.sum(0), h.T @ g, g.sum(0))):
                grad = grad + 1e-4 * w[i]
                m[i] = 0.9 * m[i] + 0.1 * grad
                s[i] = 0.999 * s[i] + 0.001 * grad**2
                w[i] = w[i] - 3e-3 * (m[i] / (1 - 0.9**t)) / (np.sqrt(s[i] / (1 - 0.999**t)) + 1e-8)
    return w


def parts_for(rows: int, sample: int, part_rows: int) -> int:
    """A power of two."""
    wanted = 2 ** round(math.log2(max(2, rows / part_rows)))
    return max(2, min(wanted, 2 ** int(math.log2(max(2, sample / SAMPLE_PART)))))


def fit(sample: np.ndarray, parts: int, neighbours: int = 10, hidden: int = 64, seed: int = 5) -> Router:
    """``sample``: distinct vectors."""
    near = neighbour_lists(sample, neighbours)
    links = np.zeros((len(sample), len(sample)), np.float32)
    links[np.arange(len(sample))[:, None], near] = 1
    links = np.maximum(links, links.T)
    own = np.eye(parts)[cut(links, parts, seed)]
    around = own[near].mean(1) if near.shape[1] else own
    return Router(learn(sample, 0.5 * own + 0.5 * around, hidden, seed), parts)


def usable(c: Column, length: int | None = None) -> Column:
    ok = c.isNotNull() & (F.size(c) > 0) & F.forall(c, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(c, lambda x: x != 0)
    return F.coalesce(ok & (F.size(c) == length) if length else ok, F.lit(False))


def matrix(column: pa.Array) -> np.ndarray:
    values = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(len(column), -1) if len(column) else values.reshape(0, 1)


def nearest(qid: np.ndarray, q: np.ndarray, cid: np.ndarray, c: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Place of the query, place of the candidate and score of each query's ``k`` best, in order. A matrix product finds what may be
    among them; its score is then the plain sum."""
    s = q @ c.T
    s[qid[:, None] == cid[None, :]] = -np.inf
    scale = np.linalg.norm(q, axis=1) * np.linalg.norm(c, axis=1).max() * 1e-12
    kth = np.partition(s, len(cid) - k, axis=1)[:, len(cid) - k] if len(cid) > k else np.full(len(qid), -np.inf)
    r, at = np.nonzero((s >= (kth - scale)[:, None]) & (s > -np.inf))
    exact = np.concatenate([np.empty(0), *((q[r[i : i + 65536]] * c[at[i : i + 65536]]).sum(1) for i in range(0, len(r), 65536))])
    order = np.lexsort((cid[at], -exact, r))
    r, at, exact = r[order], at[order], exact[order]
    keep = np.arange(len(r)) - np.searchsorted(r, r) < k
    return r[keep], at[keep], exact[keep]


def probes_needed(rows: DataFrame, router: Router, ids: np.ndarray, held: np.ndarray, k: int, target: float) -> tuple[int, float]:
    """Parts to visit, and the share of true neighbours in them: ``held`` vectors against every row. Each task keeps ``k`` of each."""
    if not len(held):
        return router.parts, 1.0

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: list[np.ndarray] = [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0)]  # query, id, part, score
        for b in batches:
            for at in range(0, b.num_rows, 4096):
                piece = b.slice(at, 4096)
                cid = piece.column(0).to_numpy()
                r, c, score = nearest(ids, held, cid, matrix(piece.column(1)), k)
                found = [np.concatenate(x) for x in zip(best, (r, cid[c], piece.column(2).to_numpy()[c], score), strict=True)]
                order = np.lexsort((found[1], -found[3], found[0]))
                found = [x[order] for x in found]
                keep = np.arange(len(order)) - np.searchsorted(found[0], found[0]) < k
                best = [x[keep] for x in found]
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in best], names=["q", "id", "part", "score"])

    found = rows.select("id", "v", F.col("part").cast("long")).mapInArrow(run, "q bigint, id bigint, part bigint, score double")
    order = Window.partitionBy("q").orderBy(F.desc("score"), "id")
    true = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("q", "part").toArrow()
    place = np.argsort(router.ranked(held), axis=1)
    down = place[true["q"].to_numpy(), true["part"].to_numpy()]  # how far down the query's list each true neighbour lives
    for probes in range(1, router.parts + 1):
        recall = float((down < probes).mean()) if len(down) else 1.0
        if recall >= target:
            break
    return probes, recall


def index(vectors: DataFrame, queries: Column, id_col: str = "vec_id", vector: str = "embedding", k: int = 20, part_rows: int = 128, target: float = 0.96, sample_rows: int = 4096, probe_rows: int = 400) -> PartitionIndex | None:
    """Fit, deal every usable vector to its part, and measure how many parts to visit. None without usable vectors.
    ``queries``: condition on the rows that are queries."""
    own = vectors.where(F.col(f"`{id_col}`").isNotNull())
    plain = own.select(F.col(f"`{id_col}`").cast("long").alias("id"), F.col(f"`{vector}`").cast("array<double>").alias("v"), queries.alias("asks"))
    plain = plain.where(usable(F.col("v")))
    drawn = plain.orderBy(F.xxhash64("id"), "id").limit(sample_rows).select("id", "v").collect()
    if not drawn:
        return None
    lengths = sorted(len(r["v"]) for r in drawn)
    length = max(set(lengths), key=lengths.count)
    drawn = [r for r in drawn if len(r["v"]) == length]
    plain = plain.where(F.size("v") == length)
    held = drawn[: min(probe_rows, len(drawn) // 10)]
    x = np.array([r["v"] for r in drawn[len(held) :]])
    router = fit(x[np.sort(np.unique(x, axis=0, return_index=True)[1])], parts_for(own.count(), len(x), part_rows))

    def route(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(router.scores(matrix(b.column(1))).argmax(1), pa.int32())], names=["id", "v", "asks", "part"])

    rows = common.stored(plain.mapInArrow(route, "id bigint, v array<double>, asks boolean, part int"), "routed")
    counts = np.zeros(router.parts, np.int64)
    for r in rows.groupBy("part").count().collect():  # one row a part
        counts[r["part"]] = r["count"]
    probes, recall = probes_needed(rows, router, np.array([r["id"] for r in held], np.int64), np.array([r["v"] for r in held]), k, target)
    return PartitionIndex(rows, router, counts, length, probes, recall)


def search(found: PartitionIndex, k: int = 20, block_rows: int | None = None) -> DataFrame:
    """query_id, rank, vec_id, score: the ``k`` nearest of each row that asks."""
    spark, router, counts, probes = found.rows.sparkSession, found.router, found.counts, found.probes
    block_rows = block_rows or max(1, min(65536, BLOCK_BYTES // (8 * found.length)))

    def visit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                ranked = router.ranked(matrix(b.column(1)))
                enough = (np.cumsum(counts[ranked], axis=1) > k).argmax(1) + 1  # with itself
                enough[counts.sum() <= k] = router.parts
                visits = [own[: max(probes, n)].astype(np.int32) for own, n in zip(ranked, enough, strict=True)]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(visits, pa.list_(pa.int32()))], names=["id", "v", "parts"])

    asks = found.rows.where("asks").select("id", "v").mapInArrow(visit, "id bigint, v array<double>, parts array<int>")
    asks = common.stored(asks, "queries")
    asked = {r["p"]: r["n"] for r in asks.select(F.explode("parts").alias("p")).groupBy("p").agg(F.count("*").alias("n")).collect()}
    grid = {p: (-(-int(counts[p]) // block_rows), -(-n // (QUERIES_A_BLOCK * block_rows))) for p, n in asked.items() if counts[p]}
    if not grid:
        return spark.createDataFrame([], RESULT)
    blocks = lambda side: F.try_element_at(F.create_map(*(F.lit(x) for p, own in grid.items() for x in (p, own[side]))), F.col("p"))
    dealt = lambda side: F.pmod(F.xxhash64("id", F.lit(side)), blocks(side)).cast("int")
    every = lambda side: F.explode(F.sequence(F.lit(0), blocks(side) - 1))
    cands = found.rows.select("id", "v", F.col("part").alias("p")).where(blocks(0).isNotNull()).select("id", "v", "p", dealt(0).alias("cb"), every(1).alias("qb"), F.lit(0).alias("kind"))
    moved = asks.select("id", "v", F.explode("parts").alias("p")).where(blocks(0).isNotNull()).select("id", "v", "p", every(0).alias("cb"), dealt(1).alias("qb"), F.lit(1).alias("kind"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows come by block, its candidates first: they are held, and its queries stream past them."""
        here, held, block = None, [], None
        for b in batches:
            keys = np.column_stack([b.column(i).to_numpy() for i in range(2, 6)]) if b.num_rows else np.empty((0, 4))
            cuts = np.flatnonzero(np.r_[True, (keys[1:] != keys[:-1]).any(1), True]) if len(keys) else []
            for lo, hi in zip(cuts[:-1], cuts[1:], strict=True):
                if tuple(keys[lo, :3]) != here:
                    here, held, block = tuple(keys[lo, :3]), [], None
                ids, x = b.column(0).to_numpy()[lo:hi], matrix(b.column(1).slice(lo, hi - lo))
                if keys[lo, 3] == 0:
                    held.append((ids, x))
                    continue
                if not held:
                    continue
                if block is None:
                    block = tuple(np.concatenate(part) for part in zip(*held, strict=True))
                for at in range(0, len(ids), 64):
                    r, c, score = nearest(ids[at : at + 64], x[at : at + 64], *block, k)
                    yield pa.RecordBatch.from_arrays([pa.array(ids[at : at + 64][r]), pa.array(block[0][c]), pa.array(score)], names=["query_id", "vec_id", "score"])

    met = cands.unionByName(moved).repartition("p", "cb", "qb").sortWithinPartitions("p", "cb", "qb", "kind").select("id", "v", "p", "cb", "qb", "kind")
    out = met.mapInArrow(run, "query_id bigint, vec_id bigint, score double")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return out.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def neighbours(vectors: DataFrame, queries: Column, k: int = 20, **more) -> DataFrame:
    """Index and search in one. ``more``: as of ``index``."""
    found = index(vectors, queries, k=k, **more)
    return search(found, k) if found else vectors.sparkSession.createDataFrame([], RESULT)


def op7_learned_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 nearest of every vector whose id is divisible by 20, among all vectors."""
    return neighbours(common.table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), F.col("vec_id") % 20 == 0)
