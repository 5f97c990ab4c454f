"""Approximate nearest neighbours: robust-pruned directed graphs, one per shard, searched by beams.

Rows are dealt over shards of bounded size by a hash. In each shard, points join the graph in batches: a greedy beam
search from the entry point proposes neighbours, and relaxed distance pruning keeps those that no kept neighbour covers
(``ALPHA`` times nearer to the candidate than the point is); links back are pruned the same way. Every query then runs a
beam search in every shard, and the best of all shards are merged. Identical vectors are one graph point that carries
its k + 1 smallest ids, which is all a top-k can need, so a vector that a third of all rows share is no obstacle.

A task holds the points and graph of one shard at a time; queries stream past it in batches and are never gathered.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import cut, parts_for

SHARD_ROWS = 6_000
DEGREE, BEAM_BUILD, BEAM_SEARCH, ALPHA = 24, 40, 160, 1.2
BATCH = 256
#: Every how many ids one is a query.
QUERY_EVERY = 50
TOP = 5


def marked_usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding array<double>, good) of every row; good are those with an id and a vector that is not null, not zero and finite in all components."""
    v = F.col("embedding").cast("array<double>")
    good = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < float("inf")), F.lit(False))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col("vec_id").cast("long"), v.alias("embedding"), (F.coalesce(good, F.lit(False)) & F.col("vec_id").cast("long").isNotNull()).alias("good"))


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding array<double>) of the rows that take part."""
    return marked_usable(vectors).where("good").drop("good")


def beam_search(x: np.ndarray, links: np.ndarray, entry: int, queries: np.ndarray, beam: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and similarities of the ``beam`` best points met from the entry, best first, for a batch of queries; -1 pads.

    Each step expands every query's best point not yet expanded, until all points in its beam are.
    """
    n = len(queries)
    ids = np.full((n, beam), -1, np.int64)
    sims = np.full((n, beam), -np.inf, np.float32)
    done = np.ones((n, beam), bool)
    ids[:, 0], sims[:, 0], done[:, 0] = entry, queries @ x[entry], False
    seen = np.zeros((n, len(x)), bool)
    seen[:, entry] = True
    seen[:, -1] = True  # the extra row that absent links point at
    live = np.arange(n)
    while len(live):
        at = np.where(done[live], -np.inf, sims[live]).argmax(axis=1)
        done[live, at] = True
        near = links[ids[live, at]]
        fresh = ~seen[live[:, None], near]
        seen[live[:, None], near] = True
        got = np.einsum("qrd,qd->qr", x[near], queries[live])
        got[~fresh] = -np.inf
        all_sims = np.concatenate([sims[live], got], axis=1)
        order = np.argpartition(-all_sims, beam - 1, axis=1)[:, :beam]
        sims[live] = np.take_along_axis(all_sims, order, 1)
        ids[live] = np.take_along_axis(np.concatenate([ids[live], np.where(fresh, near, -1)], axis=1), order, 1)
        done[live] = np.take_along_axis(np.concatenate([done[live], ~fresh], axis=1), order, 1) | (sims[live] == -np.inf)
        live = live[~done[live].all(axis=1)]
    order = np.argsort(-sims, axis=1, kind="stable")
    return np.take_along_axis(ids, order, 1), np.take_along_axis(sims, order, 1)


def robust_prune(x: np.ndarray, points: np.ndarray, candidates: np.ndarray, degree: int, alpha: float) -> np.ndarray:
    """For each of ``points``, at most ``degree`` of its candidates (-1 pads): the nearest stays, and drops those it covers; and so on."""
    dist = lambda s: 2.0 - 2.0 * s  # noqa: E731  squared distance of unit vectors
    bad = (candidates < 0) | (candidates == points[:, None])
    y = x[np.where(bad, 0, candidates)]
    own = dist(np.einsum("pcd,pd->pc", y, x[points]))
    own[bad] = np.inf
    order = np.argsort(own, axis=1, kind="stable")
    candidates, own = np.take_along_axis(candidates, order, 1), np.take_along_axis(own, order, 1)
    y = np.take_along_axis(y, order[:, :, None], 1)
    between = dist(y @ y.transpose(0, 2, 1))
    alive = np.isfinite(own)
    # repeated candidates: only the first counts
    srt = np.sort(candidates, axis=1)
    if (srt[:, 1:] == srt[:, :-1]).any():
        same = candidates[:, :, None] == candidates[:, None, :]
        alive &= ~np.tril(same, -1).any(axis=2)
    out = np.full((len(points), degree), -1, np.int64)
    rows = np.arange(len(points))
    for k in range(degree):
        first = alive.argmax(axis=1)
        has = alive[rows, first]
        if not has.any():
            break
        out[has, k] = candidates[rows[has], first[has]]
        covered = alpha * between[rows, first] <= own
        alive &= ~covered
        alive[rows, first] = False
    return out


def build_graph(x: np.ndarray, degree: int = DEGREE, beam: int = BEAM_BUILD, alpha: float = ALPHA, seed: int = 3) -> tuple[np.ndarray, int]:
    """Links (points x degree; absent ones point at the extra row len(x), a zero vector appended by the caller) and the entry point."""
    n = len(x) - 1
    links = np.full((n + 1, degree), n, np.int64)
    entry = int((x[:n] @ x[:n].mean(axis=0)).argmax())
    order = np.random.default_rng(seed).permutation(n)
    order = np.concatenate([[entry], order[order != entry]])
    s, step = 1, 8
    while s < n:
        new = order[s : s + step]
        found, _ = beam_search(x, links, entry, x[new], beam)
        if len(new) > 1:  # points of one batch may be neighbours too
            found = np.concatenate([found, np.broadcast_to(new, (len(new), len(new)))[:, : min(len(new), 32)]], axis=1)
        kept = robust_prune(x, new, found, degree, alpha)
        links[new] = np.where(kept < 0, n, kept)
        back = np.stack([np.repeat(new, degree), kept.ravel()], axis=1)
        back = back[back[:, 1] >= 0]
        back = back[np.argsort(back[:, 1], kind="stable")]
        to, first, count = np.unique(back[:, 1], return_index=True, return_counts=True)
        most = int(count.max())
        extra = np.full((len(to), most), -1, np.int64)
        extra[np.repeat(np.arange(len(to)), count), np.arange(len(back)) - np.repeat(first, count)] = back[:, 0]
        old = np.where(links[to] == n, -1, links[to])
        room = (old < 0).sum(axis=1) >= count
        for t, e, c in zip(to[room], extra[room], count[room]):
            fresh = e[:c][~np.isin(e[:c], links[t])]  # points of one batch may have linked each other already
            links[t, np.flatnonzero(links[t] == n)[: len(fresh)]] = fresh
        if (~room).any():
            pruned = robust_prune(x, to[~room], np.concatenate([old[~room], extra[~room]], axis=1), degree, alpha)
            links[to[~room]] = np.where(pruned < 0, n, pruned)
        s, step = s + len(new), min(BATCH, 2 * step)
    return links, entry


def _unit(vectors: pa.Array, dim: int) -> np.ndarray:
    raw = vectors.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)
    big = np.abs(raw).max(axis=1, keepdims=True)
    scaled = raw / big
    return scaled / np.sqrt((scaled * scaled).sum(axis=1, keepdims=True))


def search(vectors: DataFrame, every: int = QUERY_EVERY, k: int = TOP, shard_rows: int = SHARD_ROWS, beam: int = BEAM_SEARCH) -> DataFrame:
    """The k nearest found of each query (ids divisible by ``every``): query_id, rank, vec_id, score (cosine in double precision).

    A row is never its own neighbour; ties go to the smaller id. Vectors that are null, zero, or hold null or non-finite
    components take no part, as queries or candidates. With fewer than k candidates, all are returned if the beams meet them.
    Repeated rows (same id and vector) count once.
    """
    good = usable(vectors).distinct()
    # copies: the k + 1 smallest ids of each distinct vector; the limit of a rank is applied before the shuffle as well
    copies = good.withColumn("h", F.xxhash64("embedding"))
    few = copies.withColumn("at", F.row_number().over(Window.partitionBy("h", "embedding").orderBy("vec_id"))).where(F.col("at") <= k + 1)
    points = few.groupBy("embedding").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))
    points = cut(points)
    shards = parts_for(points.count(), shard_rows)
    points = points.withColumn("shard", F.pmod(F.xxhash64("embedding"), F.lit(shards)))
    queries = good.where(F.pmod("vec_id", F.lit(every)) == 0).select(F.col("vec_id").alias("query_id"), "embedding")
    asked = queries.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1)))).withColumn("shard", F.col("shard").cast("long"))
    both = points.select("shard", F.lit(None).cast("long").alias("query_id"), "embedding", "ids").union(asked.select("shard", "query_id", "embedding", F.lit(None).cast("array<long>").alias("ids")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, held, graphs = None, [], None
        for batch in batches:
            own = batch.column("shard").to_numpy()
            for x in np.unique(own):
                part = batch.filter(pa.array(own == x))
                if x != shard:
                    shard, held, graphs = x, [], None
                asks = part.column("query_id").is_valid()
                held.append(part.filter(pc.invert(asks)))
                part = part.filter(asks)
                if len(part):  # the shard's points come first; its queries then pass by
                    graphs = _graphs(pa.Table.from_batches(held)) if graphs is None else graphs
                    yield from _ask(graphs, part, k, beam)

    found = both.repartition(max(shards, 1), "shard").sortWithinPartitions("shard", "query_id").mapInArrow(run, "query_id long, vec_id long, score double")
    nearest = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")  # every shard's k best; ranked before the shuffle, then again
    top = found.withColumn("rank", F.row_number().over(nearest)).where(F.col("rank") <= k)
    return top.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _graphs(points: pa.Table) -> dict[int, tuple]:
    """A graph for each vector length of a shard: ids, unit vectors, links, entry."""
    out = {}
    if len(points):
        dims = np.diff(points.column("embedding").combine_chunks().offsets.to_numpy())
        for dim in np.unique(dims).tolist():  # vectors of different lengths have no cosine
            p = points.filter(pa.array(dims == dim))
            unit = _unit(p.column("embedding").combine_chunks(), dim)
            x = np.concatenate([unit, np.zeros((1, dim))]).astype(np.float32)
            out[dim] = (p.column("ids").to_pylist(), unit, x, *build_graph(x))
    return out


def _ask(graphs: dict[int, tuple], queries: pa.RecordBatch, k: int, beam: int) -> Iterator[pa.RecordBatch]:
    lengths = np.diff(queries.column("embedding").offsets.to_numpy())
    for dim, (ids, unit, x, links, entry) in graphs.items():
        q = queries.filter(pa.array(lengths == dim))
        for s in range(0, len(q), BATCH):
            asked, own = q.slice(s, BATCH), q.column("query_id").slice(s, BATCH).to_pylist()
            part = _unit(asked.column("embedding"), dim)
            near, _ = beam_search(x, links, entry, part.astype(np.float32), min(beam, len(unit)))
            near = near[:, : 4 * k]
            score = np.einsum("qcd,qd->qc", unit[np.maximum(near, 0)], part)
            out: list[tuple] = []
            for i, mine in enumerate(own):
                best = sorted((-float(c), v) for c, j in zip(score[i], near[i]) if j >= 0 for v in ids[j] if v != mine)[:k]
                out += [(mine, v, -c) for c, v in best]
            if out:
                a, b, c = zip(*out)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64()), pa.array(c, pa.float64())], names=["query_id", "vec_id", "score"])
