"""Near-duplicate embeddings by NN-descent over a neighbour graph of balls.

Equal vectors are one point. Points within ``BALL`` degrees of a leader form a ball: any two of them are within the
threshold's angle, so they are linked without a test, and a group of near copies costs a few balls whatever its size.
NN-descent runs over the leaders: a start graph from random-hyperplane buckets, then rounds in which all neighbours and
reverse neighbours of a leader meet and propose each other. A list keeps its ``LIST`` nearest leaders and, where they do
not suffice (a saturated list), every further one whose ball may reach over. An audit takes blocks of leaders, by hash,
until brute force has found ``EDGES`` true edges of theirs or no leader is left; its edges join the graph, so it is exact
where the audit takes in all. Rounds go on, each with more hash tables, until the graph had ``CONTENT`` of the audit's
edges of itself; after ``MOST_ROUNDS`` all leaders that are left are compared exactly, block by block. Threshold edges
between balls are then counted exactly: by the triangle inequality where it decides, by cosines of members where it does not.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import components, cut, parts_for, runs
from .ann import marked_usable

COSINE = 0.95
#: Radius of a ball in degrees: twice that is below arccos(COSINE).
BALL = 9.0
LIST, TABLES, BLOCK, MOST_ROUNDS, CONTENT = 6, 4, 400, 4, 0.995
#: Leaders of one block of the audit, and the true edges it must have seen.
AUDIT, EDGES = 4096, 4000
#: Members of one neighbourhood that meet in one task.
MEET = 192
_ANGLE = math.acos(COSINE)
_EPS = 1e-7


def _matrix(column: pa.ChunkedArray | pa.Array, kind=np.float64) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(column), -1).astype(kind)


def _buckets(points: DataFrame, count: int, table: int, block: int) -> DataFrame:
    """``points`` (id, unit, ...) with bucket, part: signs of random projections; buckets too large for one block are dealt into parts by a hash."""
    bits = max(0, math.ceil(math.log2(max(1, 2 * count / block))))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = _matrix(b.column("unit"))
            planes = np.random.default_rng(1000 + table).standard_normal((x.shape[1], bits)) if len(b) else None
            code = ((x @ planes) > 0) @ (1 << np.arange(bits)) if bits and len(b) else np.zeros(len(b), np.int64)
            yield b.append_column("bucket", pa.array(code.astype(np.int64)))

    kept = ", ".join(f"{c} {t}" for c, t in points.dtypes)
    coded = points.mapInArrow(sign, f"{kept}, bucket long")
    sizes = coded.groupBy("bucket").agg(F.ceil(F.count("*") / block).alias("n"))
    return coded.join(sizes, "bucket").withColumn("part", F.pmod(F.xxhash64("id", F.lit(table)), "n")).drop("n")


def _grouped(rows: DataFrame, keys: list[str], work, schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in runs(batches, keys):
            yield from work(group).to_batches()

    return rows.repartition(*keys).sortWithinPartitions(*keys, "id").mapInArrow(run, schema)


def _cover(group: pa.Table) -> pa.Table:
    """Greedy leaders of one block: in id order, each uncovered point leads all uncovered points within ``BALL``."""
    x = _matrix(group.column("unit"))
    ids = group.column("id").to_numpy()
    near = x @ x.T >= math.cos(math.radians(BALL))
    free, lead = np.ones(len(x), bool), np.zeros(len(x), np.int64)
    for i in range(len(x)):
        if free[i]:
            mine = near[i] & free
            mine[i] = True
            lead[mine] = i
            free[mine] = False
    angle = np.arccos(np.clip((x * x[lead]).sum(axis=1), -1, 1))
    angle[lead == np.arange(len(x))] = 0.0
    return group.select(["id", "unit", "mult"]).append_column("ball", pa.array(ids[lead])).append_column("angle", pa.array(angle))


def _propose(group: pa.Table) -> pa.Table:
    """Of the members of one meeting: each one's best partners here that beat what it has, and all whose balls may reach over."""
    x = _matrix(group.column("unit"), np.float32)
    ids, r = group.column("id").to_numpy(), group.column("radius").to_numpy()
    worst = group.column("worst").to_numpy()
    s = (x @ x.T).astype(np.float64)
    s[ids[:, None] == ids[None]] = -2.0
    wide = s >= np.cos(np.minimum(np.pi, _ANGLE + r[:, None] + r[None] + 1e-4))
    keep = wide.copy()
    k = min(LIST, len(ids) - 1)
    if k > 0:
        best = np.argpartition(-s, k - 1, axis=1)[:, :k]
        rows = np.arange(len(ids))[:, None]
        keep[rows, best] |= s[rows, best] > worst[:, None]
    keep &= s > -2.0
    a, b = np.nonzero(keep)
    return pa.table({"u": ids[a], "v": ids[b], "s": s[a, b], "wide": wide[a, b]})


_EDGES = "u long, v long, s double, wide boolean"


def _lists(edges: DataFrame) -> DataFrame:
    """The graph from proposals: per leader its ``LIST`` nearest, and all wide ones (lists that are saturated grow)."""
    once = edges.groupBy("u", "v").agg(F.max("s").alias("s"), F.max("wide").alias("wide"))
    deal = once.where("NOT wide").groupBy("u").agg(F.slice(F.sort_array(F.collect_list(F.struct("s", "v")), asc=False), 1, LIST).alias("x"))
    near = deal.select("u", F.explode("x").alias("x")).select("u", "x.v", "x.s", F.lit(False).alias("wide"))
    return cut(once.where("wide").select("u", "v", "s", "wide").union(near))


def _meet(graph: DataFrame, leaders: DataFrame) -> DataFrame:
    """One round's meetings: for each leader u, itself, its neighbours and its reverse neighbours, in parts of bounded size."""
    both = graph.select("u", "v").union(graph.select(F.col("v").alias("u"), F.col("u").alias("v"))).union(leaders.select(F.col("id").alias("u"), F.col("id").alias("v"))).distinct()
    size = both.groupBy("u").agg(F.ceil(F.count("*") / MEET).alias("n"))
    parts = both.join(size, "u").withColumn("part", F.pmod(F.xxhash64("u", "v"), "n")).select(F.col("u").alias("bucket"), "part", F.col("v").alias("id"))
    worst = graph.where("NOT wide").groupBy(F.col("u").alias("id")).agg(F.min("s").alias("worst"), F.count("*").alias("n"))
    known = leaders.join(worst, "id", "left").withColumn("worst", F.when(F.col("n") >= LIST, F.col("worst")).otherwise(-2.0)).drop("n")
    return parts.join(known.select("id", "unit", "radius", "worst"), "id")


def exact(leaders: DataFrame, count: int, block: int) -> DataFrame:
    """(u, v): all wide edges of the leaders u of one block (of about ``AUDIT``, by hash), by brute force."""
    blocks = parts_for(count, AUDIT)
    chosen = leaders.where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == block).select("id", "unit", "radius").toPandas()
    if not len(chosen):
        return leaders.sparkSession.createDataFrame([], "u long, v long")
    shared = leaders.sparkSession.sparkContext.broadcast((chosen["id"].to_numpy(), np.array(chosen["unit"].tolist(), np.float32), chosen["radius"].to_numpy()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, x, r = shared.value
        for batch in batches:
            for s in range(0, len(batch), 512):
                b = batch.slice(s, 512)
                other, far = b.column("id").to_numpy(), b.column("radius").to_numpy()
                sims = x @ _matrix(b.column("unit"), np.float32).T
                i, j = np.nonzero(sims >= np.cos(np.minimum(np.pi, _ANGLE + r + far.max() + 1e-4))[:, None].astype(np.float32) - np.float32(1e-6))
                keep = (sims[i, j] >= np.cos(np.minimum(np.pi, _ANGLE + r[i] + far[j] + 1e-4))) & (ids[i] != other[j])
                yield pa.RecordBatch.from_arrays([pa.array(ids[i[keep]]), pa.array(other[j[keep]])], names=["u", "v"])

    return leaders.select("id", "unit", "radius").mapInArrow(run, "u long, v long")


def audit(leaders: DataFrame, count: int) -> tuple[DataFrame, int, int]:
    """The true edges (u, v) of the first blocks of leaders, their number, and that of the blocks: enough for ``EDGES`` edges, or all."""
    true, n, block = None, 0, 0
    while block < parts_for(count, AUDIT) and (true is None or n < EDGES):
        met = cut(exact(leaders, count, block))
        true, n, block = met if true is None else true.union(met), n + met.count(), block + 1
    return true, n, block


def _had(graph: DataFrame, true: DataFrame, n: int) -> float:
    """Share of the ``n`` true edges that the graph has; 1 without any."""
    return true.join(graph.select("u", "v"), ["u", "v"], "left_semi").count() / n if n else 1.0


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(id, own, ball, far, linked, open): how many of the other ball the point is linked with, where its leader and radius decide that."""
    for b in batches:
        if not len(b):
            continue
        cos = (_matrix(b.column("unit")) * _matrix(b.column("lead"))).sum(axis=1)
        angle, r = np.arccos(np.clip(cos, -1, 1)), b.column("radius").to_numpy()
        size = b.column("size").to_numpy()
        alone = r == 0
        every = np.where(alone, cos >= COSINE, angle <= _ANGLE - r - _EPS)
        none = np.where(alone, cos < COSINE, angle > _ANGLE + r + _EPS)
        yield pa.RecordBatch.from_arrays([b.column("id"), b.column("own"), b.column("far"), pa.array(np.where(every, size, 0)), pa.array(~every & ~none)], names=["id", "own", "far", "linked", "open"])


def _test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        if len(b):
            hit = (_matrix(b.column("unit")) * _matrix(b.column("other"))).sum(axis=1) >= COSINE
            yield pa.RecordBatch.from_arrays([b.column("id"), b.column("own"), b.column("far"), pa.array(np.where(hit, b.column("mult").to_numpy(), 0))], names=["id", "own", "far", "linked"])


def _of_one_length(good: DataFrame, seed_rows: int) -> DataFrame:
    blocks = _buckets(good, seed_rows, 99, BLOCK * 3)
    covered = cut(_grouped(blocks, ["bucket", "part"], _cover, "id long, unit array<double>, mult long, ball long, angle double"))
    # a ball is named by its smallest point
    names = covered.groupBy("ball").agg(F.min("id").alias("name"), F.max("angle").alias("radius"), F.sum("mult").alias("size"))
    members = cut(covered.join(names, "ball").select("id", "unit", "mult", F.col("name").alias("ball"), "size", "angle", (F.col("id") == F.col("ball")).alias("leads"), "radius"))
    leaders = cut(members.where("leads").select(F.col("ball").alias("id"), "unit", "radius", "size"))
    count = leaders.count()

    def met(t: int) -> DataFrame:
        return _grouped(_buckets(leaders.withColumn("worst", F.lit(-2.0)), count, t, BLOCK), ["bucket", "part"], _propose, _EDGES)

    graph = _lists(reduce(DataFrame.union, map(met, range(TABLES))))
    true, n, seen = audit(leaders, count)
    tables, blocks = TABLES, parts_for(count, AUDIT)
    for _ in range(MOST_ROUNDS):
        graph = _lists(graph.union(_grouped(_meet(graph, leaders), ["bucket", "part"], _propose, _EDGES)))
        if seen == blocks or _had(graph, true, n) >= CONTENT:  # where the audit took in all leaders, its edges are all there are
            break
        graph = _lists(reduce(DataFrame.union, map(met, range(tables, 2 * tables)), graph))
        tables *= 2
    else:
        if _had(graph, true, n) < CONTENT:
            for block in range(seen, blocks):
                true = true.union(cut(exact(leaders, count, block)))
    wide = graph.where("wide").select("u", "v").union(true)
    wide = cut(wide.union(wide.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct())
    far = leaders.select(F.col("id").alias("v"), F.col("unit").alias("lead"), "radius", "size")
    asked = members.select("id", "unit", F.col("ball").alias("u")).join(wide.join(far, "v"), "u").select("id", "unit", F.col("u").alias("own"), F.col("v").alias("far"), "lead", "radius", "size")
    judged = cut(asked.mapInArrow(_count, "id long, own long, far long, linked long, open boolean"))
    open_ = judged.where("open").select("id", "own", "far").join(members.select("id", "unit"), "id")
    tested = open_.join(members.select(F.col("ball").alias("far"), F.col("unit").alias("other"), "mult"), "far")
    tested = tested.select("id", "unit", "own", "far", "other", "mult").mapInArrow(_test, "id long, own long, far long, linked long")
    cross = cut(judged.where("NOT open AND linked > 0").select("id", "own", "far", "linked").union(tested.where("linked > 0").groupBy("id", "own", "far").agg(F.sum("linked").alias("linked"))))
    root = components(cross.select(F.col("own").alias("a"), F.col("far").alias("b")).distinct()).select(F.col("id").alias("ball"), "component")
    outer = cross.groupBy("id").agg(F.sum("linked").alias("outer"))
    return members.join(outer, "id", "left").join(root, "ball", "left").select("id", (F.col("size") - 1 + F.coalesce("outer", F.lit(0))).cast("long").alias("n_links"), F.coalesce("component", "ball").alias("component"))


def near_duplicates(vectors: DataFrame) -> DataFrame:
    """A row per row of ``vectors``: vec_id, n_links, component_id, kept.

    Vectors that are null, zero or hold null or non-finite components have no links and are their own component, as are
    rows without a vec_id (null component, kept). Equal vectors are linked. Rows that repeat an id count as further
    vectors. Each length is searched by itself; vectors of unlike lengths are not linked.
    """
    marked = cut(marked_usable(vectors))
    good = marked.where("good")
    # points have numbers of their own, as unlike vectors may share a vec_id
    points = cut(good.groupBy("embedding").agg(F.min("vec_id").alias("least"), F.count("*").alias("mult")).withColumn("id", F.monotonically_increasing_id()))
    lengths = points.groupBy(F.size("embedding").alias("n")).count().orderBy("n").collect()
    big = F.array_max(F.transform("embedding", F.abs))
    scaled = F.transform("embedding", lambda x: x / big)
    norm = F.sqrt(F.aggregate("scaled", F.lit(0.0), lambda a, x: a + x * x))

    def sized(n: int) -> DataFrame:
        mine = points.where(F.size("embedding") == n).withColumn("scaled", scaled).withColumn("norm", norm)
        return cut(mine.select("id", F.transform("scaled", lambda x: x / F.col("norm")).alias("unit"), "mult"))

    # a length of one point has nothing to search
    found = [_of_one_length(sized(r.n), r["count"]) for r in lengths if r["count"] > 1]
    none = points.sparkSession.createDataFrame([], "id long, n_links long, component long")
    key = points.join(reduce(DataFrame.union, found, none), "id", "left").withColumn("n", F.coalesce("n_links", F.col("mult") - 1)).withColumn("root", F.coalesce("component", "id"))
    names = key.groupBy("root").agg(F.min("least").alias("c"))
    key = key.join(names, "root").select(F.col("embedding").alias("e"), F.xxhash64("embedding").alias("h"), "n", "c")
    took = good.select("vec_id", "embedding", F.xxhash64("embedding").alias("h"))
    linked = took.join(key, (took["h"] == key["h"]) & (took["embedding"] == key["e"])).select("vec_id", F.col("n").alias("n_links"), F.col("c").alias("component_id"))
    rest = marked.where("NOT good").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    out = linked.union(rest)
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


#: Rows of op9 in DuckDB: all pairs of vectors.
ORACLE = f"""
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS x FROM embeddings),
 g AS (SELECT * FROM v WHERE len(x) > 0 AND len(list_filter(x, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(x, lambda c: c <> 0)) > 0),
 l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM g AS a JOIN g AS b ON a.vec_id < b.vec_id AND len(a.x) = len(b.x) WHERE list_cosine_similarity(a.x, b.x) >= {COSINE}),
 e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
 n AS (SELECT a AS vec_id, count(*) AS n FROM e GROUP BY a),
 r AS (SELECT vec_id AS id, vec_id AS far FROM v UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.far),
 c AS (SELECT id, min(far) AS component_id FROM r GROUP BY id)
SELECT v.vec_id, coalesce(n, 0)::BIGINT AS n_links, component_id, v.vec_id = component_id AS kept FROM v LEFT JOIN n USING (vec_id) JOIN c ON c.id = v.vec_id
"""
