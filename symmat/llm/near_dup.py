"""Near-duplicate documents: a multi-index Hamming join over b-bit MinHash signatures, confirmed on full shingle sets.

A signature has ``CHUNKS * WIDTH`` positions of ``BITS`` bits, each the low bits of one min-hash. It is split into
``CHUNKS`` chunks. Two signatures that differ in at most ``CHUNKS * (ERRORS + 1) - 1`` positions agree on some chunk up
to ``ERRORS = 1`` wrong position (pigeonhole), so each signature is filed, for every chunk, under the ``WIDTH`` keys
that leave one position out: all pairs within that distance share a key. Farther pairs that happen to share one are
judged as well, since every candidate is confirmed on the full sets. At similarity 0.85, a pair shares no key with a
chance of about 3e-7, at 0.80 of about 3e-5.

Documents of equal shingle sets are one class, of which only the representative (smallest doc_id) is searched. The
members of a bucket belong to the bucket's hub, its smallest member; buckets of one hub form one group, so any two that
share a bucket share a group. Buckets are runs of a range sort by key and member, so that one that a third of all rows
share lies in many tasks; what runs over their borders is settled on one row a task.

Groups are cut into blocks of bounded size. In each, members without a near signature go first; of the rest, links are
counted on the full sets and leave as a spanning forest, so no pair is a row. A group of several blocks has a pivot, the
member that lies in most shared buckets, which joins every block. Members that hang together with the pivot by the links
found so far are settled; only the others meet each other and the settled ones as well, block by block. So copies of one
text cost work in proportion to their number, and the product of blocks is paid only for members that no link has settled.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._common import WORD, WordHasher, chunks, components, cut, mix64, runs, unused, utf8, word_spans

SHINGLE = 5
CHUNKS, WIDTH, ERRORS, BITS = 12, 7, 1, 16
POSITIONS = CHUNKS * WIDTH
#: Pairs whose signatures differ in more positions are not confirmed: at similarity 0.85, over 6 deviations from the mean, at 0.80 4.4.
FARTHEST = 33
LINK_PERCENT = 85
#: Members of a group in one block.
TILE = 256
#: A class of more than a share of 1 / HOT of all rows is hot: at most HOT of them are sent to all tasks.
HOT = 2000
#: Groups of several blocks up to which a row each is sent to all tasks.
PIVOTS = 100_000

_RNG = np.random.default_rng(7)
_WITH = [np.uint64(int(x) | 1) for x in _RNG.integers(1, 1 << 63, SHINGLE, dtype=np.uint64)]
_SHORT = np.uint64(0x5851F42D4C957F2D)
_FLIP = _RNG.integers(0, 1 << 32, POSITIONS, dtype=np.uint64).astype(np.uint32)
_TIMES = _RNG.integers(0, 1 << 32, POSITIONS, dtype=np.uint64).astype(np.uint32) | np.uint32(1)
_KEY = _RNG.integers(0, 1 << 63, (CHUNKS, WIDTH), dtype=np.uint64) | np.uint64(1)
_SALT = _RNG.integers(0, 1 << 63, (CHUNKS, WIDTH), dtype=np.uint64)


def shingles(flat: np.ndarray, offsets: np.ndarray, hasher: WordHasher) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of every text's shingles, not yet distinct, and n+1 offsets; texts without words have none."""
    start, end, first = word_spans(flat, offsets)
    n = np.diff(first)
    h = hasher.of(hasher.prefix(flat), start, end)
    long = max(0, len(h) - SHINGLE + 1)
    rolled = np.zeros(long, np.uint64)
    for j in range(SHINGLE):
        rolled += h[j : j + long] * _WITH[j]
    rolled = mix64(rolled)
    count = np.where(n >= SHINGLE, n - SHINGLE + 1, (n > 0).astype(n.dtype))
    at = np.concatenate([[0], np.cumsum(count)])
    inside = np.arange(at[-1]) - np.repeat(at[:-1], count) + np.repeat(first[:-1], count)
    out = np.empty(at[-1], np.uint64)
    usual = np.repeat(n >= SHINGLE, count)
    out[usual] = rolled[inside[usual]]
    for i in np.flatnonzero((n > 0) & (n < SHINGLE)):
        words = h[first[i] : first[i + 1]]
        out[at[i]] = mix64(np.array([sum(int(w) * int(c) for w, c in zip(words, _WITH)) + int(_SHORT) * len(words) & (1 << 64) - 1], np.uint64))[0]
    return out, at


def signatures(sets: np.ndarray, at: np.ndarray) -> np.ndarray:
    """b-bit MinHash signatures (texts x positions) of texts that have at least one shingle each."""
    short = (sets >> np.uint64(32)).astype(np.uint32)
    out = np.empty((len(at) - 1, POSITIONS), np.uint16)
    work = np.empty_like(short)
    for k in range(POSITIONS):
        np.bitwise_xor(short, _FLIP[k], out=work)
        np.multiply(work, _TIMES[k], out=work)
        low = np.minimum.reduceat(work, at[:-1])
        out[:, k] = (mix64(low.astype(np.uint64) + _SALT[0, 0]) & np.uint64((1 << BITS) - 1)).astype(np.uint16)
    return out


def chunk_keys(signature: np.ndarray) -> np.ndarray:
    """All keys of each signature: for each chunk, one per left-out position (texts x CHUNKS*WIDTH)."""
    x = mix64(signature.astype(np.uint64) + np.uint64(1)).reshape(len(signature), CHUNKS, WIDTH) * _KEY
    return mix64(x.sum(axis=2, dtype=np.uint64)[:, :, None] - x + _SALT).reshape(len(signature), -1)


def _describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hasher = WordHasher()
    for batch in batches:
        flat, offsets = utf8(batch.column("text"))
        ids = batch.column("doc_id")
        for i, j in chunks(offsets):
            raw, at = shingles(flat[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], hasher)
            own = [np.unique(raw[s:e]) for s, e in zip(at[:-1], at[1:])]
            n = np.array([len(x) for x in own], np.int64)
            full = np.flatnonzero(n)
            k1, k2 = np.zeros(j - i, np.uint64), np.zeros(j - i, np.uint64)
            sig: list[bytes | None] = [None] * (j - i)
            if len(full):
                sets = np.concatenate([own[x] for x in full])
                to = np.concatenate([[0], np.cumsum(n[full])])
                k1[full] = np.add.reduceat(mix64(sets ^ _SALT[1, 1]), to[:-1])
                k2[full] = np.add.reduceat(mix64(sets ^ _SALT[2, 2]), to[:-1])
                for x, row in zip(full, signatures(sets, to)):
                    sig[x] = row.tobytes()
            yield pa.RecordBatch.from_arrays(
                [ids.slice(i, j - i).cast(pa.int64()), batch.column("h").slice(i, j - i), pa.array(n), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), pa.array(sig, pa.binary())],
                names=["doc_id", "h", "n_shingles", "k1", "k2", "sig"],
            )


def _row_hash() -> Column:
    return F.xxhash64(F.col("doc_id").cast("long"), F.col("text").cast("string"))


def describe(docs: DataFrame) -> DataFrame:
    """(doc_id, h, n_shingles, k1, k2, sig) of each row: hash of id and text, set size, 128-bit key of the set, signature (null for an empty set)."""
    slim = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), _row_hash().alias("h"))
    return slim.mapInArrow(_describe, "doc_id long, h long, n_shingles long, k1 long, k2 long, sig binary")


def _file_under(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for i in range(0, len(batch), 2000):
            part = batch.slice(i, 2000)
            sig = np.frombuffer(b"".join(part.column("sig").to_pylist()), np.uint16).reshape(-1, POSITIONS)
            keys = chunk_keys(sig)
            yield pa.RecordBatch.from_arrays([pa.array(keys.ravel().view(np.int64)), pa.array(np.repeat(part.column("rep").to_numpy(zero_copy_only=False), keys.shape[1]))], names=["key", "rep"])


def _full_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hasher = WordHasher()
    for batch in batches:
        flat, offsets = utf8(batch.column("text"))
        ids = batch.column("id")
        for i, j in chunks(offsets):
            raw, at = shingles(flat[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], hasher)
            own = [np.unique(raw[s:e]) for s, e in zip(at[:-1], at[1:])]
            to = np.concatenate([[0], np.cumsum([len(x) for x in own])]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([ids.slice(i, j - i), pa.ListArray.from_arrays(to, pa.array(np.concatenate([*own, np.zeros(0, np.uint64)]).view(np.int64)))], names=["id", "set"])


_SHARED = "hub long, rep long, part int, first boolean, key long, n long, last long, head long"


def _share(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows (key, rep) sorted by both: (hub, rep) of every bucket of several; the rows of the task's first bucket carry
    ``first``, and one more row, without rep, says with which bucket the task ends (key, its first member ``last``, its
    rows ``n``) and with which it began (``head``, its key)."""
    from pyspark import TaskContext

    part = TaskContext.get().partitionId()
    head = key = hub = None
    count = 0
    held = np.zeros(0, np.int64)  # a bucket's first row waits for a second one

    def rows(hubs: np.ndarray, reps: np.ndarray, first: np.ndarray) -> pa.RecordBatch:
        none = pa.nulls(len(reps), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(hubs), pa.array(reps), pa.array(np.full(len(reps), part, np.int32)), pa.array(first), none, none, none, none], names=names)

    names = ["hub", "rep", "part", "first", "key", "n", "last", "head"]
    for batch in batches:
        if not len(batch):
            continue
        k, rep = batch.column("key").to_numpy(), batch.column("rep").to_numpy()
        if head is None:
            head = int(k[0])
        fresh = np.append(key is None or k[0] != key, k[1:] != k[:-1])
        at = np.flatnonzero(fresh)
        begin = np.concatenate([[0], at]) if not fresh[0] else at
        size = np.diff(np.append(begin, len(k)))
        hubs = np.repeat(np.where(fresh[begin], rep[begin], 0 if hub is None else hub), size)
        in_first = k == head
        if not fresh[0] and count == 1 and key != head:  # the bucket goes on: its first row, held back, comes too
            yield rows(held, held, np.zeros(1, bool))
        many = np.repeat((size > 1) | ~fresh[begin], size)
        keep = many | in_first
        if keep.any():
            yield rows(hubs[keep], rep[keep], in_first[keep])
        count = int(size[-1]) + (count if len(begin) == 1 and not fresh[0] else 0)
        key, hub = int(k[-1]), int(hubs[-1])
        held = rep[-1:] if size[-1] == 1 and fresh[begin[-1]] else held
    if head is not None:
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.int64()), pa.array([part], pa.int32()), pa.array([False]), *(pa.array([x], pa.int64()) for x in (key, count, hub, head))], names=names)


def _buckets(reps: DataFrame) -> DataFrame:
    """(hub, rep, shared): the groups, and in how many buckets of several the member lies."""
    filed = reps.select("rep", "sig").mapInArrow(_file_under, "key long, rep long")
    seen = cut(filed.repartitionByRange("key", "rep").sortWithinPartitions("key", "rep").mapInArrow(_share, _SHARED))
    ends = seen.where("rep IS NULL").select("part", "key", "n", "last", "head").orderBy("part").collect()  # a row per task
    true, more = [], set()  # the real hub of a task's first bucket; hubs whose own row the task before held back
    key = hub = None
    for e in ends:
        if e.head == key:
            true.append((e.part, hub))
            more.add(hub)
        elif e.head == e.key:
            true.append((e.part, e.last))
        if e.key != key:
            key, hub = e.key, e.last
    spark = reps.sparkSession
    own = spark.createDataFrame(true, "part int, real long")
    members = seen.where("rep IS NOT NULL").join(F.broadcast(own), "part", "left").select(F.when(F.col("first"), F.coalesce("real", "hub")).otherwise(F.col("hub")).alias("hub"), "rep")
    every = members.union(spark.createDataFrame([(h, h) for h in more], "hub long, rep long"))
    groups = cut(every.groupBy("hub", "rep").agg(F.count("*").alias("n")))
    return groups.select("hub", "rep").join(groups.groupBy("rep").agg(F.sum("n").alias("shared")), "rep")


def _promising(rows: pa.Table, percent: int) -> pa.Table:
    """A block of (hub, i, j, rep, pivot, n_shingles, sig): whether each member has a partner near enough to be worth full sets. Without one, and a pivot, a member is kept as one that is not settled."""
    sig = np.frombuffer(b"".join(rows.column("sig").to_pylist()), np.uint16).reshape(-1, POSITIONS)
    n = rows.column("n_shingles").to_numpy().astype(float)
    apart = np.zeros((len(sig), len(sig)), np.uint8)
    for k in range(POSITIONS):
        apart += sig[:, k, None] != sig[None, :, k]
    near = (apart <= FARTHEST) & (np.minimum(n[:, None], n[None]) * 100 >= np.maximum(n[:, None], n[None]) * percent)
    np.fill_diagonal(near, False)
    hopeful = near.any(axis=1)
    keep = hopeful | rows.column("pivot").is_valid().to_numpy()
    return rows.select(["hub", "i", "j", "rep", "pivot"]).append_column("hopeful", pa.array(hopeful)).filter(pa.array(keep))


def _linked(rows: pa.Table, percent: int) -> pa.Table:
    """A spanning forest (a, b) of the links within a block of (hub, rep, pivot, set), by counts of common shingles over
    column blocks; and (a, null, hub) for the members that it does not link with the pivot."""
    sets = rows.column("set").combine_chunks()
    size = np.diff(sets.offsets.to_numpy()).astype(np.int64)
    _, at, seen = np.unique(sets.flatten().to_numpy(), return_inverse=True, return_counts=True)
    member = np.repeat(np.arange(len(size)), size)
    often = seen[at] > 1
    at, member = (np.cumsum(seen > 1) - 1)[at[often]], member[often]
    order = np.argsort(at, kind="stable")
    at, member = at[order], member[order]
    common = np.zeros((len(size), len(size)), np.float64)
    for low in range(0, int((seen > 1).sum()), 4096):
        s, e = np.searchsorted(at, (low, low + 4096))
        block = np.zeros((len(size), 4096), np.float32)
        block[member[s:e], at[s:e] - low] = 1
        common += block @ block.T
    link = common * 100 >= (size[:, None] + size[None] - common) * percent
    a, b, left = [], [], np.ones(len(size), bool)
    for root in range(len(size)):
        stack = [root] if left[root] else []
        left[root] = False
        while stack:
            x = stack.pop()
            new = np.flatnonzero(link[x] & left)
            left[new] = False
            a += [x] * len(new)
            b += new.tolist()
            stack += new.tolist()
    rep = rows.column("rep").to_numpy()
    out = pa.table({"a": rep[np.array(a, int)], "b": rep[np.array(b, int)], "hub": pa.nulls(len(a), pa.int64()), "pivot": pa.nulls(len(a), pa.int64())})
    pivot = rows.column("pivot")[0].as_py()
    if pivot is None:
        return out
    tree = np.arange(len(rep))  # links come from a root outwards
    for x, y in zip(a, b):
        tree[y] = tree[x]
    with_pivot = tree == tree[int(np.flatnonzero(rep == pivot)[0])] if (rep == pivot).any() else np.zeros(len(rep), bool)
    open_ = rep[~with_pivot]
    return pa.concat_tables([out, pa.table({"a": open_, "b": pa.nulls(len(open_), pa.int64()), "hub": np.full(len(open_), rows.column("hub")[0].as_py(), np.int64), "pivot": np.full(len(open_), pivot, np.int64)})])


def _by_tile(rows: DataFrame, work, schema: str) -> DataFrame:
    """``work`` on each tile (hub, i, j) of ``rows``; tiles are bounded, and each is whole in one task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for tile in runs(batches, ["hub", "i", "j"]):
            if len(tile) > 1 or tile.column("pivot")[0].is_valid:
                yield from work(tile).to_batches()

    return rows.repartition("hub", "i", "j").sortWithinPartitions("hub", "i", "j", "rep").mapInArrow(run, schema)


def _meet(docs: DataFrame, tiles: DataFrame, reps: DataFrame, percent: int) -> tuple[DataFrame, DataFrame]:
    """(links, open): links (a, b) found in ``tiles`` (hub, i, j, rep, pivot), and (hub, rep, pivot) of members not linked with the pivot they met."""
    judged = cut(_by_tile(tiles.join(reps, "rep"), lambda tile: _promising(tile, percent), "hub long, i long, j long, rep long, pivot long, hopeful boolean"))
    hopeful = judged.where("hopeful").drop("hopeful")
    wanted = hopeful.select(F.col("rep").alias("id")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), F.col("text").cast("string")).join(wanted, "id", "left_semi")
    sets = texts.mapInArrow(_full_sets, "id long, set array<long>").withColumnRenamed("id", "rep")
    found = cut(_by_tile(hopeful.join(sets, "rep"), lambda tile: _linked(tile, percent), "a long, b long, hub long, pivot long"))
    open_ = judged.where("NOT hopeful").select("hub", "rep", "pivot").union(found.where("b IS NULL").select("hub", F.col("a").alias("rep"), "pivot")).distinct()
    return found.where("b IS NOT NULL").select("a", "b"), open_


def _blocks(members: DataFrame) -> DataFrame:
    """``members`` (hub, rep, ...) with block: ``TILE`` neighbours of a sort by hub and member, however many partitions the sort has.

    A large group lies in many partitions; a row a partition says how many members come before it.
    """
    lined = cut(members.orderBy("hub", "rep").withColumn("serial", F.monotonically_increasing_id())).withColumn("part", F.shiftright("serial", 33))
    sizes = lined.groupBy("part").agg(F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    place = F.col("before") + F.col("serial").bitwiseAND(F.lit((1 << 33) - 1))
    return lined.join(F.broadcast(sizes.select("part", before.alias("before"))), "part").withColumn("block", F.floor(place / TILE).cast("long")).select(*members.columns, "block")


def _rest(docs: DataFrame, members: DataFrame, several: DataFrame, open_: DataFrame, links: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """The links of members that do not hang together with their pivot: among each other, and with the settled members."""
    root = components(links)
    pivots = several.join(root.withColumnRenamed("id", "pivot"), "pivot", "left").select("hub", "pivot", F.coalesce("component", "pivot").alias("theirs"))
    known = open_.join(root.withColumnRenamed("id", "rep"), "rep", "left").select("hub", "rep", F.coalesce("component", "rep").alias("own"))
    few = pivots.limit(PIVOTS + 1).count() <= PIVOTS
    open_ = _blocks(known.join(F.broadcast(pivots) if few else pivots, "hub").where("own <> theirs").select("hub", "rep"))
    settled = members.select("hub", "rep").join(F.broadcast(several.select("hub")) if few else several.select("hub"), "hub", "left_semi").join(open_.select("hub", "rep"), ["hub", "rep"], "left_anti")
    settled = _blocks(settled).withColumn("block", -1 - F.col("block"))  # numbers apart from those of open blocks
    first = cut(open_.select("hub", F.col("block").alias("i")).distinct())
    second = first.withColumnRenamed("i", "j").union(settled.select("hub", F.col("block").alias("j")).distinct())
    pairs = cut(first.join(second, "hub").where("j < 0 OR j >= i"))
    both = open_.union(settled)
    own = both.withColumnRenamed("block", "i").join(pairs, ["hub", "i"]).select("hub", "i", "j", "rep")
    other = both.withColumnRenamed("block", "j").join(pairs.where("i <> j"), ["hub", "j"]).select("hub", "i", "j", "rep")
    return _meet(docs, own.union(other).withColumn("pivot", F.lit(None).cast("long")), reps, percent)[0]


def link(docs: DataFrame, percent: int = LINK_PERCENT) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows, classes, links) of ``docs``.

    rows: doc_id, h, n_shingles, k1, k2 of each input row. classes: (k1, k2, n_shingles, rep, n), one row per distinct
    non-empty set. links: confirmed (a, b) between representatives that, with the classes, reach whatever all links reach.
    """
    rows = cut(describe(docs))
    some = rows.where("n_shingles > 0 AND doc_id IS NOT NULL")
    classes = some.groupBy("k1", "k2", "n_shingles").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n"))
    lead = classes.select(F.col("rep").alias("doc_id"), "k1", "k2", "n_shingles")
    reps = some.join(lead, ["doc_id", "k1", "k2", "n_shingles"]).groupBy(F.col("doc_id").alias("rep"), "n_shingles").agg(F.first("sig").alias("sig"))
    reps = cut(reps)
    members = _blocks(_buckets(reps))
    blocks = cut(members.groupBy("hub", "block").agg(F.max(F.struct("shared", (-F.col("rep")).alias("minus"))).alias("most")))
    several = blocks.groupBy("hub").agg(F.count("*").alias("n"), (-F.max("most")["minus"]).alias("pivot")).where("n > 1").select("hub", "pivot")
    with_pivot = cut(blocks.select("hub", "block").join(several, "hub", "left"))
    own = members.join(with_pivot, ["hub", "block"]).select("hub", "block", "rep", "pivot").union(with_pivot.where("pivot IS NOT NULL").select("hub", "block", F.col("pivot").alias("rep"), "pivot")).distinct()
    links, open_ = _meet(docs, own.select("hub", F.col("block").alias("i"), F.col("block").alias("j"), "rep", "pivot"), reps, percent)
    open_ = cut(open_)
    if not open_.isEmpty():
        links = links.union(_rest(docs, members, several, open_, links, reps, percent))
    return rows, classes, cut(links.distinct())


def _judged(docs: DataFrame, percent: int) -> DataFrame:
    """(doc_id, h, n_shingles, k1, k2, component_id, kept) of each row."""
    rows, classes, links = link(docs, percent)
    root = components(links).withColumnRenamed("id", "rep")
    classes = cut(classes.join(root, "rep", "left").select("k1", "k2", "n_shingles", "n", F.coalesce("component", "rep").alias("component")))
    slim = rows.select("doc_id", "h", "n_shingles", "k1", "k2")
    # an empty set has its own document as component and must not meet other empty sets
    some, alone = slim.where("n_shingles > 0 AND doc_id IS NOT NULL"), slim.where("n_shingles = 0 OR doc_id IS NULL")
    key = ["k1", "k2", "n_shingles"]
    hot = classes.where(F.col("n") * HOT > some.count()).drop("n")  # fewer than HOT rows
    large = some.join(F.broadcast(hot), key)
    small = some.join(F.broadcast(hot.drop("component")), key, "left_anti").join(classes.drop("n"), key)
    names = ["doc_id", "h", "n_shingles", "k1", "k2", F.col("component").alias("component_id")]
    out = large.select(*names).union(small.select(*names)).union(alone.select(*names[:-1], F.col("doc_id").alias("component_id")))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def near_duplicates(docs: DataFrame, percent: int = LINK_PERCENT) -> DataFrame:
    """One row per row of ``docs`` (doc_id, text): doc_id, n_shingles, component_id, kept.

    component_id is the smallest doc_id reachable over links, kept is doc_id = component_id. A null, empty or blank text
    has an empty set and is linked with nothing; a text of fewer than five words is one shingle. A row without a doc_id
    takes no part: its component_id is null and kept is true. Rows that repeat a doc_id give a row each.
    """
    return _judged(docs, percent).select("doc_id", "n_shingles", "component_id", "kept")


def drop_near_duplicates(docs: DataFrame, percent: int = LINK_PERCENT) -> DataFrame:
    """``docs`` without the rows whose component is led by another document; all columns stay, whatever their names.

    Rows are judged one by one, so unlike texts under one doc_id may both stay; rows equal in doc_id and shingle set become
    one. Rows without words or without a doc_id all stay. An empty table gives no rows.
    """
    found = cut(_judged(docs, percent).where("kept AND n_shingles > 0 AND doc_id IS NOT NULL"))
    kept = cut(found.groupBy("doc_id", "k1", "k2", "n_shingles").agg(F.min("h").alias("h"), F.count("*").alias("n")))
    h, own_id, own_h = unused(docs, "h", "own_id", "own_h")
    marked = docs.withColumn(h, _row_hash())
    out = marked.join(kept.select(F.col("doc_id").alias(own_id), F.col("h").alias(own_h)), (F.col("doc_id").cast("long") == F.col(own_id)) & (F.col(h) == F.col(own_h)), "left_semi")
    if not kept.where("n > 1").isEmpty():
        out = out.dropDuplicates(["doc_id", h])
    rest = docs.where(F.col("doc_id").isNull() | ~F.coalesce(F.col("text").cast("string").rlike(WORD), F.lit(False)))
    return out.select(*docs.columns).unionByName(rest)


#: Rows of op1 in DuckDB: all pairs of documents with a common shingle.
ORACLE = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
 s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS s FROM d),
 n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
 p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.s = y.s AND x.doc_id < y.doc_id GROUP BY 1, 2),
 l AS (SELECT a, b FROM p JOIN n AS na ON na.doc_id = a JOIN n AS nb ON nb.doc_id = b WHERE 100 * c >= 85 * (na.n + nb.n - c)),
 e AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
 r AS (SELECT doc_id AS id, doc_id AS far FROM documents UNION SELECT r.id, e.b FROM r JOIN e ON e.a = r.far),
 c AS (SELECT id, min(far) AS component_id FROM r GROUP BY id)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, component_id, d.doc_id = component_id AS kept FROM d LEFT JOIN n USING (doc_id) JOIN c ON c.id = d.doc_id
"""
