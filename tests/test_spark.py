"""The engine through Spark on small matrices, against dense numpy."""

import numpy as np
import pytest

from symmat.model import Blocks
from symmat.operators import baseline, encode, measure, multiply, relational, reorder
from symmat.plans import choose
from symmat.sources import matrices as src
from symmat.streaming.append import BlockSink, compact, right

RNG = np.random.default_rng(8)
X = RNG.integers(0, 4, (60, 7)) * 0.25
X[:, 4] = X[:, 1]
X[5] = 0
X[:, 6] = 0


@pytest.fixture(scope="module")
def view(spark):
    return src.from_wide(spark.createDataFrame([(i, *map(float, r)) for i, r in enumerate(X)], "row_id long, " + ", ".join(f"c{j} double" for j in range(7))), [f"c{j}" for j in range(7)])


def rows(df, n=60):
    out = np.full(n, np.nan)
    for r in df.collect():
        out[r[0]] = r[1]
    return out


def dense(df):
    out = np.zeros(X.shape)
    for r in df.collect():
        out[r.row_id, r.col] = r.val
    return out


A, B = np.arange(1.0, 8), 1 + np.arange(60) % 7.0


@pytest.mark.parametrize("codec,scope,blocks", [("stream", "global", 1), ("g32", "global", 3), ("gpack", "block", 7), ("gans", "block", 100)])
def test_products_and_round_trip(spark, view, codec, scope, blocks):
    g = multiply.compress(view, blocks, codec, scope=scope).prepared()
    np.testing.assert_allclose(rows(multiply.right(g, A)), X @ A)
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(B)], "row_id long, y double")
    np.testing.assert_allclose(rows(multiply.left(g, y), 7), B @ X)
    np.testing.assert_allclose(multiply.gram_apply(g, A), X.T @ (X @ A))
    assert np.array_equal(dense(multiply.decode(g)), X)
    assert {r.row_id for r in multiply.decode(g, [3, 9]).collect()} == {3, 9}


def test_orders_do_not_change_products(view, tmp_path, spark):
    g = multiply.compress(view, 2, "gpack", order={0: [6, 5, 4, 3, 2, 1, 0], 1: [2, 0, 1, 3, 5, 4, 6]})
    np.testing.assert_allclose(rows(multiply.right(g, A)), X @ A)
    g.save(str(tmp_path / "m"))
    np.testing.assert_allclose(rows(multiply.right(Blocks.load(spark, str(tmp_path / "m")), A)), X @ A)
    best, totals = reorder.blockwise(view, 2)
    np.testing.assert_allclose(rows(multiply.right(best, A)), X @ A)
    assert set(totals) == {"paths", "matching", "identity"}


def test_loop_stops_at_zero(spark):
    zero = src.from_wide(spark.createDataFrame([(0, 0.0), (1, 0.0)], "row_id long, c double"), ["c"])
    x, norms = multiply.iterate(multiply.compress(zero, 1), np.ones(1), 5)
    assert norms == [0.0] and x.tolist() == [0.0]


def test_least_squares(spark, view):
    keep = view.select([0, 1, 2, 3])
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(B)], "row_id long, y double")
    got = multiply.cgls(multiply.compress(keep, 2).prepared(), y)
    np.testing.assert_allclose(got, np.linalg.lstsq(X[:, :4], B, rcond=None)[0], atol=1e-8)


def test_relational_grammar(spark, view):
    g = relational.build(view, 8)
    a = spark.createDataFrame([(i, float(v)) for i, v in enumerate(A)], "col int, x double")
    np.testing.assert_allclose(rows(relational.right(g, a)), X @ A)
    assert np.array_equal(dense(relational.expand(g)), X)
    assert relational.prune_useless(g).count() == g.rules.count()


def test_similarity_engines_agree(view):
    want = {(r.ci, r.cj): r.rep for r in reorder.repetitions(view, "hash").collect()}
    assert want == {(r.ci, r.cj): r.rep for r in reorder.repetitions(view, "sort").collect()}
    local = reorder.local_edges(*np.nonzero(X), X[X != 0], 60, 7)
    assert {(a, b): round(w * 60) for a, b, w in local} == {k: v for k, v in want.items() if v}


@pytest.mark.parametrize("scheme", [None, *baseline.SCHEMES])
def test_column_groups(spark, view, scheme, monkeypatch):
    if scheme:
        monkeypatch.setattr(baseline, "encode_group", lambda x, f=baseline.encode_group, s=scheme: f(x, s))
    g = baseline.column_groups(view, 3)
    np.testing.assert_allclose(rows(baseline.groups_right(g, A)), X @ A)
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(B)], "row_id long, y double")
    np.testing.assert_allclose(np.nan_to_num(rows(baseline.groups_left(g, y), 7)), B @ X)
    np.testing.assert_allclose(baseline.groups_gram(g, A), X.T @ (X @ A))
    assert np.array_equal(dense(baseline.groups_decode(g)), X)
    assert sorted(c for cols in g.groups for c in cols) == list(range(7))
    if not scheme:
        assert sum(g.sizes.values()) <= X.nbytes and {r.scheme for r in g.schemes().collect()} <= set(baseline.SCHEMES)


def test_each_scheme_is_chosen_where_it_is_smallest():
    n = 4000
    r = np.random.default_rng(1)
    few = np.zeros((n, 1))
    few[r.choice(n, 20, replace=False)] = 5.0
    cases = {"offsets": few, "runs": np.repeat(r.integers(1, 5, 40).astype(float), 100)[:, None], "codes": r.integers(1, 5, (n, 2)).astype(float), "raw": r.normal(size=(n, 1))}
    for scheme, x in cases.items():
        part = baseline.encode_group(x)
        assert part["scheme"] == scheme and part["bytes"] == min(baseline.encode_group(x, s)["bytes"] for s in baseline.SCHEMES)
        read = baseline.GroupPart(part, n, x.shape[1])
        assert np.array_equal(read.dense(), x)
        np.testing.assert_allclose(read.left(np.arange(n)), np.arange(n) @ x)


def test_entropy_over_span_borders(spark, view, monkeypatch):
    s = encode.stream(view, encode.dictionary(view), blocks=2)
    want = [measure.entropy(s, k).first() for k in (1, 3)]
    monkeypatch.setattr(measure, "SPAN", 1)
    for k, w in zip((1, 3), want):
        got = measure.entropy(s, k).first()
        assert got.total == w.total and got.h == pytest.approx(w.h)


def test_blocks_of_any_row_ids(spark, view, monkeypatch):
    import symmat.model

    ids = np.sort(np.concatenate([[-(1 << 62), -5, 0, 3, 7, 1 << 55, (1 << 55) + 1, (1 << 62) + 3], RNG.integers(-(1 << 60), 1 << 60, 52)]))
    moved = type(view)(view.rows.join(spark.createDataFrame([(i, int(x)) for i, x in enumerate(ids)], "row_id long, far long"), "row_id").select(symmat.model.F.col("far").alias("row_id"), "cols", "vals"), view.m)
    for edges in (128, 2):  # borders in an expression, and searched in Arrow batches
        monkeypatch.setattr(symmat.model, "EDGES", edges)
        for blocks in (1, 4, 7, 60, 100):
            v = type(view)(moved.rows, moved.m)
            sizes = [r["n"] for r in v.rows.groupBy(v.block_of(blocks).alias("b")).agg(symmat.model.F.count("*").alias("n")).orderBy("b").collect()]
            per = -(-60 // blocks)
            assert sizes == [per] * (60 // per) + [60 % per] * (60 % per > 0)
    g = multiply.compress(moved, 4)
    got = {r.row_id: r.y for r in multiply.right(g, A).collect()}
    np.testing.assert_allclose([got[int(i)] for i in ids], X @ A)
    assert multiply.compress(view, None).df.count() == 1 and multiply.block_count(view, 64) == -(-4 * (int((X != 0).sum()) + 60) // 64)


def test_entropy_counts_the_marks_of_empty_rows(spark, view):
    marked = [list(1 + np.flatnonzero(r)) for r in X]
    s = encode.stream(view)
    by_row = {}
    for r in s.collect():
        by_row.setdefault(r.row_id, []).append((r.pos, r.sym))
    line = [x for i in range(60) for x in [q for _, q in sorted(by_row.get(i, []))] + [0]]
    assert len(line) == sum(map(len, marked)) + 60
    for k in (0, 1, 2):
        seen: dict = {}
        for i, x in enumerate(line):
            ctx = tuple(line[max(0, i - k) : i]) if k else ()
            seen.setdefault((len(ctx), ctx), []).append(x)
        want = 0.0
        for own in seen.values():
            _, n = np.unique(own, return_counts=True)
            want -= (n * np.log2(n / n.sum())).sum()
        got = measure.entropy(s, k, encode.row_marks(view)).first()
        assert got.total == len(line) and got.h == pytest.approx(want / len(line))


def test_orders_of_each_row(spark, view):
    s = encode.stream(view, order="row_partner")
    lines: dict = {}
    for r in s.collect():
        lines.setdefault(r.row_id, {})[r.pos] = r.sym
    sets = {i: set(x.values()) for i, x in lines.items()}
    alone = {q: sum(q in x for x in sets.values()) for q in set().union(*sets.values())}
    for i, own in lines.items():
        line = [own[k] for k in range(len(own))]
        left = sorted(sets[i])
        want = [max(left, key=lambda q: (alone[q], -q))]
        while left := [q for q in left if q != want[-1]]:
            want.append(max(left, key=lambda q: (sum(q in x and want[-1] in x for x in sets.values()), -q)))
        assert line == want
    with pytest.raises(ValueError):
        encode.stream(view, order="other")


def test_blockwise_winner_has_the_least_total(view):
    best, totals = reorder.blockwise(view, 2, k=3)
    assert best.df.agg({"c_bytes": "sum"}).first()[0] + best.df.agg({"r_bytes": "sum"}).first()[0] == min(totals.values())


def test_chooser_takes_the_fastest_that_fits(view, monkeypatch):
    every = choose.candidates(view, 2)
    seconds = {"stream": 1.0, "g32": 3.0, "gpack": 5.0, "gans": 7.0}
    fixed = choose.F.create_map(*[choose.F.lit(x) for kv in seconds.items() for x in kv])
    staged = type(every)(every.df.withColumn("seconds", fixed[choose.F.col("codec")]), every.m, "mixed", every.values)
    monkeypatch.setattr(choose, "candidates", lambda *a, **k: staged)
    cost = {r.codec: r.b for r in staged.df.groupBy("codec").agg(choose.F.sum(choose.F.expr("c_bytes + r_bytes + v_bytes + 8 * r_len")).alias("b")).collect()}
    base = 8 * len(every.values) + 8 * (60 + 7)
    picked = lambda budget, **k: {r.codec for r in choose.choose(view, budget, 2, **k).df.select("codec").collect()}
    assert picked(10**9) == {"stream"} and picked(10**9, per_block=False) == {"stream"}
    assert picked(base + min(cost.values()), per_block=False) == {min(cost, key=cost.get)}


def test_products_of_several_vectors_and_norms(spark, view):
    g = multiply.compress(view, 3, "gans")
    y = spark.createDataFrame([(i, [float(v), 1.0, -2.0 * i]) for i, v in enumerate(B)], "row_id long, y array<double>")
    got = {r.col: r.x for r in multiply.left(g, y).collect()}
    np.testing.assert_allclose([got[c] for c in range(7)], X.T @ np.stack([B, np.ones(60), -2.0 * np.arange(60)], axis=1))
    np.testing.assert_allclose(rows(multiply.norms(g), 7), np.linalg.norm(X, axis=0))
    t = multiply.transposed(g)
    np.testing.assert_allclose(rows(t.left(A)), X @ A)
    assert t.transposed() is g


def test_peaks_are_of_products(view):
    peaks = measure.product_peaks(multiply.compress(view, 2)).collect()
    assert len(peaks) == 2 and all(0 < r.base_kb <= r.encoded_kb <= r.peak_kb for r in peaks)


def test_loops_keep_within_their_memory(spark, view, monkeypatch):
    monkeypatch.setattr(multiply, "KEEP_BYTES", 3000)
    g = multiply.compress(view, 6, "gpack").prepared()
    x, norms = multiply.iterate(g, np.ones(7), 3)
    z = np.ones(7)
    for _ in range(3):
        z = X.T @ (X @ z)
        z = z / np.abs(z).max()
    np.testing.assert_allclose(x, z)
    g.release()


def test_saved_blocks_can_be_read_one_by_one(spark, view, tmp_path):
    g = multiply.compress(view, 4)
    g.save(str(tmp_path / "m"))
    assert {r.block for r in Blocks.load(spark, str(tmp_path / "m"), [1, 3]).df.select("block").collect()} == {1, 3}


def test_chooser_keeps_to_its_budget(view):
    g = choose.choose(view, 8 * X.size, 2)
    np.testing.assert_allclose(rows(multiply.right(g, A)), X @ A)
    with pytest.raises(ValueError):
        choose.choose(view, 10, 2)


def test_batches_add_up(spark, tmp_path):
    sink = BlockSink(str(tmp_path / "s"), 3)
    a = spark.createDataFrame([(1, 0, 2.0), (2, 1, 1.0)], "row_id long, col int, val double")
    b = spark.createDataFrame([(1, 2, 5.0)], "row_id long, col int, val double")
    sink(a, 0)
    sink(b, 1)
    sink(b, 1)  # delivered again
    want = {1: 17.0, 2: 2.0}
    assert dict(map(tuple, right(sink.blocks(spark), np.arange(1.0, 4)).collect())) == want
    compact(sink, spark, str(tmp_path / "t"))
    assert dict(map(tuple, right(BlockSink(str(tmp_path / "t"), 3).blocks(spark), np.arange(1.0, 4)).collect())) == want


def test_nulls_and_large_numbers(spark):
    df = spark.createDataFrame([(0, None), (1, 2.0)], "row_id long, c double")
    with pytest.raises(Exception, match="null cell"):
        src.from_wide(df, ["c"]).rows.collect()
    assert src.from_wide(df, ["c"], nulls="zero").cells.count() == 1
    with pytest.raises(Exception, match="2\\*\\*53"):
        src.from_wide(spark.createDataFrame([(0, 1 << 60)], "row_id long, c long"), ["c"]).rows.collect()


def test_row_numbers_follow_the_order(spark):
    df = spark.createDataFrame([(int(v),) for v in RNG.permutation(500)], "k long")
    assert all(r.k == r.row_id for r in src.with_row_ids(df, ["k"]).collect())


def test_measures(view):
    f = measure.features(view).first()
    assert (f.n, f.m, f.t) == (60, 7, int((X != 0).sum()))
    g = multiply.compress(view, 1, "gpack")
    assert measure.size(g) < baseline.dense_bytes(60, 7) and measure.operations(g).first().compressed < 60 * 7
    codes = encode.dictionary(view, "frequency")
    s = encode.stream(view, codes, [6, 5, 4, 3, 2, 1, 0])
    assert np.array_equal(dense(encode.decode_stream(s, codes, 7)), X)


def test_large_blocks_are_built_in_pieces(spark, view, monkeypatch):
    import symmat.model

    monkeypatch.setattr(symmat.model, "PIECE_SYMBOLS", 40)
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(B)], "row_id long, y double")
    far = np.sort(RNG.integers(-(1 << 60), 1 << 60, 60))
    moved = type(view)(view.rows.join(spark.createDataFrame([(i, int(x)) for i, x in enumerate(far)], "row_id long, far long"), "row_id").select(symmat.model.F.col("far").alias("row_id"), "cols", "vals"), view.m)
    for blocks, scope in ((1, "global"), (4, "block")):
        g = multiply.compress(view, blocks, "gans", scope=scope).prepared()
        kept = g.df.select("block", "piece", "row_ids", "s_len").orderBy("block", "piece").collect()
        assert len(kept) > 2 * blocks and all(r.s_len <= 40 for r in kept) and [x for r in kept for x in r.row_ids] == list(range(60))
        per = -(-60 // blocks)
        assert all({x // per for x in r.row_ids} == {r.block} for r in kept)
        assert {r.block: r.n_rows for r in g.explain().collect()} == {b: per for b in range(blocks)}
        np.testing.assert_allclose(rows(multiply.right(g, A)), X @ A)
        np.testing.assert_allclose(rows(multiply.left(g, y), 7), B @ X)
        np.testing.assert_allclose(multiply.gram_apply(g, A), X.T @ (X @ A))
        np.testing.assert_allclose(rows(multiply.norms(g), 7), np.linalg.norm(X, axis=0))
        assert np.array_equal(dense(multiply.decode(g)), X)
        peaks = measure.product_peaks(multiply.compress(view, blocks, piece_symbols=200)).collect()
        assert sorted(r.block for r in peaks) == list(range(blocks)) and all(0 < r.base_kb <= r.encoded_kb <= r.peak_kb for r in peaks)
        of = {(r.block, r.piece): list(r.row_ids) for r in kept}
        other = multiply.compress(moved, blocks, scope=scope).df.select("block", "piece", "row_ids").collect()
        assert {(r.block, r.piece): list(r.row_ids) for r in other} == {k: [int(far[i]) for i in v] for k, v in of.items()}
    best, totals = reorder.blockwise(view, 2)
    np.testing.assert_allclose(rows(multiply.right(best, A)), X @ A)
    assert best.df.agg({"c_bytes": "sum"}).first()[0] + best.df.agg({"r_bytes": "sum"}).first()[0] == min(totals.values())
    np.testing.assert_allclose(rows(multiply.right(choose.choose(view, 8 * X.size * 4, 2), A)), X @ A)


def test_values_come_to_the_driver_packed_and_only_if_few(view, monkeypatch):
    from pyspark.sql.classic.dataframe import DataFrame

    def refused(*_):
        raise AssertionError("a row per value on the driver")

    monkeypatch.setattr(DataFrame, "toPandas", refused)
    assert np.array_equal(multiply.shared_values(view), np.unique(X[X != 0]))
    monkeypatch.setattr(multiply, "BROADCAST_BYTES", 8)
    assert multiply.shared_values(view) is None


def test_libsvm_lines_keep_their_order_over_files(spark, tmp_path):
    (tmp_path / "svm").mkdir()
    (tmp_path / "svm/part-00000.txt").write_text("0 1:1.0\n0\n")
    (tmp_path / "svm/part-00001.txt").write_text("".join(f"0 1:{i}.0 2:1.5\n" for i in range(2, 40)))  # the larger file is dealt first
    got = {(r.row_id, r.col): r.val for r in src.read_libsvm(spark, str(tmp_path / "svm"), 2).cells.collect()}
    assert got == {(0, 0): 1.0} | {(i, 0): float(i) for i in range(2, 40)} | {(i, 1): 1.5 for i in range(2, 40)}


def test_column_groups_in_pieces(spark, view, monkeypatch):
    import symmat.model

    monkeypatch.setattr(symmat.model, "PIECE_SYMBOLS", 80)
    g = baseline.column_groups(view, 2).prepared()
    assert g.encoded.count() > 4 and {r.block for r in g.encoded.select("block").collect()} == {0, 1}
    assert all(r.blocks <= 2 for r in g.schemes().collect())
    np.testing.assert_allclose(rows(baseline.groups_right(g, A)), X @ A)
    y = spark.createDataFrame([(i, float(v)) for i, v in enumerate(B)], "row_id long, y double")
    np.testing.assert_allclose(np.nan_to_num(rows(baseline.groups_left(g, y), 7)), B @ X)
    np.testing.assert_allclose(baseline.groups_gram(g, A), X.T @ (X @ A))
    assert np.array_equal(dense(baseline.groups_decode(g)), X)


def test_orders_of_a_piece_share_its_rows(spark, view, monkeypatch):
    import symmat.model
    from symmat.workloads import experiments

    monkeypatch.setattr(symmat.model, "PIECE_SYMBOLS", 100)

    def work(key, rows):
        pa = multiply.pa
        cells = len(rows.column("cols").combine_chunks().flatten())
        return pa.table({"piece": pa.array([key[1].as_py()], pa.int32()), "lot": pa.array([key[2].as_py()], pa.int32()), "ids": [rows.column("row_id").to_pylist()], "cells": pa.array([cells], pa.int32())})

    got = multiply.in_pieces(view, 1, lots=2).applyInArrow(work, "piece int, lot int, ids array<long>, cells int").orderBy("lot", "piece").collect()
    pieces = view.piece_count(1)[1]
    assert pieces > 1 and [(r.lot, r.piece) for r in got] == [(k, p) for k in range(2) for p in range(pieces)]
    assert [i for r in got for i in r.ids] == [*range(60), *range(60)] and sum(r.cells for r in got) == 2 * (X != 0).sum()
    orders = [tuple(map(int, RNG.permutation(7))) for _ in range(5)]
    want = [measure.size(multiply.compress(view, 1, "gans", order=o)) for o in orders]
    assert experiments.sizes_of_orders(view, orders) == want
    monkeypatch.setattr(experiments, "LOTS", 0)
    assert experiments.sizes_of_orders(view, orders) == want


def test_stored_tables_are_given_back(spark):
    import os

    import symmat.model as model

    folder = model.shared_folder(spark).removeprefix("file:")
    there = lambda: {f for f in os.listdir(folder) if f.startswith("stored-")}
    before = there()
    with model.scratch(spark):
        with model.scratch(spark):
            model.stored(spark.range(5).toDF("a"))
            with model.outer():
                kept = model.stored(spark.createDataFrame([(1, [1.5, -0.0], None)], "a long, b array<double>, c string"))
        assert len(there() - before) == 1 and str(kept.first().b) == "[1.5, -0.0]" and kept.first().c is None
    assert there() == before


def test_loops_keep_numbers_not_blocks(spark, view, monkeypatch):
    from symmat.workloads import experiments

    seen, real = [], choose.stored
    monkeypatch.setattr(choose, "stored", lambda df: seen.append(df.columns) or real(df))
    monkeypatch.setattr(choose, "cut", None)
    monkeypatch.setattr(experiments, "_view", lambda *a: view)
    got = {(r.method, r.metric): r.value for r in experiments.loops(spark, "", ("x",), blocks=(1, 3), rounds=1).collect()}
    assert len(seen) == 2 and not {"c", "r", "v", "row_ids"} & {c for columns in seen for c in columns}
    assert {k for k, _ in got} == {f"{c}/{b}" for c in experiments.CODECS for b in (1, 3)} and {k for k, what in got if what == "peak_pct"} == {"gpack/1", "gans/1"}
    for c in experiments.CODECS:
        assert got[f"{c}/3", "size_pct"] == pytest.approx(measure.size_pct(measure.size(multiply.compress(view, 3, c)), 60, 7))


def test_size_table_compresses_a_method_a_task(spark, view):
    import zlib

    df = baseline.byte_sizes(view, ("gzip", "rle"), 2)
    got = {(r.block, r.method): r.bytes for r in df.collect()}
    assert df.rdd.getNumPartitions() == 4  # two blocks, two methods
    for b in range(2):
        z = zlib.compressobj(6, zlib.DEFLATED, 31)
        data = X[30 * b : 30 * b + 30].tobytes()
        assert got[b, "gzip"] == len(z.compress(data)) + len(z.flush())


def test_characters_are_counted_in_one_pass(spark):
    texts = ["abca  é一~", None, "", "\x7f\x1fz" * 3, "a" * 5000]
    df = spark.createDataFrame([(7 * i, t) for i, t in enumerate(texts)], "doc_id int, text string")
    v = src.from_characters(df, "text", range(32, 127), "doc_id")
    assert "MapInArrow" in v.rows._jdf.queryExecution().executedPlan().toString()
    got = {r.row_id: dict(zip(r.cols, r.vals)) for r in v.rows.collect()}
    assert got == {7 * i: {ord(c) - 32: float(t.count(c)) for c in sorted(set(t)) if 32 <= ord(c) < 127} for i, t in enumerate(t or "" for t in texts)}


def test_entropy_makes_no_join_of_pairs(spark, view):
    s = encode.stream(view, encode.dictionary(view))
    plan = measure.entropy(s, 0, encode.row_marks(view))._jdf.queryExecution().optimizedPlan().toString()
    of_symbols = s._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("Join") == of_symbols.count("Join")
    _, n = np.unique(np.concatenate([np.zeros(60, int), 1 + np.unique(X[X != 0], return_inverse=True)[1] * 7 + np.nonzero(X)[1]]), return_counts=True)
    got = measure.entropy(s, 0, encode.row_marks(view)).first()
    assert got.total == n.sum() and got.h == pytest.approx(-(n * np.log2(n / n.sum())).sum() / n.sum())
