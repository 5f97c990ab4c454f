"""All queries of the library itself, by name, with their SQL counterparts."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sqlfn
from ..operators import baseline, encode, measure, multiply, relational, reorder
from ..plans import choose
from ..streaming import append
from . import experiments, standins, surface

BLOCKS = 4
_Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}


def _query(name: str, sql: str | None = None):
    def add(f):
        _Q[name] = f
        if sql is not None:
            _SQL[name] = sql
        return f

    return add


def _cells(name: str) -> str:
    return f"WITH cells AS ({standins.long_sql(name)})"


def _right_sql(name: str) -> str:
    return f"{_cells(name)}, ids AS ({standins.rows_sql(name)}) SELECT i.row_id::BIGINT AS row_id, round(coalesce(sum(val * (col + 1)), 0), 2) AS y FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id"


def _left_sql(name: str) -> str:
    return f"{_cells(name)} SELECT col::INTEGER AS col, round(sum(val * (1 + row_id % 7)), 2) AS x FROM cells GROUP BY col"


def _long_sql(name: str) -> str:
    return f"{_cells(name)} SELECT row_id::BIGINT AS row_id, col::INTEGER AS col, val FROM cells"


def _round_y(df: DataFrame) -> DataFrame:
    return df.select("row_id", (F.round("y", 2) + 0.0).alias("y"))


def _round_x(df: DataFrame) -> DataFrame:
    return df.select(F.col("col").cast("int").alias("col"), (F.round("x", 2) + 0.0).alias("x"))


def _vector(spark: SparkSession, x: np.ndarray, digits: int | None = None) -> DataFrame:
    return spark.createDataFrame([(i, float(v) if digits is None else round(float(v), digits) + 0.0) for i, v in enumerate(x)], "col int, x double")


def _nonzero(df: DataFrame) -> DataFrame:
    return df.where("x <> 0")


_DICT = f"dict AS (SELECT val AS value, row_number() OVER (ORDER BY val) - 1 AS code FROM (SELECT DISTINCT val FROM cells))"


@_query("value_dictionary", f"{_cells('lineitem_measures')}, {_DICT} SELECT code::BIGINT AS code, value FROM dict")
def _(spark, d):
    return encode.dictionary(standins.view(spark, d, "lineitem_measures"))


@_query("stream_symbols", f"{_cells('lineitem_onehot')}, {_DICT} SELECT 0 AS block, row_id::BIGINT AS row_id, (row_number() OVER (PARTITION BY row_id ORDER BY col) - 1)::INTEGER AS pos, (1 + code * 33 + col)::BIGINT AS sym FROM cells JOIN dict ON val = value")
def _(spark, d):
    return encode.stream(standins.view(spark, d, "lineitem_onehot"))


@_query("stream_row_greedy_roundtrip", _long_sql("events_user_day"))
def _(spark, d):
    v = standins.view(spark, d, "events_user_day")
    codes = encode.dictionary(v, "frequency")
    return encode.decode_stream(encode.stream(v, codes, "row_greedy", BLOCKS), codes, v.m)


@_query("csr_pointers", f"{_cells('events_user_day')}, ids AS ({standins.rows_sql('events_user_day')}), k AS (SELECT i.row_id, count(val) AS nnz FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id) SELECT row_id::BIGINT AS row_id, nnz::BIGINT AS nnz, (sum(nnz) OVER (ORDER BY row_id) - nnz)::BIGINT AS first FROM k")
def _(spark, d):
    return encode.csr_pointers(standins.view(spark, d, "events_user_day"))


for _codec in ("stream", "g32", "gpack", "gans"):

    def _decode_query(spark, d, codec=_codec):
        return multiply.decode(multiply.compress(standins.view(spark, d, "lineitem_onehot"), BLOCKS, codec, scope="block"))

    _query(f"decode_roundtrip_{_codec}", _long_sql("lineitem_onehot"))(_decode_query)

    def _right_query(spark, d, codec=_codec):
        v = standins.view(spark, d, "lineitem_measures")
        return _round_y(multiply.right(multiply.compress(v, BLOCKS, codec), np.arange(1.0, v.m + 1)))

    _query(f"right_{_codec}", _right_sql("lineitem_measures"))(_right_query)

    def _left_query(spark, d, codec=_codec):
        v = standins.view(spark, d, "lineitem_onehot")
        return _round_x(multiply.left(multiply.compress(v, BLOCKS, codec), standins.y_frame(v)))

    _query(f"left_{_codec}", _left_sql("lineitem_onehot"))(_left_query)


@_query("right_scan", _right_sql("lineitem_measures"))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_measures")
    codes = encode.dictionary(v)
    return _round_y(encode.right_scan(encode.stream(v, codes), codes, v.m, standins.x_frame(spark, v.m)))


@_query("left_scan", _left_sql("lineitem_onehot"))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    codes = encode.dictionary(v, "any")
    return _round_x(encode.left_scan(encode.stream(v, codes), codes, v.m, standins.y_frame(v)))


@_query("right_dense", _right_sql("star_codes"))
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    return _round_y(encode.right_dense(v, standins.x_frame(spark, v.m)))


@_query("left_dense", _left_sql("star_codes"))
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    return _round_x(encode.left_dense(v, standins.y_frame(v)))


@_query("right_relational", _right_sql("lineitem_onehot"))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    return _round_y(relational.right(relational.build(v), standins.x_frame(spark, v.m)))


@_query("left_relational", _left_sql("lineitem_onehot"))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    return _round_x(relational.left(relational.build(v), standins.y_frame(v)))


@_query("expand_relational", _long_sql("conversation_roles"))
def _(spark, d):
    return relational.expand(relational.build(standins.view(spark, d, "conversation_roles"))).select(F.col("row_id"), F.col("col").cast("int").alias("col"), "val")


@_query("pair_frequency_round1", f"{_cells('lineitem_onehot')}, s AS (SELECT row_id, dense_rank() OVER (ORDER BY col, val) AS sym, col FROM cells), p AS (SELECT sym AS a, lead(sym) OVER (PARTITION BY row_id ORDER BY col) AS b FROM s) SELECT a::BIGINT AS \"left\", b::BIGINT AS \"right\", count(*)::BIGINT AS n FROM p WHERE b IS NOT NULL GROUP BY a, b")
def _(spark, d):
    return relational.pairs_of(relational.symbol_rows(standins.view(spark, d, "lineitem_onehot"))[0])


for _side in ("right", "left"):

    def _normal(spark, d, side=_side):
        v = standins.view(spark, d, "events_user_day")
        g = multiply.compress(v, BLOCKS, "gpack", row_normal=True)
        return _round_y(multiply.right(g, np.arange(1.0, v.m + 1))) if side == "right" else _nonzero(_round_x(multiply.left(g, standins.y_frame(v))))

    _query(f"{_side}_normal_form", _right_sql("events_user_day") if _side == "right" else _left_sql("events_user_day"))(_normal)

for _method in ("heap", "batched", "sequential", "longest", "greedy"):

    def _built(spark, d, method=_method):
        v = standins.view(spark, d, "conversation_roles")
        return _round_y(multiply.right(multiply.compress(v, 2, "g32", method=method), np.arange(1.0, v.m + 1)))

    _query(f"right_method_{_method}", _right_sql("conversation_roles"))(_built)

_GRAM = "y AS (SELECT row_id, sum(val * (col + 1)) AS y FROM cells GROUP BY row_id)"


@_query("gram_apply", f"{_cells('events_user_day')}, {_GRAM} SELECT col::INTEGER AS col, round(sum(val * y), 2) AS x FROM cells JOIN y USING (row_id) GROUP BY col")
def _(spark, d):
    v = standins.view(spark, d, "events_user_day")
    return _nonzero(_round_x(_vector(spark, multiply.gram_apply(multiply.compress(v, BLOCKS, "gans"), np.arange(1.0, v.m + 1)))))


def _loop_sql(name: str, m: int, rounds: int) -> str:
    out = f"{_cells(name)}, x0 AS (SELECT unnest(range({m})) AS col, 1.0::DOUBLE AS x)"
    for k in range(rounds):
        out += (
            f", y{k} AS (SELECT row_id, sum(val * x) AS y FROM cells JOIN x{k} USING (col) GROUP BY row_id), z{k} AS (SELECT col, sum(val * y) AS z FROM cells JOIN y{k} USING (row_id) GROUP BY col)"
            f", x{k + 1} AS (SELECT col, z / (SELECT max(abs(z)) FROM z{k}) AS x FROM z{k})"
        )
    return f"{out} SELECT col::INTEGER AS col, round(x, 6) AS x FROM x{rounds} WHERE round(x, 6) <> 0"


@_query("loop_rounds_3", _loop_sql("lineitem_onehot", 33, 3))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    x, _ = multiply.iterate(multiply.compress(v, BLOCKS, "gpack").prepared(), np.ones(v.m), 3)
    return _nonzero(_vector(spark, x, 6))


@_query("right_batch", f"{_cells('events_user_day')}, ids AS ({standins.rows_sql('events_user_day')}) SELECT i.row_id::BIGINT AS row_id, coalesce(sum(val * (col + 1)), 0) AS y0, coalesce(sum(val), 0) AS y1 FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id")
def _(spark, d):
    v = standins.view(spark, d, "events_user_day")
    x = np.stack([np.arange(1.0, v.m + 1), np.ones(v.m)], axis=1)
    return multiply.right(multiply.compress(v, BLOCKS, "gpack"), x).select("row_id", F.col("y")[0].alias("y0"), F.col("y")[1].alias("y1"))


@_query("symbol_sums", f"{_cells('events_user_day')} SELECT col::INTEGER AS col, val, sum(1 + row_id % 7)::DOUBLE AS total FROM cells GROUP BY col, val")
def _(spark, d):
    return multiply.symbol_sums(multiply.compress(standins.view(spark, d, "events_user_day"), BLOCKS), standins.y_of)


@_query("reach", _long_sql("conversation_roles"))
def _(spark, d):
    return multiply.reach(multiply.compress(standins.view(spark, d, "conversation_roles"), 2)).where("col >= 0").select("row_id", "col", "val")


@_query("decode_rows", f"{_cells('events_user_day')} SELECT row_id::BIGINT AS row_id, col::INTEGER AS col, val FROM cells WHERE row_id IN (3, 7, 50)")
def _(spark, d):
    return multiply.decode(multiply.compress(standins.view(spark, d, "events_user_day"), BLOCKS, "gans"), [3, 7, 50])


@_query("column_sums", f"{_cells('lineitem_measures')} SELECT col::INTEGER AS col, round(sum(val), 2) AS x FROM cells GROUP BY col")
def _(spark, d):
    return _round_x(_vector(spark, multiply.column_sums(multiply.compress(standins.view(spark, d, "lineitem_measures"), BLOCKS))))


@_query("row_sums", f"{_cells('lineitem_measures')} SELECT row_id::BIGINT AS row_id, round(sum(val), 2) AS y FROM cells GROUP BY row_id")
def _(spark, d):
    return _round_y(multiply.row_sums(multiply.compress(standins.view(spark, d, "lineitem_measures"), BLOCKS, scope="block")))


@_query("scaled_right", _right_sql("lineitem_measures").replace("sum(val", "2 * sum(val"))
def _(spark, d):
    v = standins.view(spark, d, "lineitem_measures")
    return _round_y(multiply.right(multiply.scale(multiply.compress(v, BLOCKS), 2.0), np.arange(1.0, v.m + 1)))


def _sim_sql(name: str) -> str:
    return (
        f"{_cells(name)}, p AS (SELECT a.col AS ci, b.col AS cj, a.val AS vi, b.val AS vj, count(*) AS c FROM cells a JOIN cells b ON a.row_id = b.row_id AND a.col < b.col GROUP BY 1, 2, 3, 4)"
        f" SELECT ci::INTEGER AS ci, cj::INTEGER AS cj, sum(c - 1)::BIGINT AS rep, round(sum(c - 1) / (SELECT count(*) FROM ({standins.rows_sql(name)}) z)::DOUBLE, 9) AS score FROM p GROUP BY ci, cj"
    )


def _scores(df: DataFrame) -> DataFrame:
    return df.select("ci", "cj", F.col("rep").cast("long").alias("rep"), F.round("score", 9).alias("score"))


for _engine in ("hash", "sort"):
    _query(f"similarity_{_engine}", _sim_sql("star_codes"))(lambda spark, d, e=_engine: _scores(reorder.similarity(standins.view(spark, d, "star_codes"), e)))
for _k in (4, 8, 16):
    _sql = _sim_sql("star_codes") + ")"
    _query(
        f"prune_local_k{_k}",
        f"WITH sim AS ({_sim_sql('star_codes')}), both_ AS (SELECT *, ci AS own, cj AS other FROM sim UNION ALL SELECT *, cj, ci FROM sim), r AS (SELECT *, row_number() OVER (PARTITION BY own ORDER BY rep DESC, other) AS r FROM both_) SELECT DISTINCT ci, cj, rep, score FROM r WHERE r <= {_k}",
    )(lambda spark, d, k=_k: _scores(reorder.prune_local(reorder.similarity(standins.view(spark, d, "star_codes")), k)))
    _query(f"prune_global_k{_k}", f"SELECT * FROM ({_sim_sql('star_codes')}) z ORDER BY rep DESC, ci, cj LIMIT {8 * _k}")(
        lambda spark, d, k=_k: _scores(reorder.prune_global(reorder.similarity(standins.view(spark, d, "star_codes")), k, 16))
    )

for _algorithm in reorder.ALGORITHMS:

    def _reordered(spark, d, a=_algorithm):
        v = standins.view(spark, d, "star_codes")
        order = reorder.ALGORITHMS[a](reorder.edges_of(reorder.prune_local(reorder.similarity(v), 8)), v.m)
        return _round_y(multiply.right(multiply.compress(v, BLOCKS, "gpack", order=order), np.arange(1.0, v.m + 1)))

    _query(f"right_after_{_algorithm}", _right_sql("star_codes"))(_reordered)

for _side in ("right", "left"):

    def _blockwise(spark, d, side=_side):
        v = standins.view(spark, d, "star_codes")
        g, _ = reorder.blockwise(v, BLOCKS)
        return _round_y(multiply.right(g, np.arange(1.0, v.m + 1))) if side == "right" else _round_x(multiply.left(g, standins.y_frame(v)))

    _query(f"blockwise_{_side}", _right_sql("star_codes") if _side == "right" else _left_sql("star_codes"))(_blockwise)

    def _grouped(spark, d, side=_side):
        v = standins.view(spark, d, "star_codes")
        g = baseline.column_groups(v)
        return _round_y(baseline.groups_right(g, np.arange(1.0, v.m + 1))) if side == "right" else _round_x(baseline.groups_left(g, standins.y_frame(v)))

    _query(f"colgroup_{_side}", _right_sql("star_codes") if _side == "right" else _left_sql("star_codes"))(_grouped)


@_query(
    "size_accounting",
    " UNION ALL ".join(
        f"SELECT * FROM ({_cells(n)}, ids AS ({standins.rows_sql(n)}) SELECT '{n}' AS matrix, (SELECT count(*) FROM ids)::BIGINT AS n, {len(standins.EXPRESSIONS[n][1])}::BIGINT AS m, count(*)::BIGINT AS t, count(DISTINCT val)::BIGINT AS \"distinct\", (4 * (count(*) + (SELECT count(*) FROM ids)) + 8 * count(DISTINCT val))::BIGINT AS stream_bytes FROM cells) z"
        for n in standins.EXPRESSIONS
    ),
)
def _(spark, d):
    out = None
    for n in standins.EXPRESSIONS:
        f = measure.features(standins.view(spark, d, n)).select(F.lit(n).alias("matrix"), "n", "m", "t", "distinct", (4 * (F.col("t") + F.col("n")) + 8 * F.col("distinct")).cast("long").alias("stream_bytes"))
        out = f if out is None else out.union(f)
    return out


def _entropy_sql(k: int) -> str:
    ctx = "''" if not k else "concat_ws(',', " + ", ".join(f"coalesce(lag(sym, {i}) OVER w::VARCHAR, '-')" for i in range(1, k + 1)) + ")"
    return (
        f"{_cells('lineitem_onehot')}, {_DICT}, s AS (SELECT row_id, col, 1 + code * 33 + col AS sym FROM cells JOIN dict ON val = value UNION ALL SELECT DISTINCT row_id, 99, 0 FROM cells),"
        f" q AS (SELECT sym, {ctx} AS ctx FROM s WINDOW w AS (ORDER BY row_id, col)), c AS (SELECT ctx, sym, count(*) AS c FROM q GROUP BY ctx, sym), t AS (SELECT ctx, sum(c) AS cc FROM c GROUP BY ctx)"
        f" SELECT sum(c)::BIGINT AS total, round(sum(-c * log2(c / cc::DOUBLE)) / sum(c), 6) AS h FROM c JOIN t USING (ctx)"
    )


for _k in (0, 1, 2):
    _query(f"entropy_h{_k}", _entropy_sql(_k))(
        lambda spark, d, k=_k: measure.entropy(encode.stream(standins.view(spark, d, "lineitem_onehot")), k).select(F.col("total").cast("long").alias("total"), F.round("h", 6).alias("h"))
    )


@_query("sparse_sizes", f"{_cells('star_codes')}, k AS (SELECT count(*) AS t, count(DISTINCT val) AS v, (SELECT count(*) FROM ({standins.rows_sql('star_codes')}) z) AS n FROM cells) SELECT unnest(['csr', 'csr_iv', 'stream', 'dense']) AS method, unnest([12 * t + 8 * (n + 1), (4 + CASE WHEN v < 65536 THEN 2 ELSE 4 END) * t + 8 * (n + 1) + 8 * v, 4 * (t + n) + 8 * v, 8 * n * 16])::BIGINT AS bytes FROM k")
def _(spark, d):
    return baseline.sparse_sizes(standins.view(spark, d, "star_codes"))


@_query("peak_memory")
def _(spark, d):
    return measure.product_peaks(multiply.compress(standins.view(spark, d, "star_codes"), BLOCKS))


@_query("chooser_right", _right_sql("star_codes"))
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    return _round_y(multiply.right(choose.choose(v, 8 * v.n * v.m, BLOCKS), np.arange(1.0, v.m + 1)))


@_query("doc_chars_right", "SELECT doc_id::BIGINT AS row_id, round((" + " + ".join(f"(length(text) - length(replace(text, chr({c}), ''))) * {c - 31}" for c in range(32, 127)) + ")::DOUBLE, 2) AS y FROM documents")
def _(spark, d):
    v = standins.view(spark, d, "doc_chars")
    return _round_y(multiply.right(multiply.compress(v, BLOCKS, "gans"), np.arange(1.0, v.m + 1)))


@_query("stream_append_right", _right_sql("events_user_day"))
def _(spark, d):
    return _round_y(append.replay_events(spark, d))


@_query("windowed_events", "SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def _(spark, d):
    return append.daily_counts(spark, d).withColumn("day", F.col("day").cast("string"))


@_query("sql_right", _right_sql("conversation_roles"))
def _(spark, d):
    return _round_y(sqlfn.right_by_sql(spark, standins.view(spark, d, "conversation_roles")))


@_query("sql_expand_block", _long_sql("conversation_roles"))
def _(spark, d):
    return sqlfn.expand_by_udtf(spark, standins.view(spark, d, "conversation_roles"))


@_query("cube_size_report", f"{_cells('lineitem_onehot')} SELECT coalesce(block::INTEGER, -1) AS block, coalesce(col::INTEGER, -1) AS col, count(*)::BIGINT AS n FROM (SELECT row_id // (SELECT ((count(*) + 3) // 4) FROM lineitem) AS block, col FROM cells) z GROUP BY CUBE (block, col)")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    return v.cells.select(v.block_of(4).alias("block"), "col").cube("block", "col").agg(F.count("*").alias("n")).select(F.coalesce("block", F.lit(-1)).alias("block"), F.coalesce("col", F.lit(-1)).alias("col"), "n")


_HALF = "h AS (SELECT DISTINCT col, val, row_id < (SELECT (count(*) + 1) // 2 FROM lineitem) AS first FROM cells)"
for _name, _op, _method in (("symbol_overlap", "INTERSECT", "intersect"), ("symbol_difference", "EXCEPT", "exceptAll")):

    def _sets(spark, d, method=_method):
        v = standins.view(spark, d, "lineitem_measures")
        half = (v.n + 1) // 2
        parts = [v.cells.where(F.col("row_id") < half).select("col", "val").distinct(), v.cells.where(F.col("row_id") >= half).select("col", "val").distinct()]
        return getattr(parts[0], method)(parts[1])

    _query(_name, f"{_cells('lineitem_measures')}, {_HALF} SELECT col::INTEGER AS col, val FROM h WHERE first {_op} SELECT col::INTEGER, val FROM h WHERE NOT first")(_sets)


@_query("value_predicate", f"{_cells('lineitem_measures')} SELECT row_id::BIGINT AS row_id, col::INTEGER AS col, val FROM cells WHERE val > 1000")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_measures")
    codes = encode.dictionary(v)
    hits = codes.where("value > 1000")  # each distinct value is tested once
    s = encode.stream(v, codes).withColumn("code", encode.code_of(F.col("sym"), v.m))
    return encode.decode_stream(s.join(hits.select("code"), "code", "left_semi"), codes, v.m).select("row_id", F.col("col").cast("int").alias("col"), "val")


for _name, (_f, _sql) in surface.QUERIES.items():
    _query(_name, _sql)(_f)
for _name, _f in experiments.QUERIES.items():
    _query(_name)(_f)
_query("w_sizes_counted", experiments.counted_sizes_sql())(experiments.counted_sizes)
for _name in standins.EXPRESSIONS:
    _vectors = " UNION ALL ".join(f"SELECT '{c}' AS codec, {b}::INTEGER AS blocks, col, x FROM l" for c in experiments.CODECS for b in (1, 4, 16))
    _query(f"w_loop_vectors_{_name}", f"WITH l AS ({_loop_sql(_name, standins.width(_name), 3)}) {_vectors}")(lambda spark, d, n=_name: experiments.loop_vectors(spark, d, n, blocks=(1, 4, 16)))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """y = Mx on exact grammars of the one-hot line items."""
    v = standins.view(spark, sf_dir, "lineitem_onehot")
    return multiply.right(multiply.compress(v, BLOCKS, "g32"), np.arange(1.0, v.m + 1))


def queries() -> dict:
    return dict(_Q)


def oracle_sql() -> dict:
    return dict(_SQL)
