"""Queries of measures, sources, joins, views and further products, each with its SQL counterpart: name -> (query, SQL)."""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import sqlfn
from ..model import cut, shared_folder
from ..operators import baseline, encode, measure, multiply, reorder, temporal
from ..plans import choose
from ..sources import matrices as src
from . import standins

BLOCKS = 4
QUERIES: dict = {}


def _query(name: str, sql: str):
    def add(f):
        QUERIES[name] = (f, sql)
        return f

    return add


def _cells(name: str) -> str:
    return f"WITH cells AS ({standins.long_sql(name)}), ids AS ({standins.rows_sql(name)})"


_DICT = "dict AS (SELECT val AS value, row_number() OVER (ORDER BY val) - 1 AS code FROM (SELECT DISTINCT val FROM cells))"
_PLACED = f"placed AS (SELECT row_id, (row_number() OVER (ORDER BY row_id) - 1) // ((SELECT count(*) + {BLOCKS - 1} FROM ids) // {BLOCKS}) AS block FROM ids)"
_LONG = "SELECT row_id::BIGINT AS row_id, col::INTEGER AS col, val FROM cells"


def _zipped(df: DataFrame) -> DataFrame:
    return df.select("block", F.posexplode(F.arrays_zip("nz", "idx")).alias("pos", "x")).select("block", "pos", F.col("x.idx").alias("idx"), F.col("x.nz").alias("nz"))


@_query("csr_blocks", f"{_cells('events_user_day')}, {_PLACED} SELECT block::INTEGER AS block, (row_number() OVER (PARTITION BY block ORDER BY row_id, col) - 1)::INTEGER AS pos, col::INTEGER AS idx, val AS nz FROM cells JOIN placed USING (row_id)")
def _(spark, d):
    return _zipped(encode.csr(standins.view(spark, d, "events_user_day"), BLOCKS))


@_query("csr_iv_blocks", f"{_cells('events_user_day')}, {_PLACED}, {_DICT} SELECT block::INTEGER AS block, (row_number() OVER (PARTITION BY block ORDER BY row_id, col) - 1)::INTEGER AS pos, col::INTEGER AS idx, code::INTEGER AS nz FROM cells JOIN placed USING (row_id) JOIN dict ON val = value")
def _(spark, d):
    return _zipped(encode.csr_iv(standins.view(spark, d, "events_user_day"), blocks=BLOCKS))


@_query(
    "csr_row_starts",
    f"{_cells('label_bits')}, {_PLACED}, k AS (SELECT p.row_id, block, count(val) AS nnz FROM placed p LEFT JOIN cells c ON p.row_id = c.row_id GROUP BY 1, 2)"
    " SELECT block::INTEGER AS block, (row_number() OVER (PARTITION BY block ORDER BY row_id) - 1)::INTEGER AS pos, (sum(nnz) OVER (PARTITION BY block ORDER BY row_id) - nnz)::BIGINT AS first FROM k"
    " UNION ALL SELECT block::INTEGER, count(*)::INTEGER, sum(nnz)::BIGINT FROM k GROUP BY block",
)
def _(spark, d):
    return encode.csr(standins.view(spark, d, "label_bits"), BLOCKS).select("block", F.posexplode("first").alias("pos", "first"))


@_query("blocks_of_any_ids", f"{_cells('label_bits')}, {_PLACED} SELECT block::INTEGER AS block, count(*)::BIGINT AS n_rows FROM placed GROUP BY block")
def _(spark, d):
    return multiply.compress(standins.view(spark, d, "label_bits"), BLOCKS).explain().select("block", "n_rows")


@_query("right_any_ids", f"{_cells('label_bits')} SELECT (i.row_id * 1000003 - 4000000000000000000)::BIGINT AS row_id, coalesce(sum(val * (col + 1)), 0) AS y FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id")
def _(spark, d):
    v = standins.view(spark, d, "label_bits")
    far = type(v)(v.rows.withColumn("row_id", F.col("row_id") * 1000003 - 4000000000000000000), v.m)
    return multiply.right(multiply.compress(far, BLOCKS), np.arange(1.0, v.m + 1))


for _k in (0, 1, 2):
    _ctx = "''" if not _k else "concat_ws(',', " + ", ".join(f"coalesce(lag(sym, {i}) OVER w::VARCHAR, '-')" for i in range(1, _k + 1)) + ")"
    _sql = (
        f"{_cells('label_bits')}, {_DICT}, s AS (SELECT row_id, col, 1 + code * 2 + col AS sym FROM cells JOIN dict ON val = value UNION ALL SELECT row_id, 99, 0 FROM ids),"
        f" q AS (SELECT sym, {_ctx} AS ctx FROM s WINDOW w AS (ORDER BY row_id, col)), c AS (SELECT ctx, sym, count(*) AS c FROM q GROUP BY ctx, sym), t AS (SELECT ctx, sum(c) AS cc FROM c GROUP BY ctx)"
        f" SELECT sum(c)::BIGINT AS total, round(sum(-c * log2(c / cc::DOUBLE)) / sum(c), 6) AS h FROM c JOIN t USING (ctx)"
    )

    def _entropy(spark, d, k=_k):
        v = standins.view(spark, d, "label_bits")
        return measure.entropy(encode.stream(v), k, encode.row_marks(v)).select(F.col("total").cast("long").alias("total"), F.round("h", 6).alias("h"))

    QUERIES[f"entropy_empty_rows_h{_k}"] = (_entropy, _sql)


@_query(
    "cgls_solution",
    f"{_cells('label_bits')}, y AS (SELECT row_id, 1 + row_id % 7 AS y FROM ids), a AS (SELECT row_id, sum(CASE WHEN col = 0 THEN val ELSE 0 END) AS p, sum(CASE WHEN col = 1 THEN val ELSE 0 END) AS q FROM cells GROUP BY row_id),"
    " g AS (SELECT sum(p * p) AS pp, sum(p * q) AS pq, sum(q * q) AS qq, sum(p * y) AS py, sum(q * y) AS qy FROM a JOIN y USING (row_id))"
    " SELECT 0 AS col, round((qq * py - pq * qy) / (pp * qq - pq * pq), 6) AS x FROM g UNION ALL SELECT 1, round((pp * qy - pq * py) / (pp * qq - pq * pq), 6) FROM g",
)
def _(spark, d):
    v = standins.view(spark, d, "label_bits")
    x = multiply.cgls(multiply.compress(v, BLOCKS).prepared(), standins.y_frame(v))
    return spark.createDataFrame([(i, round(float(z), 6)) for i, z in enumerate(x)], "col int, x double")


def _similar(cells: str, n: str) -> str:
    return (
        f"{cells}, p AS (SELECT a.col AS ci, b.col AS cj, a.val AS vi, b.val AS vj, count(*) AS c FROM cells a JOIN cells b ON a.row_id = b.row_id AND a.col < b.col GROUP BY 1, 2, 3, 4)"
        f" SELECT ci::INTEGER AS ci, cj::INTEGER AS cj, sum(c - 1)::BIGINT AS rep, round(sum(c - 1) / ({n})::DOUBLE, 9) AS score FROM p GROUP BY ci, cj"
    )


_DRAWN = "('0x' || substr(md5('1:' || row_id::VARCHAR), 1, 6))::BIGINT < 1677721"


@_query(
    "similarity_sampled",
    _similar(f"WITH cells AS (SELECT * FROM ({standins.long_sql('star_codes')}) z WHERE {_DRAWN})", f"SELECT count(*) FROM ({standins.rows_sql('star_codes')}) z WHERE {_DRAWN}"),
)
def _(spark, d):
    s = reorder.similarity(standins.view(spark, d, "star_codes"), sample=0.1)
    return s.select("ci", "cj", F.col("rep").cast("long").alias("rep"), F.round("score", 9).alias("score"))


@_query("similarity_sketch_near", f"{_cells('star_codes')} SELECT DISTINCT a.col::INTEGER AS ci, b.col::INTEGER AS cj, true AS near FROM cells a JOIN cells b ON a.row_id = b.row_id AND a.col < b.col")
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    far = reorder.similarity(v, "sketch").select("ci", "cj", F.col("score").alias("est"))
    return reorder.similarity(v).join(far, ["ci", "cj"]).select("ci", "cj", (F.abs(F.col("score") - F.col("est")) < 0.05).alias("near"))


def _star_edges(spark, d):
    v = standins.view(spark, d, "star_codes")
    return v, reorder.edges_of(reorder.prune_local(reorder.similarity(v), 8))


_PRUNED = (
    f"sim AS ({_similar(_cells('star_codes'), 'SELECT count(*) FROM ids')}), two AS (SELECT *, ci AS own, cj AS other FROM sim UNION ALL SELECT *, cj, ci FROM sim),"
    " r AS (SELECT *, row_number() OVER (PARTITION BY own ORDER BY rep DESC, other) AS r FROM two), e AS (SELECT ci, cj, row_number() OVER (ORDER BY rep DESC, ci, cj) AS k FROM (SELECT DISTINCT ci, cj, rep FROM r WHERE r <= 8 AND rep > 0))"
)


@_query(
    "order_paths_links",
    f"WITH RECURSIVE {_PRUNED}, st AS (SELECT 0::BIGINT AS k, list_transform(range(16), lambda z: 0::BIGINT) AS deg, range(16) AS comp, false AS took UNION ALL"
    " SELECT e.k, CASE WHEN ok THEN list_transform(deg, lambda z, i: CASE WHEN i IN (ci + 1, cj + 1) THEN z + 1 ELSE z END) ELSE deg END,"
    " CASE WHEN ok THEN list_transform(comp, lambda z: CASE WHEN z = comp[ci + 1] THEN comp[cj + 1] ELSE z END) ELSE comp END, ok"
    " FROM (SELECT e.k, ci, cj, deg, comp, deg[ci + 1] < 2 AND deg[cj + 1] < 2 AND comp[ci + 1] <> comp[cj + 1] AS ok FROM st JOIN e ON e.k = st.k + 1) e)"
    " SELECT ci::INTEGER AS a, cj::INTEGER AS b FROM st JOIN e ON st.k = e.k WHERE took",
)
def _(spark, d):
    v, edges = _star_edges(spark, d)
    return spark.createDataFrame(reorder.path_links(edges, v.m), "a int, b int")


for _name in ("identity", "reverse"):
    QUERIES[f"order_{_name}"] = (
        lambda spark, d, a=_name: spark.createDataFrame(list(enumerate(reorder.ALGORITHMS[a]([], 16))), "pos int, col int"),
        f"SELECT range::INTEGER AS pos, {'range' if _name == 'identity' else '15 - range'}::INTEGER AS col FROM range(16)",
    )


@_query("order_scores", "SELECT unnest(['tour', 'paths', 'matching', 'coalesced']) AS algorithm, 16::BIGINT AS columns, true AS beats_the_given_order, unnest([true, true, false, false]) AS at_least_greedy")
def _(spark, d):
    v, edges = _star_edges(spark, d)
    score = lambda o: reorder.order_score(o, edges) + 1e-9
    greedy, given = reorder.order_score(reorder.paths(edges, v.m), edges), reorder.order_score(list(range(v.m)), edges)
    rows = []
    for a in ("tour", "paths", "matching", "coalesced"):
        o = reorder.ALGORITHMS[a](edges, v.m)
        rows.append((a, len(set(o)), score(o) > given, score(o) >= greedy if a in ("tour", "paths") else False))
    return spark.createDataFrame(rows, "algorithm string, columns long, beats_the_given_order boolean, at_least_greedy boolean")


@_query("rle_bytes", f"WITH v AS (SELECT row_id, col, val FROM ({standins.long_sql('star_codes').replace(' WHERE val <> 0', '')}) z), r AS (SELECT val <> lag(val) OVER (ORDER BY row_id, col) AS fresh FROM v) SELECT (12 * (1 + count(*) FILTER (WHERE fresh)))::BIGINT AS bytes FROM r")
def _(spark, d):
    return baseline.byte_sizes(standins.view(spark, d, "star_codes"), ("rle",)).select("bytes")


@_query("bytes_below_dense", "SELECT unnest(['gzip', 'xz', 'bz2', 'huffman', 'rle']) AS method, unnest([true, true, true, true, false]) AS below_dense")
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    s = baseline.byte_sizes(v, tuple(baseline.COMPRESSORS), BLOCKS).groupBy("method").agg(F.sum("bytes").alias("b"))
    return s.select("method", (F.col("b") < baseline.dense_bytes(v.n, v.m)).alias("below_dense"))


@_query("grammar_shape", f"{_cells('star_codes')} SELECT (count(*) + (SELECT count(*) FROM ids))::BIGINT AS s_len, (16 * (SELECT count(*) FROM ids))::BIGINT AS dense, true AS shorter, true AS fewer_additions, true AS size_adds_up, true AS has_depth FROM cells")
def _(spark, d):
    g = multiply.compress(standins.view(spark, d, "star_codes"), BLOCKS).prepared()
    size = measure.grammar_size(g)
    both = measure.shape(g).crossJoin(measure.operations(g))  # one row each
    return both.select(
        "s_len", F.col("dense").cast("long").alias("dense"), (F.lit(size) < F.col("s_len")).alias("shorter"), (F.col("compressed") < F.col("stream")).alias("fewer_additions"),
        (F.lit(size) == F.col("c_len") + 2 * F.col("r_len")).alias("size_adds_up"), (F.col("depth") > 1).alias("has_depth"),
    )


@_query("codec_sizes_fall", "SELECT unnest(['stream', 'g32', 'gpack', 'gans']) AS codec, unnest([true, true, true, true]) AS no_larger_than_the_one_before")
def _(spark, d):
    sizes = choose.report(standins.view(spark, d, "star_codes"), 1)
    names = ("stream", "g32", "gpack", "gans")
    return spark.createDataFrame([(c, i == 0 or sizes[c] <= sizes[names[i - 1]]) for i, c in enumerate(names)], "codec string, no_larger_than_the_one_before boolean")


@_query(
    "quantised_features",
    "WITH v AS (SELECT round(unnest(embedding)::DOUBLE, 1) AS x FROM embeddings) SELECT (SELECT count(*) FROM embeddings)::BIGINT AS n, 64::BIGINT AS m, count(*)::BIGINT AS t,"
    " round(count(*) * 100.0 / (64 * (SELECT count(*) FROM embeddings)), 6)::DOUBLE AS nonzero_pct, count(DISTINCT x)::BIGINT AS \"distinct\" FROM v WHERE x <> 0",
)
def _(spark, d):
    return measure.features(standins.view(spark, d, "embeddings_q1")).withColumn("nonzero_pct", F.round("nonzero_pct", 6))


@_query("symbol_values", f"{_cells('conversation_roles')}, {_DICT}, s AS (SELECT DISTINCT 1 + code * 3 + col AS sym, val * (col + 1) AS w FROM cells JOIN dict ON val = value) SELECT 0 AS block, (row_number() OVER (ORDER BY sym) - 1)::BIGINT AS symbol, w FROM s")
def _(spark, d):
    v = standins.view(spark, d, "conversation_roles")
    return multiply.symbol_values(multiply.compress(v, 1, piece_symbols=1 << 62), np.arange(1.0, v.m + 1)).where(F.col("symbol") < v.cells.select("col", "val").distinct().count())


@_query("left_batch", f"{_cells('events_user_day')} SELECT col::INTEGER AS col, sum(val * (1 + row_id % 7)) AS x0, sum(val) AS x1 FROM cells GROUP BY col")
def _(spark, d):
    v = standins.view(spark, d, "events_user_day")
    y = v.rows.select("row_id", F.array((1 + F.pmod("row_id", F.lit(7))).cast("double"), F.lit(1.0)).alias("y"))
    return multiply.left(multiply.compress(v, BLOCKS), y).select("col", F.col("x")[0].alias("x0"), F.col("x")[1].alias("x1")).where("x1 <> 0")


@_query("transposed_right", f"{_cells('events_user_day')} SELECT col::INTEGER AS col, sum(val * (1 + row_id % 7)) AS x FROM cells GROUP BY col")
def _(spark, d):
    v = standins.view(spark, d, "events_user_day")
    return multiply.transposed(multiply.compress(v, BLOCKS, "gans")).right(standins.y_frame(v)).where("x <> 0")


@_query("column_norms", f"{_cells('lineitem_onehot')} SELECT col::INTEGER AS col, round(sqrt(sum(val * val)), 6) AS x FROM cells GROUP BY col")
def _(spark, d):
    return multiply.norms(multiply.compress(standins.view(spark, d, "lineitem_onehot"), BLOCKS)).select("col", F.round("x", 6).alias("x")).where("x <> 0")


@_query("lossless_error", "SELECT 0.0::DOUBLE AS error, 1.0::DOUBLE AS ratio")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_measures")
    key = (F.col("row_id") * v.m + F.col("col")).alias("key")
    g = multiply.compress(v, BLOCKS, "gans")
    back = multiply.decode(g).select(key, "val")
    return spark.createDataFrame([(measure.max_abs_err(v.cells.select(key, "val"), back, "key", "val"), measure.ratio(float(back.count()), float(v.cells.count())))], "error double, ratio double")


@_query("clustered_rows_right", f"{_cells('star_codes')} SELECT row_id::BIGINT AS row_id, round(sum(val * (col + 1)), 2) AS y FROM cells GROUP BY row_id")
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    near = choose.cluster_rows(v, F.xxhash64(F.slice("vals", 1, 4)))
    y = multiply.right(multiply.compress(near, BLOCKS), np.arange(1.0, v.m + 1))
    return y.join(near.rows.select("row_id", "old_id"), "row_id").select(F.col("old_id").alias("row_id"), (F.round("y", 2) + 0.0).alias("y"))


@_query("stream_row_partner_roundtrip", f"{_cells('conversation_roles')} {_LONG}")
def _(spark, d):
    v = standins.view(spark, d, "conversation_roles")
    codes = encode.dictionary(v)
    return encode.decode_stream(encode.stream(v, codes, "row_partner", BLOCKS), codes, v.m)


@_query("stream_block_orders", f"{_cells('lineitem_onehot')}, {_PLACED}, {_DICT} SELECT block::INTEGER AS block, row_id::BIGINT AS row_id, (row_number() OVER (PARTITION BY row_id ORDER BY CASE WHEN block % 2 = 0 THEN col ELSE -col END) - 1)::INTEGER AS pos, (1 + code * 33 + col)::BIGINT AS sym FROM cells JOIN placed USING (row_id) JOIN dict ON val = value")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    ranks = [(b, c, c if b % 2 == 0 else -c) for b in range(BLOCKS) for c in range(v.m)]
    return encode.stream(v, order=spark.createDataFrame(ranks, "block int, col int, rank int"), blocks=BLOCKS)


@_query("colgroup_roundtrip", f"{_cells('star_codes')} {_LONG}")
def _(spark, d):
    return baseline.groups_decode(baseline.column_groups(standins.view(spark, d, "star_codes")))


@_query("colgroup_bytes", "SELECT true AS no_larger_than_raw, true AS bytes_as_stored")
def _(spark, d):
    v = standins.view(spark, d, "star_codes")
    g = baseline.column_groups(v)
    stored = g.encoded.agg(F.sum("bytes")).first()[0]
    return spark.createDataFrame([(stored <= 8 * v.n * v.m, stored == sum(g.sizes.values()))], "no_larger_than_raw boolean, bytes_as_stored boolean")


@_query("json_source", "SELECT event_id::BIGINT AS row_id, 0 AS col, json_extract(props, '$.k')::DOUBLE AS val FROM events WHERE json_extract(props, '$.k')::DOUBLE <> 0")
def _(spark, d):
    return src.from_json(src.table(spark, d, "events"), "props", ["k"], "event_id").cells.select("row_id", F.col("col").cast("int").alias("col"), "val")


@_query("map_source", "SELECT event_id::BIGINT AS row_id, CASE event_type WHEN 'view' THEN 0 ELSE 1 END AS col, value AS val FROM events WHERE event_type IN ('view', 'click') AND value <> 0")
def _(spark, d):
    events = src.table(spark, d, "events").select("event_id", F.create_map("event_type", "value").alias("kv"))
    return src.from_map(events, "kv", ["view", "click"], "event_id").cells.select("row_id", F.col("col").cast("int").alias("col"), "val")


@_query("one_hot_source", "SELECT event_id::BIGINT AS row_id, CASE event_type WHEN 'view' THEN 0 WHEN 'click' THEN 1 ELSE 2 END AS col, 1.0::DOUBLE AS val FROM events WHERE event_type IN ('view', 'click', 'error')")
def _(spark, d):
    return src.one_hot(src.table(spark, d, "events"), "event_type", ["view", "click", "error"], "event_id").cells.select("row_id", F.col("col").cast("int").alias("col"), "val")


@_query("hashed_words_source", "SELECT doc_id::BIGINT AS row_id, len(list_filter(string_split_regex(lower(coalesce(text, '')), '\\W+'), lambda w: w <> ''))::DOUBLE AS words FROM documents")
def _(spark, d):
    v = src.from_hashed_words(src.table(spark, d, "documents"), "text", 784, "doc_id")
    return multiply.right(multiply.compress(v, BLOCKS, "gans"), np.ones(784)).select("row_id", F.col("y").alias("words"))


@_query("typed_dictionary", "SELECT n_nationkey::BIGINT AS row_id, 0 AS col, n_name AS value FROM nation UNION ALL SELECT n_nationkey, 1, n_regionkey::VARCHAR FROM nation")
def _(spark, d):
    v, codes = src.typed_dictionary(src.table(spark, d, "nation"), ["n_name", "n_regionkey"], "n_nationkey")
    back = multiply.decode(multiply.compress(v, 2, "gans", scope="block"))
    return back.join(codes.select("col", F.col("code").cast("double").alias("val"), "value"), ["col", "val"]).select("row_id", F.col("col").cast("int").alias("col"), "value")


@_query("matrix_market_roundtrip", f"{_cells('events_user_day')} {_LONG}")
def _(spark, d):
    folder = f"{shared_folder(spark)}/mm-{uuid.uuid4().hex}"
    src.write_matrix_market(standins.view(spark, d, "events_user_day"), folder)
    return cut(src.read_matrix_market_parts(spark, folder).cells)


@_query("libsvm_roundtrip", f"{_cells('lineitem_onehot')} {_LONG}")
def _(spark, d):
    folder = f"{shared_folder(spark)}/svm-{uuid.uuid4().hex}"
    src.write_libsvm(standins.view(spark, d, "lineitem_onehot"), folder)
    return cut(src.read_libsvm(spark, folder, 33).cells)


@_query("saved_blocks_right", f"{_cells('lineitem_measures')} SELECT i.row_id::BIGINT AS row_id, round(coalesce(sum(val * (col + 1)), 0), 2) AS y FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id")
def _(spark, d):
    folder = f"{shared_folder(spark)}/blocks-{uuid.uuid4().hex}"
    v = standins.view(spark, d, "lineitem_measures")
    multiply.compress(v, BLOCKS).save(folder)
    return multiply.right(type(multiply.compress(v, 1)).load(spark, folder), np.arange(1.0, v.m + 1)).select("row_id", (F.round("y", 2) + 0.0).alias("y"))


@_query("sql_expand_rules", f"{_cells('conversation_roles')} {_LONG}")
def _(spark, d):
    return sqlfn.expand_by_sql(spark, standins.view(spark, d, "conversation_roles"))


@_query("rollup_size_report", f"{_cells('lineitem_onehot')}, {_PLACED} SELECT coalesce(block::INTEGER, -1) AS block, coalesce(col::INTEGER, -1) AS col, count(*)::BIGINT AS n FROM cells JOIN placed USING (row_id) GROUP BY ROLLUP (block, col)")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    return v.cells.select(v.block_of(BLOCKS).alias("block"), "col").rollup("block", "col").agg(F.count("*").alias("n")).select(F.coalesce("block", F.lit(-1)).alias("block"), F.coalesce("col", F.lit(-1)).alias("col"), "n")


@_query("grouping_sets_size_report", f"{_cells('lineitem_onehot')}, {_PLACED} SELECT coalesce(block::INTEGER, -1) AS block, coalesce(col::INTEGER, -1) AS col, count(*)::BIGINT AS n, round(sum(val), 4) AS total FROM cells JOIN placed USING (row_id) GROUP BY GROUPING SETS ((block), (col))")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_onehot")
    v.cells.withColumn("block", v.block_of(BLOCKS)).createOrReplaceTempView("symmat_placed")
    return spark.sql("SELECT coalesce(block, -1) AS block, coalesce(col, -1) AS col, count(*) AS n, round(sum(val), 4) AS total FROM symmat_placed GROUP BY GROUPING SETS ((block), (col))")


@_query("interval_join_events", "SELECT b.event_id::BIGINT AS event_id, a.event_id::BIGINT AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND epoch(b.ts) >= epoch(a.ts) AND epoch(b.ts) < epoch(a.ts) + 3600 * 24 WHERE a.event_type = 'purchase'")
def _(spark, d):
    events = src.table(spark, d, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    day = 24 * 3600 * 1_000_000
    spans = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("at").alias("start"), (F.col("at") + day).alias("end"))
    return temporal.interval_join(events.select("event_id", "user_id", "at"), spans, ["user_id"], "at", "start", "end", day).select("event_id", "purchase_id")


@_query("as_of_purchase", "WITH s AS (SELECT user_id, ts, max(value) AS value FROM events WHERE event_type = 'purchase' GROUP BY 1, 2) SELECT e.event_id::BIGINT AS event_id, s.value FROM events e ASOF LEFT JOIN s ON e.user_id = s.user_id AND e.ts >= s.ts WHERE e.event_type = 'view'")
def _(spark, d):
    events = src.table(spark, d, "events")
    state = events.where("event_type = 'purchase'").select("user_id", "ts", "value")
    return temporal.as_of(events.where("event_type = 'view'").select("event_id", "user_id", "ts"), state, ["user_id"], "ts", "value").select("event_id", "value")


@_query(
    "row_of_position",
    f"{_cells('events_user_day')}, k AS (SELECT i.row_id, count(val) AS nnz FROM ids i LEFT JOIN cells c ON i.row_id = c.row_id GROUP BY i.row_id), f AS (SELECT row_id, nnz, sum(nnz) OVER (ORDER BY row_id) - nnz AS first FROM k)"
    " SELECT p::BIGINT AS position, row_id::BIGINT AS row_id FROM range(0, 5000, 7) t(p) JOIN f ON p >= first AND p < first + nnz",
)
def _(spark, d):
    starts = encode.csr_pointers(standins.view(spark, d, "events_user_day")).select("row_id", "first", (F.col("first") + F.col("nnz")).alias("end"), F.lit(0).alias("k"))
    points = spark.range(0, 5000, 7).select(F.col("id").alias("position"), F.lit(0).alias("k"))
    return temporal.interval_join(points, starts, ["k"], "position", "first", "end", 64).select("position", "row_id")


@_query("observed_counts", f"{_cells('lineitem_onehot')} SELECT (SELECT count(*) FROM ids)::BIGINT AS n, count(*)::BIGINT AS t, max(abs(val)) AS largest FROM cells")
def _(spark, d):
    v, seen = measure.observed(standins.view(spark, d, "lineitem_onehot"))
    v.rows.write.format("noop").mode("overwrite").save()
    got = seen.get
    return spark.createDataFrame([(got["n"], got["t"], float(got["largest"]))], "n long, t long, largest double")


@_query("top_rows", f"{_cells('lineitem_measures')}, y AS (SELECT row_id, sum(val * (col + 1)) AS y FROM cells GROUP BY row_id) SELECT row_id::BIGINT AS row_id, round(y, 2) AS y FROM y ORDER BY round(y, 2) DESC, row_id LIMIT 20")
def _(spark, d):
    v = standins.view(spark, d, "lineitem_measures")
    y = multiply.right(multiply.compress(v, BLOCKS), np.arange(1.0, v.m + 1))
    return y.select("row_id", (F.round("y", 2) + 0.0).alias("y")).orderBy(F.desc("y"), "row_id").limit(20)


@_query("peak_memory_order", f"SELECT range::INTEGER AS block, true AS grows FROM range({BLOCKS})")
def _(spark, d):
    peaks = measure.product_peaks(multiply.compress(standins.view(spark, d, "star_codes"), BLOCKS))
    return peaks.select("block", ((F.col("base_kb") > 0) & (F.col("encoded_kb") >= F.col("base_kb")) & (F.col("peak_kb") > F.col("encoded_kb"))).alias("grows"))
