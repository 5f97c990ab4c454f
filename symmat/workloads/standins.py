"""Matrices built from the given tables, each both as a view and as SQL, by the same column expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import MatrixView
from ..sources import matrices as src

LINE = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
_NUMBERED = f"(SELECT row_number() OVER (ORDER BY {', '.join(LINE)}) - 1 AS row_id, * FROM lineitem)"
_STAR = f"""(SELECT l.*, c.c_nationkey, s.s_nationkey, o.o_orderdate, p.p_size, cn.n_regionkey AS c_region, p.p_brand, sn.n_regionkey AS s_region, p.p_type, p.p_retailprice, o.o_orderstatus, o.o_orderpriority
 FROM {_NUMBERED} l JOIN orders o ON l.l_orderkey = o.o_orderkey JOIN customer c ON o.o_custkey = c.c_custkey JOIN part p ON l.l_partkey = p.p_partkey JOIN supplier s ON l.l_suppkey = s.s_suppkey
 JOIN nation cn ON c.c_nationkey = cn.n_nationkey JOIN nation sn ON s.s_nationkey = sn.n_nationkey)"""
_DAYS = [(t, d) for t in ("click", "view", "error", "purchase", "signup") for d in range(1, 31)]

#: name -> (FROM item in SQL, column expressions, valid in Spark and DuckDB)
EXPRESSIONS: dict[str, tuple[str, dict[str, str]]] = {
    "lineitem_dense": (_NUMBERED, {c: c for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")}),
    "lineitem_measures": (
        _NUMBERED,
        {c: c for c in ("l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax")} | {f"ship_{p}": f"{p}(l_shipdate)" for p in ("year", "month", "day")},
    ),
    "lineitem_onehot": (
        _NUMBERED,
        {f"line_{i}": f"l_linenumber = {i}" for i in range(1, 8)} | {f"flag_{x}": f"l_returnflag = '{x}'" for x in "ANR"} | {f"status_{x}": f"l_linestatus = '{x}'" for x in "FO"}
        | {f"year_{y}": f"year(l_shipdate) = {y}" for y in range(1995, 2002)} | {f"month_{k}": f"month(l_shipdate) = {k}" for k in range(1, 13)} | {"l_discount": "l_discount", "l_tax": "l_tax"},
    ),
    "star_codes": (
        _STAR,
        {"c_nation": "c_nationkey", "s_nation": "s_nationkey", "order_year": "year(o_orderdate)", "p_size": "p_size", "order_month": "month(o_orderdate)", "c_region": "c_region", "brand": "substring(p_brand, 7)", "s_region": "s_region",
         "ship_year": "year(l_shipdate)", "type_length": "length(p_type)", "price": "p_retailprice", "l_discount": "l_discount", "status": "ascii(o_orderstatus)", "ship_month": "month(l_shipdate)", "l_tax": "l_tax", "priority": "ascii(o_orderpriority) - 48"},
    ),
    "events_user_day": (
        "(SELECT user_id AS row_id, * FROM (SELECT user_id, " + ", ".join(f"sum(CASE WHEN event_type = '{t}' AND day(ts) = {d} THEN 1 ELSE 0 END) AS {t}_{d}" for t, d in _DAYS) + " FROM events GROUP BY user_id) z)",
        {f"{t}_{d}": f"{t}_{d}" for t, d in _DAYS},
    ),
    "label_bits": ("(SELECT doc_id AS row_id, quality, toxic FROM labels)", {"quality": "quality", "toxic": "toxic"}),
    "conversation_roles": (
        "(SELECT conv_id AS row_id, " + ", ".join(f"sum(CASE WHEN role = '{r}' THEN 1 ELSE 0 END) AS n_{r}" for r in ("user", "assistant", "system")) + " FROM conversations GROUP BY conv_id)",
        {f"n_{r}": f"n_{r}" for r in ("user", "assistant", "system")},
    ),
    "nation_adjacency": (
        f"(SELECT c_nationkey AS row_id, " + ", ".join(f"sum(CASE WHEN s_nationkey = {k} THEN 1 ELSE 0 END) AS to_{k}" for k in range(25)) + f" FROM {_STAR} y GROUP BY c_nationkey)",
        {f"to_{k}": f"to_{k}" for k in range(25)},
    ),
}
ARRAYS = {"embeddings": None, "embeddings_q2": 2, "embeddings_q1": 1}
NAMES = (*EXPRESSIONS, "doc_chars", *ARRAYS)


def numbered_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The lines with the row ids that all their stand-ins share."""
    return src.with_row_ids(src.table(spark, sf_dir, "lineitem").select(*LINE), LINE)


def _base(spark: SparkSession, sf_dir: str, name: str, lines: DataFrame | None) -> DataFrame:
    """The numbered rows of a stand-in: the same relation as its SQL, with range-partitioned numbering in place of a window."""
    for t in ("lineitem", "orders", "customer", "part", "supplier", "nation", "events", "labels", "conversations"):
        src.table(spark, sf_dir, t).createOrReplaceTempView(t)
    item, columns = EXPRESSIONS[name]
    if _NUMBERED in item:
        wanted = {w for e in columns.values() for w in LINE if w in e} if item == _NUMBERED else set(LINE)
        numbered = numbered_lines(spark, sf_dir) if lines is None else lines
        (numbered.select("row_id", *[c for c in LINE if c in wanted]) if item == _NUMBERED else numbered).createOrReplaceTempView("symmat_numbered_lines")
        item = item.replace(_NUMBERED, "symmat_numbered_lines")
    return spark.sql(f"SELECT * FROM {item} z")


def view(spark: SparkSession, sf_dir: str, name: str, lines: DataFrame | None = None) -> MatrixView:
    """A stand-in by name; ``lines``: the ``numbered_lines`` where they are at hand."""
    if name == "doc_chars":
        return src.from_characters(src.table(spark, sf_dir, "documents"), "text", range(32, 127), "doc_id")
    if name in ARRAYS:
        full = src.from_array(src.table(spark, sf_dir, "embeddings"), "embedding", 64, "vec_id")
        return full if ARRAYS[name] is None else src.quantise(full, ARRAYS[name])
    base = _base(spark, sf_dir, name, lines)
    return src.from_expressions(base, EXPRESSIONS[name][1])


def width(name: str) -> int:
    return 95 if name == "doc_chars" else 64 if name in ARRAYS else len(EXPRESSIONS[name][1])


def rows_sql(name: str) -> str:
    """(row_id) of a stand-in in DuckDB."""
    if name == "doc_chars":
        return "SELECT doc_id AS row_id FROM documents"
    if name in ARRAYS:
        return "SELECT vec_id AS row_id FROM embeddings"
    return f"SELECT row_id FROM {EXPRESSIONS[name][0]} z"


def long_sql(name: str) -> str:
    """(row_id, col, val) of a stand-in's nonzero cells in DuckDB."""
    if name == "doc_chars":
        return "SELECT doc_id AS row_id, c - 32 AS col, (length(text) - length(replace(text, chr(c::INTEGER), '')))::DOUBLE AS val FROM documents, range(32, 127) t(c) WHERE length(replace(text, chr(c::INTEGER), '')) < length(text)"
    if name in ARRAYS:
        v = "x::DOUBLE" if ARRAYS[name] is None else f"round(x::DOUBLE, {ARRAYS[name]})"
        return f"SELECT row_id, col, {v} AS val FROM (SELECT vec_id AS row_id, generate_subscripts(embedding, 1) - 1 AS col, unnest(embedding) AS x FROM embeddings) e WHERE {v} <> 0"
    item, columns = EXPRESSIONS[name]
    arrays = ", ".join(f"CAST({e} AS DOUBLE)" for e in columns.values())
    return f"SELECT row_id, col, val FROM (SELECT row_id, generate_subscripts(v, 1) - 1 AS col, unnest(v) AS val FROM (SELECT row_id, [{arrays}] AS v FROM {item} z)) WHERE val <> 0"


def x_frame(spark: SparkSession, m: int) -> DataFrame:
    return spark.range(m).select(F.col("id").cast("int").alias("col"), (F.col("id") + 1).cast("double").alias("x"))


def y_of(ids):
    """The left vector by formula: 1 + row_id mod 7."""
    return 1 + ids % 7


def y_frame(v: MatrixView) -> DataFrame:
    return v.rows.select("row_id", (1 + F.pmod("row_id", F.lit(7))).cast("double").alias("y"))
