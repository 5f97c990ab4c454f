"""One grammar for the whole matrix, built by DataFrame rounds: a shared rule set, and products by joins level by level."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import MatrixView, cut

#: Most pairs that one round replaces; they and their map go to the driver and back.
PAIRS = 20_000


@dataclass(frozen=True)
class RelationalGrammar:
    """rows (row_id, syms array<long>), rules (rule, left, right, level), terminals (sym, col, val)."""

    rows: DataFrame
    rules: DataFrame
    terminals: DataFrame
    depth: int
    m: int


def pairs_of(rows: DataFrame) -> DataFrame:
    """(left, right, n): adjacent pairs and the number of rows that hold them."""
    near = F.arrays_zip(F.slice("syms", 1, F.size("syms") - 1).alias("l"), F.slice("syms", 2, F.size("syms") - 1).alias("r"))
    return rows.where(F.size("syms") > 1).select(F.explode(near).alias("p")).groupBy(F.col("p.l").alias("left"), F.col("p.r").alias("right")).agg(F.count("*").alias("n"))


def symbol_rows(view: MatrixView) -> tuple[DataFrame, DataFrame]:
    """(row_id, syms) and (sym, col, val): ids are dense numbers of the distinct (column, value) cells."""
    from ..sources.matrices import with_row_ids

    terminals = with_row_ids(view.cells.select("col", "val").distinct(), ["col", "val"], "sym").select((F.col("sym") + 1).alias("sym"), "col", "val")
    cells = view.cells.join(terminals, ["col", "val"]).groupBy("row_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("col", "sym"))), lambda x: x["sym"]).alias("syms"))
    empty = F.array().cast("array<bigint>")
    return view.rows.select("row_id").join(cells, "row_id", "left").select("row_id", F.coalesce("syms", empty).alias("syms")), terminals


def build(view: MatrixView, max_rounds: int = 30, min_count: int = 2, theta: float = 0.5) -> RelationalGrammar:
    """Batched pair replacement on the rows themselves. A round is one aggregation of adjacent pairs, one bounded collect of the most frequent, one narrow rewrite."""
    spark = view.rows.sparkSession
    rows, terminals = symbol_rows(view)
    rows, terminals = cut(rows), cut(terminals)
    top = terminals.agg(F.max("sym")).first()[0] or 0
    rules: list[tuple[int, int, int, int]] = []
    level: dict[int, int] = {}
    for _ in range(max_rounds):
        counted = pairs_of(rows).where(F.col("n") >= min_count).orderBy(F.desc("n"), "left", "right").limit(PAIRS).collect()
        if not counted:
            break
        need = max(min_count, theta * counted[0].n)
        taken: set[int] = set()
        chosen = {}
        for p in counted:
            if p.n < need:
                break
            if p.left not in taken and p.right not in taken:
                taken.update((p.left, p.right))
                top += 1
                level[top] = 1 + max(level.get(p.left, 0), level.get(p.right, 0))
                rules.append((top, p.left, p.right, level[top]))
                chosen[p.left] = (p.right, top)
        new = spark.createDataFrame([(a, b, c) for a, (b, c) in chosen.items()], "l long, r long, id long")
        lookup = new.agg(F.map_from_entries(F.collect_list(F.struct("l", F.struct("r", "id")))).alias("m"))
        # a fold: a symbol that, with the one before it, makes a chosen pair takes that one's place
        last = lambda a: F.element_at(a, -1)

        def step(a, s):
            hit = F.when(F.size(a) > 0, F.element_at(F.col("m"), last(a)))
            return F.when(hit["r"] == s, F.concat(F.slice(a, 1, F.size(a) - 1), F.array(hit["id"]))).otherwise(F.array_append(a, s))

        folded = F.aggregate("syms", F.array().cast("array<bigint>"), step)
        rows = cut(rows.crossJoin(F.broadcast(lookup)).select("row_id", folded.alias("syms")))  # one row of at most PAIRS entries
    frame = spark.createDataFrame(rules, "rule long, left long, right long, level int")
    return RelationalGrammar(rows, frame, terminals, max(level.values(), default=0), view.m)


def right(g: RelationalGrammar, x: DataFrame) -> DataFrame:
    """y = Mx: Val of terminals by a join with x, of rules level by level, then sums by row. x: (col, x)."""
    w = g.terminals.join(x, "col").select("sym", (F.col("val") * F.col("x")).alias("w"))
    for d in range(1, g.depth + 1):
        here = g.rules.where(F.col("level") == d)
        up = here.join(w.withColumnsRenamed({"sym": "left", "w": "a"}), "left").join(w.withColumnsRenamed({"sym": "right", "w": "b"}), "right")
        w = cut(w.union(up.select(F.col("rule").alias("sym"), (F.col("a") + F.col("b")).alias("w"))))
    y = g.rows.select("row_id", F.explode("syms").alias("sym")).join(w, "sym").groupBy("row_id").agg(F.sum("w").alias("y"))
    return g.rows.select("row_id").join(y, "row_id", "left").select("row_id", F.coalesce("y", F.lit(0.0)).alias("y"))


def left(g: RelationalGrammar, y: DataFrame) -> DataFrame:
    """y'M: sums of y by top symbol, pushed from the highest level down to terminals. y: (row_id, y)."""
    s = g.rows.select("row_id", F.explode("syms").alias("sym")).join(y, "row_id").groupBy("sym").agg(F.sum("y").alias("s"))
    for d in range(g.depth, 0, -1):
        here = g.rules.where(F.col("level") == d).join(s.withColumnRenamed("sym", "rule"), "rule")
        down = here.select(F.explode(F.array("left", "right")).alias("sym"), "s")
        s = cut(s.union(down).groupBy("sym").agg(F.sum("s").alias("s")))
    return s.join(g.terminals, "sym").groupBy("col").agg(F.sum(F.col("val") * F.col("s")).alias("x"))


def expand(g: RelationalGrammar) -> DataFrame:
    """(row_id, col, val): the matrix again, a join a level from the highest down."""
    s = g.rows.select("row_id", F.explode("syms").alias("sym"))
    for d in range(g.depth, 0, -1):
        here = g.rules.where(F.col("level") == d).select(F.col("rule").alias("sym"), F.array("left", "right").alias("kids"))
        s = s.join(here, "sym", "left").select("row_id", F.explode(F.coalesce("kids", F.array("sym"))).alias("sym"))
    return s.join(g.terminals, "sym").select("row_id", "col", "val")


def prune_useless(g: RelationalGrammar) -> DataFrame:
    """The rules that the rows or other useful rules use: anti-joins from the highest level down."""
    used = g.rows.select(F.explode("syms").alias("rule")).distinct()
    kept = None
    for d in range(g.depth, 0, -1):
        here = g.rules.where(F.col("level") == d).join(used, "rule", "left_semi")
        used = cut(used.union(here.select(F.explode(F.array("left", "right")).alias("rule"))).distinct())
        kept = here if kept is None else kept.union(here)
    return g.rules if kept is None else kept
