"""Chat formatting with linked tool calls (DataFrame functions only).

A turn whose text is a JSON object with a ``tool_calls`` array makes calls: ``{"id", "name", "arguments": {...},
"after": [ids]}``. A turn of role ``tool`` whose text is a JSON object with ``tool_call_id`` is a result. A result meets
the latest call of its id in an earlier turn of its conversation, so ids may start afresh in every turn. A call's level is one
more than the largest level of the calls of its own turn that it waits for (``after``, or a string argument ``"$id"``);
those of earlier turns are made before it anyway. Arguments are checked against a table of tool schemas. Every turn becomes
one canonical JSON line: keys sorted, no blanks, one form per value, numbers exact whatever their size. Lines are numbered
per conversation, a result directly after its call's turn and results of one turn by level. No conversation, turn or call
is gathered in one row or task: what runs along a conversation is summed up by spans of turns or of sorted rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._common import cut

#: Turns whose calls and results meet in one window.
TURNS = 1024
#: Tools known by default: (tool, argument, JSON type, required).
SCHEMAS = (
    ("search", "query", "string", True), ("search", "limit", "integer", False),
    ("calculator", "expression", "string", True),
    ("weather", "city", "string", True), ("weather", "days", "integer", False), ("weather", "metric", "boolean", False),
    ("fetch", "url", "string", True), ("fetch", "headers", "object", False),
)
#: In a text on its way through a variant, a number is a string that begins with the first sign; a string that begins with either gets the second before it.
NUMBER, ESCAPE = "\ue000", "\ue001"
#: A JSON text's strings, numbers, and what lies between; possessive, so that long texts need no stack.
_TOKEN = r'(?s)"[^"\\]*+(?:\\.[^"\\]*+)*+"|-?[0-9]++(?:\.[0-9]++)?+(?:[eE][+-]?[0-9]++)?+|[^"0-9-]++|.'
_NUMBER = r"^(-?)(0|[1-9][0-9]*+)(?:\.([0-9]++))?+(?:[eE]([+-]?[0-9]++))?+$"
#: Digits before the point, and zeros behind it, up to which a number is written out.
PLAIN, SMALL = 21, 6


def schemas(spark: SparkSession, rows: tuple = SCHEMAS) -> DataFrame:
    return spark.createDataFrame(list(rows), "tool string, arg string, type string, required boolean")


def _let(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def canonical_number(token: Column) -> Column:
    """One form for each value of a JSON number, exact: 1.0, 1e0 and 100e-2 are 1, 1E400 is 1e+400. Null for what is no number, or has an exponent beyond 64 bits."""
    def group(n: int) -> Column:
        return F.regexp_extract(token, _NUMBER, n)

    parts = F.struct(
        group(1).alias("sign"), F.regexp_replace(F.concat(group(2), group(3)), "^0++", "").alias("all"), F.length(group(3)).alias("behind"),
        F.when(group(4) == "", F.lit(0).cast("long")).otherwise(group(4).try_cast("long")).alias("e"),
    )

    def digits(x: Column) -> Column:
        return F.struct(x["sign"].alias("sign"), F.regexp_replace(x["all"], "0++$", "").alias("d"), (x["e"] - x["behind"] + F.length(x["all"])).alias("point"))

    def written(x: Column) -> Column:
        d, n, point = x["d"], F.length(x["d"]), x["point"].cast("int")
        far = F.concat(F.substring(d, 1, 1), F.when(n > 1, F.concat(F.lit("."), F.substring(d, F.lit(2), n))).otherwise(""), F.lit("e"), F.when(x["point"] > 0, "+").otherwise(""), (x["point"] - 1).cast("string"))
        plain = (
            F.when((n <= x["point"]) & (x["point"] <= PLAIN), F.rpad(d, point, "0"))
            .when((x["point"] > 0) & (x["point"] <= PLAIN), F.concat(F.substring(d, F.lit(1), point), F.lit("."), F.substring(d, point + 1, n)))
            .when((x["point"] <= 0) & (x["point"] > -SMALL), F.concat(F.lit("0."), F.repeat(F.lit("0"), -point), d))
            .otherwise(far)
        )
        return F.when(n == 0, "0").otherwise(F.concat(x["sign"], plain))

    return F.when(token.rlike(_NUMBER), _let(parts, lambda p: _let(digits(p), written)))


def _guarded(text: Column) -> Column:
    """A JSON text with every number as a marked string in canonical form. What is no JSON stays no JSON."""
    def one(token: Column) -> Column:
        inside = F.substring(token, F.lit(2), F.length(token))
        marked = inside.startswith(NUMBER) | inside.startswith(ESCAPE) | F.lower(F.substring(inside, 1, 6)).isin("\\ue000", "\\ue001")
        number = canonical_number(token)
        return (
            F.when(token.startswith('"') & (F.length(token) > 1) & marked, F.concat(F.lit('"' + ESCAPE), inside))
            .when(token.rlike(_NUMBER), F.concat(F.lit('"' + NUMBER), F.coalesce(number, token), F.lit('"')))
            .otherwise(token)
        )

    return F.array_join(F.transform(F.regexp_extract_all(text, F.lit(_TOKEN), F.lit(0)), one), "")


def _plain(json: Column) -> Column:
    """The JSON text of a guarded variant, numbers and strings as they are."""
    return F.regexp_replace(F.regexp_replace(json, f'"{NUMBER}([^"]*+)"', "$1"), f'"{ESCAPE}', '"')


def _string(value: Column) -> Column:
    """A guarded string or number as plain text."""
    return F.regexp_replace(value, f"^[{NUMBER}{ESCAPE}]", "")


def _json_type(value: Column) -> Column:
    """The JSON schema type of a guarded variant; a number of whole value is an integer."""
    t = F.schema_of_variant(value)
    text = F.try_variant_get(value, "$", "string")
    behind = F.length(F.regexp_extract(text, "[.]([0-9]+)", 1))
    power = F.coalesce(F.regexp_extract(text, "e[+]([0-9]+)$", 1).try_cast("long"), F.lit(0))
    number = F.when(text.contains("e-") | (behind > power), "number").otherwise("integer")
    return (
        F.when(value.isNull() | (t == "VOID"), "null").when(t.startswith("STRING"), F.when(text.startswith(NUMBER), number).otherwise("string")).when(t.startswith("BOOLEAN"), "boolean")
        .when(t.startswith("OBJECT"), "object").when(t.startswith("ARRAY"), "array").otherwise("null")
    )


def turns(conversations: DataFrame) -> DataFrame:
    """(conv_id, conv, turn, role, text, uid, body, makes, result_id) of each row.

    conv is never null; uid a hash of the row; body the guarded JSON object, as text, of a turn that is one; makes says
    whether it makes calls. A JSON text that repeats a key within an object has no canonical form and counts as plain text.
    """
    base = conversations.select(F.col("conv_id"), F.col("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    looks = F.coalesce(F.ltrim("text").startswith("{"), F.lit(False))
    body = F.when(looks, F.try_parse_json(_guarded(F.col("text"))))
    conv = F.coalesce(F.concat(F.lit("c"), F.col("conv_id").cast("string")), F.lit("-"))
    read = base.withColumn("conv", conv).withColumn("uid", F.xxhash64("conv_id", "turn", "role", "text")).withColumn("body", F.to_json(body))
    v = F.try_parse_json("body")
    makes = (F.col("role") == "assistant") & F.try_variant_get(v, "$.tool_calls", "array<variant>").isNotNull()
    result = F.when(F.col("role") == "tool", _string(F.try_variant_get(v, "$.tool_call_id", "string")))
    return read.withColumn("makes", F.coalesce(makes, F.lit(False))).withColumn("result_id", result)


def calls_of(parsed: DataFrame) -> DataFrame:
    """One row per call: node, conv, turn, uid, at, id, name, arguments (guarded JSON), after (array of ids), stands.

    Of calls that repeat an id in one turn, the first stands; a call without an id does not. The others are never linked.
    """
    made = F.try_variant_get(F.try_parse_json("body"), "$.tool_calls", "array<variant>")
    one = parsed.where("makes").select("conv", "turn", "uid", F.posexplode(made).alias("at", "c"))
    rows = one.select(
        "conv", "turn", "uid", "at", _string(F.try_variant_get("c", "$.id", "string")).alias("id"), _string(F.try_variant_get("c", "$.name", "string")).alias("name"),
        F.to_json(F.try_variant_get("c", "$.arguments", "variant")).alias("arguments"), F.coalesce(F.try_variant_get("c", "$.after", "array<string>"), F.array().cast("array<string>")).alias("after"),
    )
    refs = F.regexp_extract_all(F.coalesce("arguments", F.lit("")), F.lit(r'"\$([^"\\]+)"'), F.lit(1))
    rows = cut(rows.withColumn("after", F.array_distinct(F.concat(F.transform("after", _string), refs))))  # numbers of checkpointed rows stay
    rows = rows.withColumn("node", F.monotonically_increasing_id())
    first = rows.where("id IS NOT NULL").groupBy("conv", "turn", "id").agg(F.min(F.struct("at", "node"))["node"].alias("node")).select("node", F.lit(True).alias("stands"))
    return rows.join(first, "node", "left").withColumn("stands", F.coalesce("stands", F.lit(False)))


def _pointers(single: DataFrame, longest: int) -> DataFrame:
    """(u, p, d) of nodes that wait for one node each: the end p of u's chain, d steps away; p null on or behind a circle. Pointers double."""
    ptr = cut(single.select("u", F.col("v").alias("p"), F.lit(1).cast("long").alias("d")))
    for _ in range(math.ceil(math.log2(longest + 1)) + 1):
        ahead = ptr.select(F.col("u").alias("p"), F.col("p").alias("p2"), F.col("d").alias("d2"))
        on = ptr.join(ahead, "p", "left")
        if on.where("p2 IS NOT NULL").isEmpty():
            return ptr
        ptr = cut(on.select("u", F.coalesce("p2", "p").alias("p"), (F.col("d") + F.coalesce("d2", F.lit(0))).alias("d")))
    # no chain is longer: what still points at a pointer goes round
    ring = ptr.select(F.col("u").alias("p"), F.lit(True).alias("ring"))
    return cut(ptr.join(ring, "p", "left").select("u", F.when(F.col("ring").isNull(), F.col("p")).alias("p"), "d"))


def levels(nodes: DataFrame, edges: DataFrame, longest: int) -> DataFrame:
    """(node, level): 0 for nodes that wait for none, else one more than the largest level of those they wait for; null on or behind a circle.

    ``edges``: (u, v), u waits for v. Chains, where each waits for one, are settled by doubling pointers, in a number of
    rounds that is logarithmic in ``longest``, the most nodes of a chain. What waits for several is settled in Kahn's order over
    the ends of chains, a round for each such node on the longest way.
    """
    edges = cut(edges.distinct())
    if edges.isEmpty():
        return nodes.select("node", F.lit(0).cast("long").alias("level"))
    degree = edges.groupBy("u").agg(F.count("*").alias("n"))
    chains = _pointers(edges.join(degree.where("n = 1"), "u"), longest)
    many = edges.join(degree.where("n > 1").select("u"), "u").select(F.col("u").alias("a"), F.col("v").alias("u"))
    # every wait of a node of several, as (a, end of the chain, steps); an end of null never settles
    waits = cut(many.join(chains, "u", "left").select("a", F.when(F.col("d").isNull(), F.col("u")).otherwise(F.col("p")).alias("p"), F.coalesce("d", F.lit(0).cast("long")).alias("d")))
    done = cut(nodes.select("node").join(degree.select(F.col("u").alias("node")), "node", "left_anti").withColumn("level", F.lit(0).cast("long")))
    fresh = done
    while not waits.isEmpty():
        met = waits.join(done.select(F.col("node").alias("p"), "level"), "p", "left")
        ready = met.groupBy(F.col("a").alias("node")).agg(F.max(F.col("level") + F.col("d") + 1).alias("level"), F.count_if(F.col("level").isNull()).alias("open"))
        fresh = cut(ready.where("open = 0").select("node", "level"))
        if fresh.isEmpty():
            break
        done = cut(done.union(fresh))
        waits = cut(waits.join(fresh.select(F.col("node").alias("a")), "a", "left_anti"))
    ends = done.select(F.col("node").alias("p"), "level")
    far = chains.join(ends, "p").select(F.col("u").alias("node"), (F.col("level") + F.col("d")).alias("level"))
    return nodes.select("node").join(done.union(far), "node", "left")


def _latest(asks: DataFrame, calls: DataFrame, same_turn: bool) -> DataFrame:
    """``asks`` (conv, id, turn, ...) with node: the latest call of their id in an earlier turn, or in their own too. Null where there is none.

    Calls and asks of one id meet by spans of ``TURNS`` turns; the last call of each span is handed on to the later ones.
    """
    span = F.floor(F.coalesce(F.col("turn"), F.lit(-1)) / TURNS).alias("span")
    names = [c for c in asks.columns if c not in ("conv", "id", "turn")]
    nothing = [F.lit(None).cast(t).alias(c) for c, t in asks.dtypes if c in names]
    called = calls.where("stands").select("conv", "id", "turn", span, F.col("node").alias("own"), F.lit(0 if same_turn else 2).alias("kind"), *nothing)
    asked = asks.select("conv", "id", "turn", span, F.lit(None).cast("long").alias("own"), F.lit(1).alias("kind"), *names)
    in_span = Window.partitionBy("conv", "id", "span").orderBy(F.col("turn").asc_nulls_first(), "kind").rowsBetween(Window.unboundedPreceding, 0)
    near = called.union(asked).withColumn("near", F.last("own", ignorenulls=True).over(in_span))
    last = called.groupBy("conv", "id", "span").agg(F.max(F.struct("turn", "own"))["own"].alias("last"))
    spans = last.select("conv", "id", "span", "last").union(asked.select("conv", "id", "span", F.lit(None).cast("long"))).groupBy("conv", "id", "span").agg(F.max("last").alias("last"))
    before = F.last("last", ignorenulls=True).over(Window.partitionBy("conv", "id").orderBy("span").rowsBetween(Window.unboundedPreceding, -1))
    far = spans.select("conv", "id", "span", before.alias("far"))
    return near.where("kind = 1").join(far, ["conv", "id", "span"]).select("conv", "id", "turn", *names, F.coalesce("near", "far").alias("node"))


def validate(calls: DataFrame, known: DataFrame) -> DataFrame:
    """(node, problems): sorted problems of each call; empty when it stands and its arguments fit the tool's schema."""
    args = calls.withColumn("v", F.try_parse_json("arguments"))
    # as a map, since not every name of an argument can be written as a path
    own = F.explode(F.map_entries(F.try_variant_get("v", "$", "map<string,variant>")))
    given = args.select("node", F.col("name").alias("tool"), own.alias("e")).select("node", "tool", _string(F.col("e.key")).alias("arg"), _json_type(F.col("e.value")).alias("is"))
    tools = F.broadcast(known.select("tool").distinct())  # a row per tool, as many as the caller's table of schemas
    unknown = calls.join(tools, calls["name"] == tools["tool"], "left_anti").select("node", F.lit("unknown tool").alias("p"))
    broken = args.where("v IS NULL OR NOT coalesce(schema_of_variant(v) LIKE 'OBJECT%', false)").select("node", F.lit("arguments are no object").alias("p"))
    typed = given.join(known, ["tool", "arg"])
    wrong = typed.where(~((F.col("is") == F.col("type")) | ((F.col("type") == "number") & (F.col("is") == "integer")))).select("node", F.concat(F.lit("type of "), "arg").alias("p"))
    extra = given.join(tools, "tool", "left_semi").join(known, ["tool", "arg"], "left_anti").select("node", F.concat(F.lit("unexpected "), "arg").alias("p"))
    needed = calls.select("node", F.col("name").alias("tool")).join(known.where("required"), "tool").select("node", "arg")
    missing = needed.join(given.select("node", "arg"), ["node", "arg"], "left_anti").select("node", F.concat(F.lit("missing "), "arg").alias("p"))
    lost = calls.where("NOT stands").select("node", F.when(F.col("id").isNull(), "no id").otherwise("repeated id").alias("p"))
    every = unknown.union(broken).union(wrong).union(extra).union(missing).union(lost).groupBy("node").agg(F.array_sort(F.collect_set("p")).alias("problems"))
    return calls.select("node").join(every, "node", "left").select("node", F.coalesce("problems", F.array().cast("array<string>")).alias("problems"))


def linked(parsed: DataFrame, calls: DataFrame, known: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(results, counts): conv, uid, turn, call_turn, level of each result row, call_turn null for orphans; conv, uid, n_calls, n_linked, n_invalid of each turn that makes calls."""
    asks = calls.select("conv", "turn", F.col("node").alias("u"), F.explode("after").alias("id"))
    near = _latest(asks, calls, same_turn=True).where("node IS NOT NULL")
    facts = calls.select("node", F.col("turn").alias("call_turn"), "at", F.col("uid").alias("call_uid"))
    edges = near.join(facts, "node").where(F.col("turn").eqNullSafe(F.col("call_turn"))).select("u", F.col("node").alias("v"))
    longest = (calls.agg(F.max("at")).first()[0] or 0) + 1
    level = cut(levels(calls, edges, longest))
    results = parsed.where("result_id IS NOT NULL").select("conv", F.col("result_id").alias("id"), "turn", "uid", "row")
    met = cut(_latest(results, calls, same_turn=False))
    used = met.where("node IS NOT NULL").select("node").distinct().withColumn("linked", F.lit(True))
    info = calls.select("conv", "uid", "node").join(validate(calls, known), "node").join(level, "node").join(used, "node", "left")
    bad = (F.size("problems") > 0) | F.col("level").isNull()
    counts = info.groupBy("conv", "uid").agg(F.count("*").alias("n_calls"), F.count_if(F.coalesce("linked", F.lit(False))).alias("n_linked"), F.count_if(bad).alias("n_invalid"))
    to = facts.join(level, "node").select("node", "call_turn", (F.coalesce("level", F.lit(1 << 30)) + 1).alias("level"), "at")
    return met.join(to, "node", "left").select("row", (F.col("node").isNull()).alias("orphan"), "call_turn", "level", "at"), counts


def format_chat(conversations: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """A row per turn: conv_id, turn, position (from 0 in its conversation), role, line (canonical JSON), n_calls, n_linked, n_invalid, orphan.

    n_calls: calls the turn makes; n_linked: those with a result in the conversation; n_invalid: those whose arguments
    break their schema, that have no id or one the turn has used, or that wait in a circle. orphan: a result with no call of
    its id in an earlier turn. Null role or text: left out of the line. Rows without a conv_id form one conversation; a null
    turn comes before all others. Repeated rows stay, one after the other, and each makes its calls again. An empty table
    gives no rows. Other columns play no part, whatever their names.
    """
    spark = conversations.sparkSession
    known = schemas(spark) if known is None else known
    parsed = cut(turns(conversations)).withColumn("row", F.monotonically_increasing_id())
    calls = cut(calls_of(parsed))
    counts, level0 = None, F.lit(0).cast("long")
    if calls.isEmpty():
        placed = parsed.withColumns({"orphan": F.col("result_id").isNotNull(), "anchor": F.col("turn"), "level": level0, "at": F.lit(0)})
    else:
        found, counts = linked(parsed, calls, known)
        own = parsed.where("result_id IS NULL").withColumns({"orphan": F.lit(False), "anchor": F.col("turn"), "level": level0, "at": F.lit(0)})
        # results alone are joined, by row: turns without an identifier never meet on a null
        met = parsed.where("result_id IS NOT NULL").join(found, "row").withColumns({"anchor": F.when(F.col("orphan"), F.col("turn")).otherwise(F.col("call_turn")), "level": F.coalesce("level", level0), "at": F.coalesce("at", F.lit(0))})
        placed = own.unionByName(met.drop("call_turn"))
    content = F.coalesce("body", "text")
    line = F.to_json(F.struct(_plain_or_text(content).alias("content"), F.col("role"), F.col("result_id").alias("tool_call_id")))
    placed = placed.select("conv_id", "conv", "turn", "role", "uid", "row", "anchor", "level", "at", "orphan", line.alias("line"))
    # the row's number parts equal rows, that they need not lie in one partition
    order = [F.col("conv"), F.col("anchor").asc_nulls_first(), F.col("level"), F.col("at"), F.col("turn").asc_nulls_first(), F.col("uid"), F.col("row")]
    # a range sort over conversations and what is in them: a long one lies in many partitions
    lined = cut(placed.orderBy(*order).withColumn("serial", F.monotonically_increasing_id())).withColumn("part", F.shiftright("serial", 33))
    sizes = lined.groupBy("conv", "part").agg(F.min("serial").alias("first"), F.count("*").alias("n"))
    before = F.coalesce(F.sum("n").over(Window.partitionBy("conv").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    out = lined.join(sizes.select("conv", "part", (F.col("first") - before).alias("from")), ["conv", "part"]).withColumn("position", F.col("serial") - F.col("from"))
    zero = F.lit(0).cast("long")
    names = ("n_calls", "n_linked", "n_invalid")
    if counts is None:
        return out.select("conv_id", "turn", "position", "role", "line", *[zero.alias(c) for c in names], "orphan")
    return out.join(counts, ["conv", "uid"], "left").select("conv_id", "turn", "position", "role", "line", *[F.coalesce(c, zero).alias(c) for c in names], "orphan")


def _plain_or_text(content: Column) -> Column:
    return F.when(F.col("body").isNotNull(), _plain(content)).otherwise(content)


#: Rows of op8 in DuckDB, for tables whose turns are no JSON objects.
ORACLE = """
SELECT conv_id, turn, (row_number() OVER (PARTITION BY conv_id ORDER BY turn) - 1)::BIGINT AS position, role,
 '{"content":' || to_json(text)::VARCHAR || ',"role":' || to_json(role)::VARCHAR || '}' AS line,
 0::BIGINT AS n_calls, 0::BIGINT AS n_linked, 0::BIGINT AS n_invalid, false AS orphan FROM conversations
"""
