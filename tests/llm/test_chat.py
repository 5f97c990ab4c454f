"""Chat formatting against a plain reading of its rules."""

import json
from collections import Counter, defaultdict
from decimal import Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from symmat.llm import chat

TURNS = "conv_id long, turn long, role string, text string"
TOOLS = {t: {a: (k, r) for u, a, k, r in chat.SCHEMAS if u == t} for t, *_ in chat.SCHEMAS}


def kind(v):
    return {bool: "boolean", int: "integer", str: "string", dict: "object", list: "array", type(None): "null"}.get(type(v), "number")


def problems(call):
    out, args = set(), call.get("arguments")
    schema = TOOLS.get(call.get("name"))
    if schema is None:
        out.add("unknown tool")
    if not isinstance(args, dict):
        out.add("arguments are no object")
        args = {}
    for a, v in args.items() if schema else ():
        if a not in schema:
            out.add(f"unexpected {a}")
        elif kind(v) != schema[a][0] and not (schema[a][0] == "number" and kind(v) == "integer"):
            out.add(f"type of {a}")
    return out | {f"missing {a}" for a, (_, need) in (schema or {}).items() if need and a not in args}


def plainly(rows):
    """(conv_id, turn, role, text) in order, n_calls, n_linked, n_invalid, orphan of every row, conversation by conversation."""
    out = []
    for conv in {r[0] for r in rows}:
        mine = sorted((r for r in rows if r[0] == conv), key=lambda r: r[1])
        calls, results, keyed = [], [], defaultdict(list)
        for r in mine:
            body = json.loads(r[3]) if r[3] and r[3].startswith("{") else {}
            if r[2] == "assistant" and isinstance(body.get("tool_calls"), list):
                seen = set()
                for at, c in enumerate(body["tool_calls"]):
                    stands = c.get("id") is not None and c["id"] not in seen
                    seen.add(c.get("id"))
                    refs = [v[1:] for v in (c.get("arguments") or {}).values() if isinstance(v, str) and v.startswith("$")] if isinstance(c.get("arguments"), dict) else []
                    calls.append({"turn": r[1], "at": at, "id": c.get("id"), "stands": stands, "after": set(c.get("after", [])) | set(refs), "bad": bool(problems(c)) or not stands, "linked": False})
            if r[2] == "tool" and "tool_call_id" in body:
                before = [c for c in calls if c["stands"] and c["id"] == body["tool_call_id"] and c["turn"] < r[1]]
                if before:
                    before[-1]["linked"] = True
                results.append((r, before[-1] if before else None))
        for c in calls:
            c["near"] = [d for d in calls if d["turn"] == c["turn"] and d["stands"] and d["id"] in c["after"]]
        level = {id(c): None for c in calls}
        for _ in calls:
            for c in calls:
                if all(level[id(d)] is not None for d in c["near"]) and level[id(c)] is None:
                    level[id(c)] = 1 + max((level[id(d)] for d in c["near"]), default=-1)
        for r in mine:
            own = [c for c in calls if c["turn"] == r[1]] if r[2] == "assistant" else []
            found = next((c for q, c in results if q is r), "none")
            place = (r[1], 0, 0, r[1]) if found in ("none", None) else (found["turn"], 1 + (1 << 30 if level[id(found)] is None else level[id(found)]), found["at"], r[1])
            keyed[place].append((*r, len(own), sum(c["linked"] for c in own), sum(c["bad"] or level[id(c)] is None for c in own), found is None))
        out += [(conv, i, *x[1:]) for i, x in enumerate(y for k in sorted(keyed) for y in keyed[k])]
    return out


def random_rows(seed):
    r = np.random.default_rng(seed)
    rows = []
    for conv in range(12):
        for turn in range(int(r.integers(2, 14))):
            what = r.choice(["user", "assistant", "tool"], p=[0.2, 0.35, 0.45])
            ids = [f"call_{k}" for k in range(4)]
            if what == "user":
                rows.append((conv, turn, what, f"question {turn}"))
            elif what == "tool":
                rows.append((conv, turn, what, json.dumps({"tool_call_id": str(r.choice(ids)), "content": turn})))
            else:
                made = []
                for _ in range(int(r.integers(0, 6))):
                    args = [{"query": "x"}, {"query": "$" + str(r.choice(ids)), "limit": 2}, {"city": 3}, {"city": "a", "days": 1.5}, [1], None, {"url": "u", "headers": {}}][r.integers(7)]
                    c = {"name": str(r.choice(["search", "weather", "fetch", "other"])), "arguments": args}
                    if r.random() < 0.9:
                        c["id"] = str(r.choice(ids))
                    if r.random() < 0.5:
                        c["after"] = [str(x) for x in r.choice(ids, r.integers(1, 3))]
                    made.append(c)
                rows.append((conv, turn, what, json.dumps({"tool_calls": made}) if made else "no calls"))
    return rows


def test_linking_ordering_and_validation_as_in_a_plain_reading(spark, monkeypatch):
    monkeypatch.setattr(chat, "TURNS", 4)  # ids are handed on over several spans
    rows = random_rows(1) + [(50 + a, b, c, d) for a, b, c, d in random_rows(2)]
    want = plainly(rows)
    got = chat.format_chat(spark.createDataFrame(rows, TURNS).repartition(3)).collect()
    assert len(want) == len(rows) == len(got)
    assert {(r.conv_id, r.position): (r.turn, r.role, r.n_calls, r.n_linked, r.n_invalid, r.orphan) for r in got} == {(c, i): (t, role, *rest) for c, i, t, role, _, *rest in want}
    assert sum(r.n_linked for r in got) > 10 and sum(r.n_invalid for r in got) > 10 and any(r.orphan for r in got)


def test_long_chains_circles_and_ladders(spark):
    n = 60
    edges = [(i, i - 1) for i in range(1, n)] + [(100, 101), (101, 100), (102, 100), (200, n - 1), (200, 30), (201, 200), (202, 201), (202, 5), (203, 202), (300, 300), (301, 300), (301, 2)]
    nodes = sorted({x for e in edges for x in e} | {400})
    got = {r.node: r.level for r in chat.levels(spark.createDataFrame([(x,) for x in nodes], "node long"), spark.createDataFrame(edges, "u long, v long"), n).collect()}
    want = {i: i for i in range(n)} | {100: None, 101: None, 102: None, 200: n, 201: n + 1, 202: n + 2, 203: n + 3, 300: None, 301: None, 400: 0}
    assert got == want


@pytest.mark.parametrize("number,want", [("1.0", "1"), ("1e0", "1"), ("100e-2", "1"), ("1E400", "1e+400"), ("-0.0", "0"), ("-0.50e-3", "-0.0005"), ("12.34e1", "123.4"), ("1e-7", "1e-7"), ("007", None), ("1e21", "1e+21"), ("1e20", "1" + "0" * 20)])
def test_numbers_have_one_form(spark, number, want):
    assert spark.range(1).select(chat.canonical_number(F.lit(number)).alias("n")).first().n == want


def test_canonical_json_of_random_values(spark):
    r = np.random.default_rng(5)

    def value(depth):
        pick = r.integers(8 if depth else 6)
        return [lambda: None, lambda: bool(r.integers(2)), lambda: int(r.integers(-9, 10**12)), lambda: float(np.round(r.normal() * 10.0 ** r.integers(-9, 25), 6)),
                lambda: "".join(r.choice(list('a"\\/\n\t\x01é\ue000\ue001$1{}[]:,'), r.integers(0, 9))), lambda: str(r.choice(["1.0", "-5", "\ue0007", "x"])),
                lambda: [value(depth - 1) for _ in range(r.integers(4))], lambda: {"".join(r.choice(list("ab1\ue000-\""), r.integers(0, 4))): value(depth - 1) for _ in range(r.integers(4))}][pick]()

    values = [{"k": value(3), "j": value(2)} for _ in range(150)]
    rows = [(i, 0, "user", json.dumps(v, ensure_ascii=bool(i % 2), indent=i % 3)) for i, v in enumerate(values)]
    got = {x.conv_id: x.line for x in chat.format_chat(spark.createDataFrame(rows, TURNS)).collect()}
    shuffled = [(i, 0, "user", json.dumps(dict(reversed(v.items())))) for i, v in enumerate(values)]
    assert got == {x.conv_id: x.line for x in chat.format_chat(spark.createDataFrame(shuffled, TURNS)).collect()}
    same = lambda t: json.loads(t, parse_float=Decimal, parse_int=Decimal)
    for i, v in enumerate(values):
        text = json.loads(got[i])["content"]
        assert same(text) == same(json.dumps(v)) and " " not in text.replace('" "', ""), (text, v)
        assert list(json.loads(text)) == sorted(json.loads(text))


def test_odd_rows(spark):
    call = '{"tool_calls": [{"name": "search", "id": 7, "arguments": {"query": "x", "limit": 2.0}}]}'
    rows = [
        (None, None, "user", "hi"), (None, 1, "assistant", call), (None, 2, "tool", '{"tool_call_id": "7"}'),  # rows without an id are one conversation
        (1, 0, "user", '{"a": 1, "a": 2}'), (1, 0, "user", "{broken"), (1, 1, None, None), (1, 1, None, None), (1, 2, "user", ""), (1, 3, "user", "x" * 100_000 + '"' * 5_000),
        (2, 0, "user", '{"big": 1E400, "b": 1.0, "s": "' + '\\\\n' * 20_000 + '"}'),
    ]
    df = spark.createDataFrame(rows, TURNS).withColumns({"line": F.lit(1), "conv": F.lit(2), "row": F.lit(3)})
    got = sorted(chat.format_chat(df).collect(), key=lambda r: (r.conv_id is not None, r.conv_id, r.position))
    assert [(r.turn, r.position, r.n_calls, r.n_linked, r.n_invalid, r.orphan) for r in got[:3]] == [(None, 0, 0, 0, 0, False), (1, 1, 1, 1, 0, False), (2, 2, 0, 0, 0, False)]
    assert Counter(r.position for r in got[3:9]) == Counter(range(6)) and {json.loads(got[k].line)["content"] for k in (3, 4)} == {'{"a": 1, "a": 2}', "{broken"}
    assert got[5].line == got[6].line == "{}" and json.loads(got[8].line)["content"] == rows[8][3] and json.loads(got[9].line)["content"].startswith('{"b":1,"big":1e+400,')
    assert chat.format_chat(df.where("false")).count() == 0
    two = spark.createDataFrame([(1, 0, "assistant", call)] * 2 + [(1, 5000, "tool", '{"tool_call_id": "7"}')], TURNS)
    assert sorted((r.turn, r.n_calls, r.orphan) for r in chat.format_chat(two).collect()) == [(0, 2, False), (0, 2, False), (5000, 0, False)]
