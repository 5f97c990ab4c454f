"""Secret scan: fixed patterns, and sliding-window Shannon entropy over candidate strings (DataFrame functions only).

The patterns give the base spans. The entropy method looks at maximal runs of key characters of at least ``WINDOW``
characters, sorts each into a character class, and slides a window over it: counts of the characters in the window and
the sum of c*log2(c) are updated by the character that leaves and the one that enters. A run whose best window reaches
its class's threshold adds a span, unless an allow-list pattern fits all of it; placeholder words and repeated characters
inside a run take out the windows at them, not the run. What an assignment covers is no part of a run, and a run that is
an access or hex span as a whole adds nothing; a run that such a span is only a part of is judged as a whole. Every text
is scanned whole; the expensive parts run only on texts that hold a candidate. Running sums over matches go by groups of
``GROUP``, so a text of very many matches takes time in proportion to them.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import unused

#: Patterns of the base spans.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{14,}"
HEX = r"[0-9a-f]{16,}"
VALUE_LEAST = 12

WINDOW = 20
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
#: Character classes in the order they are tried: name, pattern of the whole run, least entropy in bits of its best window.
CLASSES = (
    ("hex", r"^(?=.*[0-9])(?=.*[A-Fa-f])[0-9A-Fa-f]+$", 3.0),
    ("alnum", r"^(?=.*[0-9])(?=.*[A-Za-z])([A-Z0-9]+|[a-z0-9]+)$", 3.4),
    ("mixed", r"^(?=.*[0-9])(?=.*[A-Z])(?=.*[a-z])[A-Za-z0-9+/_=-]+$", 3.7),
    ("marked", r"^(?=.*[0-9])(?=.*[A-Za-z])([A-Z0-9+/_=-]+|[a-z0-9+/_=-]+)$", 3.6),
    ("letters", r"^(?=.*[A-Za-z])([A-Z+/_=-]+|[a-z+/_=-]+)$", 3.9),
    ("two cases", r"^(?=.*[A-Z])(?=.*[a-z])[A-Za-z+/_=-]+$", 4.0),
    ("digits", r"^(?=.*[0-9])[0-9+/_=-]+$", 3.5),
)  # what is left is marks alone, whose five characters cannot reach any of these
#: Whole runs that are no secrets: UUIDs, path-like, snake- and kebab-case words and short numbers.
ALLOW = (
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"^/?(?:(?:[a-z]++|[0-9]{1,4}+)[/_-])++[a-z]*+[0-9]{0,4}+/?$",  # possessive: long runs need no stack
)
#: Parts of a run that are no secrets, with what is within a window of them: documentation examples and placeholders.
PLACEHOLDER = r"(?i)example|sample|placeholder|changeme|dummy"
_ZONE = rf"(?i).{{0,{WINDOW}}}(?:{PLACEHOLDER[4:]}).{{0,{WINDOW}}}"
#: Windows that hold one character this often in a row do not count.
REPEATS = 8
_REPEAT = rf"(.)\1{{{REPEATS - 1},}}+"
KINDS = ("assign", "access", "hex", "entropy")
#: Matches whose positions are summed up together.
GROUP = 128
_SPANS = "array<struct<start:int,end:int,text:string>>"


def _let(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once: within a lambda, a plain column would be evaluated at every element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _grouped(items: Column) -> Column:
    """An array (a lambda's variable) in groups of ``GROUP``; one empty group if it is empty."""
    last = F.greatest(F.floor((F.size(items) - 1) / GROUP), F.lit(0)).cast("int")
    return F.transform(F.sequence(F.lit(0), last), lambda g: F.slice(items, g * GROUP + 1, GROUP))


def spans(text: Column, pattern: str) -> Column:
    """Leftmost non-overlapping matches of ``pattern`` as (start, end, text), in code points, end exclusive."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern, -1)
    steps = F.zip_with(found, F.slice(between, F.lit(1), F.size(found)), lambda m, gap: F.struct(F.length(gap).alias("gap"), F.length(m).alias("size"), m.alias("text")))

    def total(acc: Column, x: Column) -> Column:
        return acc + x["gap"] + x["size"]

    def after(acc: Column, group: Column) -> Column:
        return F.array_append(acc, F.aggregate(group, F.element_at(acc, -1), total))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + x["gap"]
        end = start + x["size"]
        return F.struct(end.alias("at"), F.array_append(acc["out"], F.struct(start.alias("start"), end.alias("end"), x["text"].alias("text"))).alias("out"))

    def inside(group: Column, at: Column) -> Column:
        return F.aggregate(group, F.struct(at.alias("at"), F.array().cast(_SPANS).alias("out")), step, lambda acc: acc["out"])

    def placed(groups: Column) -> Column:
        starts = F.aggregate(groups, F.array(F.lit(0)), after)  # where each group begins, and the end
        return F.flatten(F.zip_with(groups, F.slice(starts, F.lit(1), F.size(groups)), inside))

    each = _let(steps, lambda x: _let(_grouped(x), placed))
    return F.when(text.rlike(pattern), each).otherwise(F.array().cast(_SPANS))


def _without_assignments(text: Column) -> Column:
    """``text`` with blanks in place of every assignment whose value is long enough; all positions stay."""
    found = F.regexp_extract_all(text, F.lit(ASSIGN), F.lit(0))
    gone = F.transform(found, lambda m: F.when(F.length(F.regexp_extract(m, ASSIGN, 2)) >= VALUE_LEAST, F.repeat(F.lit(" "), F.length(m))).otherwise(m))
    blank = F.array_join(F.zip_with(F.split(text, ASSIGN, -1), F.concat(gone, F.array(F.lit(""))), lambda b, m: F.concat(b, m)), "")
    return F.when(text.rlike(ASSIGN), blank).otherwise(text)


def _clog(c: Column) -> Column:
    return F.when(c > 0, c * F.log2(c.cast("double"))).otherwise(F.lit(0.0))


def best_entropy(text: Column, window: int = WINDOW) -> Column:
    """The largest Shannon entropy, in bits, of any window of ``window`` characters of an ASCII text at least that long."""
    codes = F.transform(F.split(text, ""), F.ascii)  # one pass; a substring per place would be quadratic in the run
    zero = F.struct(F.array_repeat(F.lit(0), 128).alias("n"), F.lit(0.0).alias("s"), F.lit(math.inf).alias("least"), F.lit(0).alias("at"), codes.alias("codes"))

    def plus(n: Column, code: Column, by: int) -> Column:
        return F.concat(F.slice(n, F.lit(1), code), F.array(F.get(n, code) + by), F.slice(n, code + 2, F.lit(127) - code))

    def step(acc: Column, code: Column) -> Column:
        at = acc["at"] + 1
        gone = F.when(at > window, F.get(acc["codes"], at - 1 - window)).otherwise(F.lit(-1))
        old_in, old_out = F.get(acc["n"], code), F.coalesce(F.get(acc["n"], gone), F.lit(0))
        same = gone == code
        s = acc["s"] + F.when(same, 0.0).otherwise(_clog(old_in + 1) - _clog(old_in) + F.when(gone >= 0, _clog(old_out - 1) - _clog(old_out)).otherwise(0.0))
        n = F.when(same, acc["n"]).when(gone >= 0, plus(plus(acc["n"], code, 1), gone, -1)).otherwise(plus(acc["n"], code, 1))
        return F.struct(n.alias("n"), s.alias("s"), F.when(at >= window, F.least(acc["least"], s)).otherwise(acc["least"]).alias("least"), at.alias("at"), acc["codes"].alias("codes"))

    least = F.aggregate(codes, zero, step, lambda acc: acc["least"])
    return F.lit(math.log2(window)) - least / window


def _parts(run: Column) -> Column:
    """The parts of a run whose windows count: between placeholders and their surroundings, and between repeats."""
    calm = F.when(run.rlike(PLACEHOLDER), F.regexp_replace(run, _ZONE, "\n")).otherwise(run)
    side = "$1" * (REPEATS - 1)
    return F.filter(F.split(F.regexp_replace(calm, _REPEAT, f"{side}\n{side}"), "\n"), lambda part: F.length(part) >= WINDOW)


def _suspicious(run: Column) -> Column:
    """Is this run on no allow-list, and the best window of its parts above its class's threshold?"""
    need = F.lit(None).cast("double")
    for _, pattern, least in reversed(CLASSES):
        need = F.when(run.rlike(pattern), F.lit(least)).otherwise(need)
    allowed = F.lit(False)
    for pattern in ALLOW:
        allowed = allowed | run.rlike(pattern)
    return F.when(allowed | need.isNull(), False).otherwise(F.exists(_parts(run), lambda part: best_entropy(part) >= need))


def find(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """``docs`` plus a column for each kind, arrays of (start, end, text), and the names of these columns.

    They are named so that none clashes with a column of ``docs``. A null text counts as empty.
    """
    *own, runs, plain = unused(docs, *KINDS, "runs", "plain")
    name = dict(zip(KINDS, own))
    text = F.coalesce(F.col("text"), F.lit(""))
    out = docs.withColumns({name["assign"]: spans(text, ASSIGN), name["access"]: spans(text, ACCESS), name["hex"]: spans(text, HEX), plain: _without_assignments(text)})
    out = out.withColumn(runs, spans(F.col(plain), CANDIDATE))
    a = F.col(name["assign"])
    out = out.withColumn(name["assign"], F.when(F.size(a) > 0, F.filter(a, lambda x: F.length(F.regexp_extract(x["text"], ASSIGN, 2)) >= VALUE_LEAST)).otherwise(a))
    fresh = F.filter(runs, lambda run: ~run["text"].rlike(f"^(?:{ACCESS}|{HEX})$") & _suspicious(run["text"]))
    return out.withColumn(name["entropy"], F.when(F.size(runs) > 0, fresh).otherwise(F.array().cast(_SPANS))).drop(runs, plain), name


def _joined(name: dict[str, str], kinds: tuple[str, ...]) -> Column:
    """kind:start:end of the spans of ``kinds``, by start, then kind as listed, comma-joined."""
    def tag(kind: str) -> Column:
        number = F.lit(KINDS.index(kind))
        return F.transform(F.col(name[kind]), lambda x: F.struct(x["start"].alias("start"), number.alias("kind"), x["end"].alias("end")))

    tagged = F.concat(*[tag(k) for k in kinds])
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(F.array_sort(tagged), lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["end"].cast("string"))), ",")


def scan(docs: DataFrame) -> DataFrame:
    """A row per row of ``docs``: doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_entropy.

    Without secrets: zeros, the hash of an empty string, an empty string. Null ids and repeated rows give rows like others;
    other columns play no part, whatever their names. An empty table gives no rows.
    """
    found, name = find(docs.select("doc_id", F.col("text").cast("string")))
    counts = [F.size(name[k]).cast("long").alias(f"n_{k}") for k in KINDS]
    return found.select("doc_id", *counts[:3], F.sha2(_joined(name, KINDS[:3]), 256).alias("base_sha256"), _joined(name, KINDS).alias("spans"), counts[3])


def redact(docs: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """``docs`` with every found span of ``text`` replaced by ``mask``; overlapping spans are masked as one.

    All rows and columns stay, whatever their names; a null text stays null. Spans are cut out by groups, each from its own
    part of the text.
    """
    found, name = find(docs)
    every = F.array_sort(F.transform(F.concat(*[F.col(name[k]) for k in KINDS]), lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"))))

    def rest(text: Column, n: Column) -> Column:
        return F.substring(text, n + 1, F.length(text))

    def step(acc: Column, x: Column) -> Column:
        gap, on = x["start"] - acc["at"], F.greatest(x["end"] - acc["at"], F.lit(0))
        out = F.when(gap >= 0, F.concat(acc["out"], F.substring(acc["text"], F.lit(1), gap), F.lit(mask))).otherwise(acc["out"])
        return F.struct((acc["at"] + on).alias("at"), rest(acc["text"], on).alias("text"), out.alias("out"))

    def group(acc: Column, spans_: Column) -> Column:
        return _let(F.greatest(F.array_max(F.transform(spans_, lambda x: x["end"])), acc["at"]), lambda to: cut_to(acc, spans_, to))

    def cut_to(acc: Column, spans_: Column, to: Column) -> Column:
        own = F.struct(acc["at"].alias("at"), F.substring(acc["text"], F.lit(1), to - acc["at"]).alias("text"), F.lit("").alias("out"))
        done = F.aggregate(spans_, own, step, lambda a: a["out"])
        return F.struct(to.alias("at"), rest(acc["text"], to - acc["at"]).alias("text"), F.array_append(acc["out"], done).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.col("text").cast("string").alias("text"), F.array().cast("array<string>").alias("out"))
    masked = F.aggregate(_let(every, _grouped), start, group, lambda acc: F.concat(F.array_join(acc["out"], ""), acc["text"]))
    has = sum((F.size(name[k]) for k in KINDS), F.lit(0)) > 0
    return found.withColumn("text", F.when(has, masked).otherwise(F.col("text"))).select(*docs.columns)
