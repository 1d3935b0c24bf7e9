"""Two ways to run a rule: over the whole collection as one SQL plan, or page by page inside rows.

Page by page suits collections that grow: a page never needs another one, so the
plan has no shuffle and runs on streams as well.  The evaluator is plain nested
loops over one page's regions and serves as the reference for small tests.
"""

from __future__ import annotations

import operator
import re
from collections.abc import Iterator
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions.predicates import ascii_word
from ..session import shipped
from .rules import VALUES, BoxLiteral, Call, Compare, Field, Logic, Rule, RuleError, aliases, conjuncts, to_df

EDGES = ("x_l", "y_l", "x_h", "y_h")
NESTED = ("region_id", *EDGES, "text_start", "text_end", "text", "html_tag")
_OPS = {"=": operator.eq, "<>": operator.ne, "<": operator.lt, ">": operator.gt, "<=": operator.le, ">=": operator.ge}


def run_collection(rule: Rule, regions: DataFrame, views: dict[str, DataFrame] | None = None) -> DataFrame:
    return to_df(rule, regions, views)


# ---------------------------------------------------------------- one page
def _box(x: Any, row: dict[str, dict]) -> tuple:
    return x.bounds if isinstance(x, BoxLiteral) else tuple(row[x.alias][e] for e in EDGES)


def _at_most(a: int | None, b: int | None) -> bool:
    return a is None or b is None or a <= b


def _holds_call(x: Call, row: dict[str, dict]) -> bool:
    name = x.name.lower()
    if name in ("follows", "overlap", "spanin", "samespan"):
        a, b = (row[f.alias] for f in x.args[:2])
        s, e, t, u = a["text_start"], a["text_end"], b["text_start"], b["text_end"]
        return {"follows": lambda: e <= t and t - e <= x.args[2], "overlap": lambda: s < u and t < e, "spanin": lambda: t <= s and e <= u and (s, e) != (t, u), "samespan": lambda: (s, e) == (t, u)}[name]()
    a, b = _box(x.args[0], row), _box(x.args[1], row)
    across = _at_most(b[0], a[0]) and _at_most(a[2], b[2])
    along = _at_most(b[1], a[1]) and _at_most(a[3], b[3])
    if name == "contains":
        return across and along
    if name == "intersects":
        return _at_most(a[0], b[2]) and _at_most(b[0], a[2]) and _at_most(a[1], b[3]) and _at_most(b[1], a[3])
    if name == "touches":
        less = lambda p, o: p is None or o is None or p < o
        same = lambda p, o: p is not None and p == o
        shared = lambda i: less(a[i], b[i + 2]) and less(b[i], a[i + 2])
        on = lambda i: same(a[i + 2], b[i]) or same(b[i + 2], a[i])
        return (on(0) and shared(1)) or (on(1) and shared(0))
    side = name.removeprefix("strict").removesuffix("of")
    sides = {"north": _at_most(a[3], b[1]), "south": _at_most(b[3], a[1]), "east": _at_most(b[2], a[0]), "west": _at_most(a[2], b[0])}
    place = all(v for k, v in sides.items() if k in side)
    return place and (not name.startswith("strict") or (across if side in ("north", "south") else along))


def _value(x: Any, row: dict[str, dict]) -> Any:
    if isinstance(x, Field):
        return row[x.alias][x.name]
    if isinstance(x, Call) and x.name.lower() in VALUES:
        a, b = _box(x.args[0], row), _box(x.args[-1], row)
        return {
            "area": lambda: (a[2] - a[0]) * (a[3] - a[1]), "centroidx": lambda: (a[0] + a[2]) / 2, "centroidy": lambda: (a[1] + a[3]) / 2,
            "gapx": lambda: max(0, a[0] - b[2], b[0] - a[2]), "gapy": lambda: max(0, a[1] - b[3], b[1] - a[3]),
        }[x.name.lower()]()
    return x


def holds(x: Any, row: dict[str, dict]) -> bool:
    if x is None:
        return True
    if isinstance(x, Logic):
        if x.op == "NOT":
            return not holds(x.terms[0], row)
        return all(holds(t, row) for t in x.terms) if x.op == "AND" else any(holds(t, row) for t in x.terms)
    if isinstance(x, Compare):
        a, b = _value(x.left, row), _value(x.right, row)
        return a is not None and b is not None and _OPS[x.op](a, b)
    return _holds_call(x, row)


def _java_to_python(pattern: str) -> re.Pattern:
    return re.compile(pattern, re.ASCII)


def evaluate_page(rule: Rule, regions: list[dict]) -> list[tuple]:
    """Selected values of every combination of the page's regions that the rule holds for."""
    if rule.group:
        raise RuleError("groupings run over the collection")
    wanted = []
    for s in rule.sources:
        if s.kind in ("PHRASE", "POSTINGS", "REGEX"):
            rx = _java_to_python(ascii_word(s.arg) if s.kind != "REGEX" else s.arg)
            wanted.append([r for r in regions if r["text"] is not None and rx.search(r["text"])])
        elif s.kind in ("REGIONS", "ANCESTORS", "DESCENDANTS"):
            wanted.append(regions)
        else:
            raise RuleError(f"{s.kind} runs over the collection")
    # Each condition is tested as soon as all it speaks of is bound; those on one source thin it out beforehand.
    names = [s.alias for s in rule.sources]
    tests: list[list[Any]] = [[] for _ in names]
    for t in conjuncts(rule.where):
        at = max((names.index(a) for a in aliases(t)), default=0)
        if len(aliases(t)) == 1:
            wanted[at] = [r for r in wanted[at] if holds(t, {names[at]: r})]
        else:
            tests[at].append(t)
    out: list[tuple] = []

    def step(i: int, row: dict[str, dict]) -> None:
        if i == len(rule.sources):
            out.append(tuple(_value(x, row) for x in rule.select))
            return
        s = rule.sources[i]
        for r in wanted[i]:
            if s.kind == "ANCESTORS" and not row[s.arg]["region_id"].startswith(r["region_id"] + "."):
                continue
            if s.kind == "DESCENDANTS" and not r["region_id"].startswith(row[s.arg]["region_id"] + "."):
                continue
            now = {**row, s.alias: r}
            if all(holds(t, now) for t in tests[i]):
                step(i + 1, now)

    step(0, {})
    return list(dict.fromkeys(out)) if rule.distinct else out


def run_per_page(rule: Rule, nested: DataFrame) -> DataFrame:
    """A rule over ``page_id, regions`` (arrays of NESTED): stateless, no shuffle."""
    names = [f"{x.name}" if isinstance(x, Field) else f"c{i}" for i, x in enumerate(rule.select)]
    kinds = {"page_id": "long", **{e: "long" for e in EDGES}, "text_start": "long", "text_end": "long"}
    schema = ", ".join(f"{n} {kinds.get(n, 'string')}" for n in names)
    types = [pa.int64() if kinds.get(n) == "long" else pa.string() for n in names]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for page, regions in zip(batch.column("page_id").to_pylist(), batch.column("regions").to_pylist(), strict=True):
                rows += evaluate_page(rule, [{**r, "page_id": page} for r in regions])
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names)

    return shipped(nested).mapInArrow(run, schema)
