"""Rule language: text to a typed tree, rewrites, and lowering to one SQL statement.

    SELECT s.page_id, s.region_id
    FROM PHRASE('Return Flag', D) AS h, PHRASE('Returned', D) AS v, REGIONS(D) AS s
    WHERE StrictSouthOf(v, h) AND StrictEastOf(s, v)

Sources: REGIONS(D), REGEX('p', D), PHRASE('p', D), DICT('view', D), ANCESTORS(a), DESCENDANTS(a),
MAXIMAL(a), MINIMAL(a).  Boxes: BOX(x_l, y_l, x_h, y_h) with INF for a missing bound.  Grouping:
GROUP BY ALIGNED(COLUMN|ROW [, CONSECUTIVE] [, MAXDIST n]) HAVING COUNT > n AND Contains(MBR, BOX(...)); a grouped
rule may select SUPER.region_id, the least node around each group.  Values: Area(a), CentroidX(a), CentroidY(a),
GapX(a, b), GapY(a, b).
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace
from typing import Any

from pyspark.sql import DataFrame, SparkSession

from ..functions.predicates import ascii_word

EDGES = ("x_l", "y_l", "x_h", "y_h")


class RuleError(ValueError):
    """The rule is not well formed."""


# ---------------------------------------------------------------- tree
@dataclass(frozen=True)
class Source:
    kind: str
    alias: str
    arg: str | None = None


@dataclass(frozen=True)
class Call:
    name: str
    args: tuple[Any, ...]


@dataclass(frozen=True)
class Compare:
    op: str
    left: Any
    right: Any


@dataclass(frozen=True)
class Logic:
    op: str  # AND, OR, NOT
    terms: tuple[Any, ...]


@dataclass(frozen=True)
class Field:
    alias: str
    name: str


@dataclass(frozen=True)
class BoxLiteral:
    bounds: tuple[int | None, ...]


@dataclass(frozen=True)
class Grouping:
    axis: str
    consecutive: bool = False
    max_dist: int | None = None


@dataclass(frozen=True)
class Rule:
    select: tuple[Any, ...]
    sources: tuple[Source, ...]
    where: Any = None
    group: Grouping | None = None
    having: Any = None
    distinct: bool = False
    access: str = "none"
    notes: tuple[str, ...] = field(default=())


SOURCES = ("REGIONS", "REGEX", "PHRASE", "DICT", "ANCESTORS", "DESCENDANTS", "MAXIMAL", "MINIMAL")
#: Rule-language names of predicates on two boxes, and of those on two text spans.
BOX_PREDICATES = {
    **{f"{s}{d}of": f"{p}{d}_of" for s, p in (("", ""), ("strict", "strict_")) for d in ("north", "south", "east", "west")},
    **{f"{v}{h}of": f"{v}_{h}_of" for v in ("north", "south") for h in ("east", "west")},
    "contains": "box_within", "touches": "box_touches", "intersects": "box_intersects",
}
SPAN_PREDICATES = {"follows": 3, "overlap": 2, "spanin": 2, "samespan": 2}
#: Functions that give a number, and how many boxes they take.
VALUES = {"area": 1, "centroidx": 1, "centroidy": 1, "gapx": 2, "gapy": 2}
#: Names that stand for a group's properties.
GROUP_NAMES = ("MBR", "COUNT", "SUPER")

_LEX = re.compile(r"\s*(?:(?P<str>'(?:[^']|'')*')|(?P<num>-?\d+)|(?P<name>[A-Za-z_][A-Za-z0-9_]*)|(?P<op><=|>=|<>|!=|[=<>(),.*]))")


def lex(text: str) -> list[tuple[str, str]]:
    out, at = [], 0
    text = text.rstrip()
    while at < len(text):
        m = _LEX.match(text, at)
        if not m:
            raise RuleError(f"cannot read {text[at : at + 20]!r}")
        out.append((m.lastgroup, m.group(m.lastgroup)))
        at = m.end()
    return out


class _Reader:
    def __init__(self, tokens: list[tuple[str, str]]) -> None:
        self.tokens, self.at = tokens, 0

    def peek(self, ahead: int = 0) -> str:
        i = self.at + ahead
        return self.tokens[i][1].upper() if i < len(self.tokens) else ""

    def take(self, want: str | None = None) -> tuple[str, str]:
        if self.at >= len(self.tokens):
            raise RuleError(f"the rule ends where {want or 'more'} is needed")
        kind, value = self.tokens[self.at]
        if want is not None and value.upper() != want:
            raise RuleError(f"{want} is needed, not {value}")
        self.at += 1
        return kind, value

    def accept(self, want: str) -> bool:
        if self.peek() == want:
            self.at += 1
            return True
        return False


def parse(text: str) -> Rule:
    r = _Reader(lex(text))
    r.take("SELECT")
    distinct = r.accept("DISTINCT")
    select = [_operand(r)]
    while r.accept(","):
        select.append(_operand(r))
    r.take("FROM")
    sources = [_source(r)]
    while r.accept(","):
        sources.append(_source(r))
    where = _or(r) if r.accept("WHERE") else None
    group = having = None
    if r.accept("GROUP"):
        r.take("BY")
        r.take("ALIGNED")
        r.take("(")
        axis = r.take()[1].lower()
        consecutive, far = False, None
        while r.accept(","):
            word = r.take()[1].upper()
            if word == "CONSECUTIVE":
                consecutive = True
            elif word == "MAXDIST":
                far = int(r.take()[1])
            else:
                raise RuleError(f"unknown flag {word}")
        r.take(")")
        group = Grouping(axis, consecutive, far)
        having = _or(r) if r.accept("HAVING") else None
    if r.at < len(r.tokens):
        raise RuleError(f"cannot read {r.tokens[r.at][1]!r}")
    return check(Rule(tuple(select), tuple(sources), where, group, having, distinct))


def _source(r: _Reader) -> Source:
    kind = r.take()[1].upper()
    if kind not in SOURCES:
        raise RuleError(f"unknown source {kind}")
    r.take("(")
    value = r.take()
    arg = value[1][1:-1].replace("''", "'") if value[0] == "str" else value[1]
    if r.accept(","):
        r.take()
    elif kind == "REGIONS":
        arg = None
    r.take(")")
    r.take("AS")
    return Source(kind, r.take()[1], arg)


def _or(r: _Reader) -> Any:
    terms = [_and(r)]
    while r.accept("OR"):
        terms.append(_and(r))
    return terms[0] if len(terms) == 1 else Logic("OR", tuple(terms))


def _and(r: _Reader) -> Any:
    terms = [_not(r)]
    while r.accept("AND"):
        terms.append(_not(r))
    return terms[0] if len(terms) == 1 else Logic("AND", tuple(terms))


def _not(r: _Reader) -> Any:
    if r.accept("NOT"):
        return Logic("NOT", (_not(r),))
    if r.peek() == "(":
        r.take()
        inner = _or(r)
        r.take(")")
        return inner
    left = _operand(r)
    if r.peek() in ("=", "<", ">", "<=", ">=", "<>", "!="):
        op = r.take()[1]
        return Compare("<>" if op == "!=" else op, left, _operand(r))
    return left


def _operand(r: _Reader) -> Any:
    kind, value = r.take()
    if kind == "num":
        return int(value)
    if kind == "str":
        return value[1:-1].replace("''", "'")
    if value.upper() == "BOX":
        r.take("(")
        bounds = []
        for i in range(4):
            if i:
                r.take(",")
            word = r.take()[1]
            bounds.append(None if word.upper() == "INF" else int(word))
        r.take(")")
        return BoxLiteral(tuple(bounds))
    if r.accept("("):
        args = []
        if not r.accept(")"):
            args.append(_operand(r))
            while r.accept(","):
                args.append(_operand(r))
            r.take(")")
        return Call(value, tuple(args))
    if r.accept("."):
        return Field(value, r.take()[1])
    return Field(value, "")


# ---------------------------------------------------------------- checks
def check(rule: Rule) -> Rule:
    """Aliases are known, predicates exist and have the right number of arguments."""
    names = {s.alias for s in rule.sources}
    if len(names) < len(rule.sources):
        raise RuleError("an alias stands twice")
    known: set[str] = set()
    for s in rule.sources:
        if s.kind in ("ANCESTORS", "DESCENDANTS", "MAXIMAL", "MINIMAL") and s.arg not in known:
            raise RuleError(f"{s.kind} needs an alias before it, not {s.arg}")
        known.add(s.alias)

    def visit(x: Any) -> None:
        if isinstance(x, Field) and x.alias not in names and not (rule.group and x.alias.upper() in GROUP_NAMES):
            raise RuleError(f"unknown alias {x.alias}")
        if isinstance(x, Call):
            low = x.name.lower()
            wanted = SPAN_PREDICATES.get(low) or VALUES.get(low) or (2 if low in BOX_PREDICATES else None)
            if wanted is None:
                raise RuleError(f"unknown predicate {x.name}")
            if len(x.args) != wanted:
                raise RuleError(f"{x.name} has {len(x.args)} arguments")
            for a in x.args:
                visit(a)
        if isinstance(x, Compare):
            visit(x.left)
            visit(x.right)
        if isinstance(x, Logic):
            for t in x.terms:
                visit(t)

    for x in (*rule.select, rule.where, rule.having):
        visit(x)
    if rule.group and len(rule.sources) != 1:
        raise RuleError("alignment groups the spans of one source")
    return rule


# ---------------------------------------------------------------- rewrites
def phrase_of(pattern: str) -> str | None:
    """The phrase if the pattern is nothing but words and blanks: only those can the text index answer as a scan would."""
    return pattern if re.fullmatch(r"[A-Za-z0-9_]+(?: [A-Za-z0-9_]+)*", pattern) else None


def rewrite(rule: Rule, access: str = "none", counts: dict[str, int] | None = None) -> Rule:
    """Order joins by match counts, send literal phrases to the text index, note what was done.

    ``counts`` are matches per alias (posting counts); sources without one are scanned last.
    """
    notes = []
    sources = list(rule.sources)
    if "text" in access:
        for i, s in enumerate(sources):
            if s.kind == "PHRASE" and phrase_of(s.arg):
                sources[i] = replace(s, kind="POSTINGS")
                notes.append(f"{s.alias}: text index")
            elif s.kind == "PHRASE":
                notes.append(f"{s.alias}: scan, as the phrase has more than words and blanks")
    if counts:
        free = [s for s in sources if s.kind not in ("ANCESTORS", "DESCENDANTS", "MAXIMAL", "MINIMAL")]
        rest = [s for s in sources if s not in free]
        sources = sorted(free, key=lambda s: counts.get(s.alias, 1 << 62)) + rest
        notes.append("join order: " + ", ".join(s.alias for s in sources))
    return replace(rule, sources=tuple(sources), access=access, notes=tuple(notes))


def conjuncts(x: Any) -> list[Any]:
    """The terms that must all hold."""
    if x is None:
        return []
    return [y for t in x.terms for y in conjuncts(t)] if isinstance(x, Logic) and x.op == "AND" else [x]


def aliases(x: Any) -> set[str]:
    """The aliases a term speaks of."""
    if isinstance(x, Field):
        return {x.alias}
    parts = getattr(x, "args", None) or getattr(x, "terms", None) or ((x.left, x.right) if isinstance(x, Compare) else ())
    return set().union(*map(aliases, parts)) if parts else set()


def constant_boxes(rule: Rule) -> dict[str, BoxLiteral]:
    """Per alias the constant box that must contain it."""
    found = {}
    for t in conjuncts(rule.where):
        if isinstance(t, Call) and t.name.lower() == "contains" and isinstance(t.args[0], Field) and isinstance(t.args[1], BoxLiteral):
            found[t.args[0].alias] = t.args[1]
    return found


# ---------------------------------------------------------------- lowering
def _box_sql(x: Any) -> list[str | None]:
    if isinstance(x, BoxLiteral):
        return [None if b is None else str(b) for b in x.bounds]
    if isinstance(x, Field) and not x.name:
        return [f"{x.alias}.{e}" for e in EDGES]
    raise RuleError(f"{x} is no box")


def _le(a: str | None, b: str | None) -> list[str]:
    return [] if a is None or b is None else [f"{a} <= {b}"]


def _predicate(call: Call) -> str:
    low = call.name.lower()
    if low in SPAN_PREDICATES:
        a, b = (x.alias for x in call.args[:2])
        return {
            "follows": f"({a}.text_end <= {b}.text_start AND {b}.text_start - {a}.text_end <= {call.args[2] if len(call.args) > 2 else 0})",
            "overlap": f"({a}.text_start < {b}.text_end AND {b}.text_start < {a}.text_end)",
            "spanin": f"({b}.text_start <= {a}.text_start AND {a}.text_end <= {b}.text_end AND ({a}.text_start <> {b}.text_start OR {a}.text_end <> {b}.text_end))",
            "samespan": f"({a}.text_start = {b}.text_start AND {a}.text_end = {b}.text_end)",
        }[low]
    a, b = _box_sql(call.args[0]), _box_sql(call.args[1])
    x_in, y_in = _le(b[0], a[0]) + _le(a[2], b[2]), _le(b[1], a[1]) + _le(a[3], b[3])
    plain = {"north": _le(a[3], b[1]), "south": _le(b[3], a[1]), "east": _le(b[2], a[0]), "west": _le(a[2], b[0])}
    if low == "contains":
        terms = x_in + y_in
    elif low == "intersects":
        terms = _le(a[0], b[2]) + _le(b[0], a[2]) + _le(a[1], b[3]) + _le(b[1], a[3])
    elif low == "touches":
        # An open bound is no edge that could be touched, and limits no overlap.
        on = lambda i: "(" + (" OR ".join(f"{p} = {o}" for p, o in ((a[i + 2], b[i]), (b[i + 2], a[i])) if p is not None and o is not None) or "FALSE") + ")"
        shared = lambda i: "(" + (" AND ".join(f"{p} < {o}" for p, o in ((a[i], b[i + 2]), (b[i], a[i + 2])) if p is not None and o is not None) or "TRUE") + ")"
        terms = [f"(({on(0)} AND {shared(1)}) OR ({on(1)} AND {shared(0)}))"]
    else:
        side = low.removeprefix("strict").removesuffix("of")
        sides = [d for d in plain if d in side]
        terms = [t for d in sides for t in plain[d]] + ((x_in if side in ("north", "south") else y_in) if low.startswith("strict") else [])
    return "(" + (" AND ".join(terms) or "TRUE") + ")"


def _value_sql(call: Call) -> str:
    boxes = [_box_sql(x) for x in call.args]
    if any(e is None for box in boxes for e in box):
        raise RuleError(f"{call.name} needs closed boxes")
    a, b = boxes[0], boxes[-1]
    return {
        "area": f"(({a[2]} - {a[0]}) * ({a[3]} - {a[1]}))", "centroidx": f"(({a[0]} + {a[2]}) / 2.0D)", "centroidy": f"(({a[1]} + {a[3]}) / 2.0D)",
        "gapx": f"greatest(0L, {a[0]} - {b[2]}, {b[0]} - {a[2]})", "gapy": f"greatest(0L, {a[1]} - {b[3]}, {b[1]} - {a[3]})",
    }[call.name.lower()]


def _expr(x: Any) -> str:
    if isinstance(x, Logic):
        return f"NOT {_expr(x.terms[0])}" if x.op == "NOT" else "(" + f" {x.op} ".join(map(_expr, x.terms)) + ")"
    if isinstance(x, Compare):
        return f"{_expr(x.left)} {x.op} {_expr(x.right)}"
    if isinstance(x, Call):
        return _value_sql(x) if x.name.lower() in VALUES else _predicate(x)
    if isinstance(x, Field):
        return f"{x.alias}.{x.name}" if x.name else x.alias
    if isinstance(x, str):
        return "'" + x.replace("'", "''") + "'"
    return str(x)


def _literal(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _prefixes_sql(path: str) -> str:
    """The paths above a path, as an array."""
    parts = f"split({path}, '[.]')"
    return f"if(size({parts}) > 1, transform(sequence(1, size({parts}) - 1), i -> array_join(slice({parts}, 1, i), '.')), array())"


def _source_sql(s: Source, views: dict[str, str], bare: bool = False) -> str:
    """A source as a table or subquery; ``bare`` if the rule needs no more than its ids and box."""
    regions = views["regions"]
    if s.kind == "REGIONS":
        return regions
    if s.kind == "REGEX":
        return f"(SELECT * FROM {regions} WHERE text IS NOT NULL AND rlike(text, {_literal(s.arg)}))"
    if s.kind == "PHRASE":
        return f"(SELECT * FROM {regions} WHERE text IS NOT NULL AND rlike(text, {_literal(ascii_word(s.arg))}))"
    if s.kind == "POSTINGS":
        from ..index.text import phrase_sql

        return phrase_sql(s.arg, views["postings"], None if bare else regions)
    if s.kind == "DICT":
        return f"(SELECT r.* FROM {regions} r LEFT SEMI JOIN {views[f'dict {s.alias}']} d ON r.page_id = d.page_id AND r.region_id = d.region_id)"
    raise RuleError(f"{s.kind} stands alone")


def _bare_aliases(rule: Rule) -> set[str]:
    """Aliases of which only ids and boxes are used."""
    used: set[str] = set()

    def visit(x: Any) -> None:
        if isinstance(x, Field) and x.name and x.name.lower() not in ("page_id", "region_id", *EDGES):
            used.add(x.alias)
        if isinstance(x, Call) and x.name.lower() in SPAN_PREDICATES:
            used.update(a.alias for a in x.args if isinstance(a, Field))
        for y in getattr(x, "args", None) or getattr(x, "terms", None) or ((x.left, x.right) if isinstance(x, Compare) else ()):
            visit(y)

    for x in (*rule.select, rule.where, rule.having):
        visit(x)
    return {s.alias for s in rule.sources} - used - {s.arg for s in rule.sources if s.kind in ("MAXIMAL", "MINIMAL")}


def to_sql(rule: Rule, views: dict[str, str] | None = None) -> str:
    """One SQL statement; every join gets the page's equality, so no pair crosses pages."""
    views = {"regions": "regions", "postings": "postings"} | {f"dict {s.alias}": f"dict_{s.alias}" for s in rule.sources} | (views or {})
    if rule.group:
        return _group_sql(rule, views)
    parts, first, bare = [], rule.sources[0].alias, _bare_aliases(rule)
    regions = views["regions"]
    for i, s in enumerate(rule.sources):
        a, c = s.arg, s.alias
        if s.kind in ("MAXIMAL", "MINIMAL"):
            parts.append(f"JOIN {regions} {c} ON {c}.page_id = {a}.page_id AND {c}.region_id = {a}.{s.kind.lower()}_region")
        elif s.kind == "ANCESTORS":  # the paths above are generated, so nodes meet by equality
            parts.append(f"JOIN LATERAL (SELECT explode({_prefixes_sql(f'{a}.region_id')}) AS up) up_{c} JOIN {regions} {c} ON {c}.page_id = {a}.page_id AND {c}.region_id = up_{c}.up")
        elif s.kind == "DESCENDANTS":
            parts.append(f"JOIN (SELECT *, explode({_prefixes_sql('region_id')}) AS up FROM {regions}) {c} ON {c}.page_id = {a}.page_id AND {c}.up = {a}.region_id")
        elif i == 0:
            parts.append(f"{_source_sql(s, views, c in bare)} {c}")
        else:
            parts.append(f"JOIN {_source_sql(s, views, c in bare)} {c} ON {c}.page_id = {first}.page_id")
    where = f" WHERE {_expr(rule.where)}" if rule.where is not None else ""
    return f"SELECT {'DISTINCT ' if rule.distinct else ''}{', '.join(map(_expr, rule.select))} FROM {' '.join(parts)}{where}"


def _having_box(having: Any) -> BoxLiteral | None:
    terms = having.terms if isinstance(having, Logic) and having.op == "AND" else [having]
    for t in terms:
        if isinstance(t, Call) and t.name.lower() == "contains" and isinstance(t.args[0], Field) and t.args[0].alias.upper() == "MBR":
            return t.args[1]
    return None


def _group_sql(rule: Rule, views: dict[str, str]) -> str:
    """Alignment groups by windows; a bound on the shared edge moves below the grouping.

    That bound leaves out spans that might stand between others, so it stays above for consecutive groups.
    """
    s, g = rule.sources[0], rule.group
    key, lo, hi, a_lo, a_hi = ("x_l", "y_l", "y_h", "x_l", "x_h") if g.axis == "column" else ("y_l", "x_l", "x_h", "y_l", "y_h")
    below = [_expr(rule.where)] if rule.where is not None else []
    box = _having_box(rule.having)
    if box is not None and not g.consecutive and box.bounds[EDGES.index(key)] is not None:
        below.append(f"{s.alias}.{key} >= {box.bounds[EDGES.index(key)]}")
    inner = f"SELECT {s.alias}.* FROM {_source_sql(s, views)} {s.alias}" + (f" WHERE {' AND '.join(below)}" if below else "")
    order = f"(PARTITION BY page_id, {key} ORDER BY {lo}, {hi}, region_id)"
    near = f"SELECT *, lag({hi}) OVER g AS _p_hi, lag({a_lo}) OVER g AS _p_a, lag({a_hi}) OVER g AS _p_b FROM ({inner}) WINDOW g AS {order}"
    cuts = [f"{lo} - _p_hi > {g.max_dist}"] if g.max_dist is not None else []
    if g.consecutive:
        split = f"""SELECT n.page_id, n.region_id, TRUE AS _split FROM (SELECT * FROM ({near}) WHERE {lo} > _p_hi) n LEFT SEMI JOIN ({inner}) o ON o.page_id = n.page_id AND o.{key} <> n.{key}
AND o.{a_lo} < greatest(n.{a_hi}, n._p_b) AND o.{a_hi} > least(n.{a_lo}, n._p_a) AND o.{lo} < n.{lo} AND o.{hi} > n._p_hi"""
        near = f"SELECT n.*, c._split FROM ({near}) n LEFT JOIN ({split}) c ON c.page_id = n.page_id AND c.region_id = n.region_id"
        cuts.append("_split")
    cut = f"CASE WHEN {' OR '.join(f'coalesce({c}, FALSE)' for c in cuts)} THEN 1 ELSE 0 END" if cuts else "0"
    runs = f"SELECT *, sum({cut}) OVER {order} AS island FROM ({near})"
    w = f"OVER (PARTITION BY page_id, {key}, island)"
    sized = f"SELECT *, count(*) {w} AS _n, min(x_l) {w} AS m_x_l, min(y_l) {w} AS m_y_l, max(x_h) {w} AS m_x_h, max(y_h) {w} AS m_y_h FROM ({runs})"
    having = ""
    if rule.having is not None:

        def sub(x: Any) -> Any:
            if isinstance(x, Field) and x.alias.upper() == "COUNT":
                return Field("_n", "")
            if isinstance(x, Compare):
                return Compare(x.op, sub(x.left), sub(x.right))
            if isinstance(x, Logic):
                return Logic(x.op, tuple(map(sub, x.terms)))
            return x

        having = " WHERE " + _expr(sub(rule.having))
        for e in EDGES:
            having = re.sub(rf"\bMBR\.{e}\b", f"m_{e}", having, flags=re.I)
    found = f"SELECT * FROM ({sized}) {s.alias}{having}"
    name = s.alias
    if any("SUPER" in {a.upper() for a in aliases(x)} for x in rule.select):
        group = f"page_id, {key}, island, m_x_l, m_y_l, m_x_h, m_y_h"
        size = "struct((r.x_h - r.x_l) * (r.y_h - r.y_l), -size(split(r.region_id, '[.]')), r.region_id)"
        found = f"""SELECT least.* FROM (SELECT g.page_id, g.{key}, g.island, min_by(struct(r.*), {size}) AS least FROM (SELECT DISTINCT {group} FROM ({found})) g
JOIN {views["regions"]} r ON r.page_id = g.page_id AND r.x_l <= g.m_x_l AND r.y_l <= g.m_y_l AND r.x_h >= g.m_x_h AND r.y_h >= g.m_y_h GROUP BY g.page_id, g.{key}, g.island)"""
        name = "SUPER"
    return f"SELECT {'DISTINCT ' if rule.distinct else ''}{', '.join(_expr(x) for x in rule.select)} FROM ({found}) {name}"


def to_df(rule: Rule, regions: DataFrame, views: dict[str, DataFrame] | None = None) -> DataFrame:
    """Run a rule over a relation of regions (and dictionary or postings views).

    The nodes of a dictionary source are found by an equi-join of runs of words and stand in a view of their own.
    """
    from ..operators.spans import dict_rows

    spark: SparkSession = regions.sparkSession
    views = dict(views or {})
    names = {}
    for s in rule.sources:
        if s.kind == "DICT":
            terms = views[s.arg] if s.arg in views else spark.table(s.arg)
            names[f"dict {s.alias}"] = f"rule_dict_{s.alias}"
            dict_rows(regions, terms, "text", ("page_id", "region_id")).select("page_id", "region_id").createOrReplaceTempView(f"rule_dict_{s.alias}")
    for name, df in {"regions": regions, **views}.items():
        df.createOrReplaceTempView(f"rule_{name}")
        names[name] = f"rule_{name}"
    return spark.sql(to_sql(rule, names))


def rule_size(rule: Rule) -> dict[str, int]:
    """Operators, predicates and constants of a rule: its simplicity."""
    counts = {"sources": len(rule.sources), "predicates": 0, "constants": sum(s.kind in ("REGEX", "PHRASE", "DICT") for s in rule.sources), "groupings": int(rule.group is not None)}

    def visit(x: Any) -> None:
        if isinstance(x, (Call, Compare)):
            counts["predicates"] += 1
        for y in getattr(x, "args", None) or getattr(x, "terms", None) or ((x.left, x.right) if isinstance(x, Compare) else ()):
            visit(y)
        if isinstance(x, BoxLiteral):
            counts["constants"] += sum(b is not None for b in x.bounds)
        if isinstance(x, (int, str)):
            counts["constants"] += 1

    visit(rule.where)
    visit(rule.having)
    return counts
