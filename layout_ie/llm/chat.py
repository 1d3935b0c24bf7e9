"""Chat formatting: layouts found by schema fingerprint, turns made canonical, formatted reversibly, read back.

Everything is DataFrame expressions.  A record's nested field paths that any
layout knows, over all elements of its arrays, are sorted and hashed as its fingerprint; the most
specific layout whose paths are among them is a declarative mapping to turns (role, text), and each
element of an array is read by its own layout.  Extra fields do not change the layout.  A table's
columns are fingerprinted in the same way: a layout of turn rows maps them to conversations, a layout of
records is read record by record.

The template writes each turn as ``<|turn|>role``, a line feed, the text and
``<|end|>`` with a line feed.  Control strings of common templates inside a text get
a backslash after their first character (one more if there are some), so no
text can end a turn, and taking one away gives the text back.  Roles are written
percent-encoded.  The loss mask lists the code point ranges of assistant texts.

Defined results: a null text or role is empty; turns of a conversation stand in
the order of turn, role, text, repeated rows included; a row with a null conversation id is a
conversation by itself, equal ones are one; a record of no known layout has null turns, a table of none
raises; empty tables give empty results.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce
from operator import or_

import xxhash
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import unused

START, END = "<|turn|>", "<|end|>\n"
#: First characters and rests of control strings: fixed values of common templates.
_CONTROL_HEAD = r"(<|\[)"
_CONTROL_TAIL = r"(\||/?s>|/?INST\]|</?SYS>>|/?system>|/?user>|/?assistant>)"
TURN = "struct<role:string,text:string>"


# ---------------------------------------------------------------- layouts
@dataclass(frozen=True)
class Layout:
    """``paths`` identify the layout.

    Either ``turns`` names an array with ``role`` and ``text`` fields, or ``parts`` are (role, field, ...) to join by
    an empty line, or each row is a turn with ``role`` and ``text`` at place ``order`` of conversation ``group``.
    """

    name: str
    paths: tuple[str, ...]
    turns: str = ""
    role: str = ""
    text: str = ""
    parts: tuple[tuple[str, ...], ...] = ()
    group: str = ""
    order: str = ""


LAYOUTS = (
    Layout("messages", ("messages", "messages[].role", "messages[].content"), "messages", "role", "content"),
    Layout("dialog", ("conversations", "conversations[].from", "conversations[].value"), "conversations", "from", "value"),
    Layout("system_dialog", ("system", "conversations", "conversations[].from", "conversations[].value"), "conversations", "from", "value", (("system", "system"),)),
    Layout("instruction_input", ("instruction", "input", "output"), parts=(("user", "instruction", "input"), ("assistant", "output"))),
    Layout("instruction", ("instruction", "output"), parts=(("user", "instruction"), ("assistant", "output"))),
    Layout("prompt_completion", ("prompt", "completion"), parts=(("user", "prompt"), ("assistant", "completion"))),
    Layout("prompt_response", ("prompt", "response"), parts=(("user", "prompt"), ("assistant", "response"))),
    Layout("system_prompt_response", ("system", "prompt", "response"), parts=(("system", "system"), ("user", "prompt"), ("assistant", "response"))),
    Layout("question_answer", ("question", "answer"), parts=(("user", "question"), ("assistant", "answer"))),
    Layout("question_context", ("context", "question", "answer"), parts=(("user", "context", "question"), ("assistant", "answer"))),
)
#: Tables with one row a turn.
ROW_LAYOUTS = tuple(
    Layout(name, (group, order, role, text), "", role, text, (), group, order)
    for name, group, order, role, text in (
        ("turn_rows", "conv_id", "turn", "role", "text"),
        ("message_rows", "conversation_id", "message_index", "role", "content"),
        ("dialog_rows", "conversation_id", "turn", "from", "value"),
        ("utterance_rows", "dialogue_id", "turn_id", "speaker", "utterance"),
    )
)
#: Names that layouts use for the canonical roles.
ROLE_NAMES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}


def _known(layouts: tuple[Layout, ...]) -> list[str]:
    """The layouts' paths; any array of turns may hold elements of any layout."""
    turns = [x for x in layouts if x.turns]
    return sorted({p for x in layouts for p in x.paths} | {f"{x.turns}[].{n}" for x in turns for y in turns for n in (y.role, y.text)})


def paths_hash(paths: Column) -> Column:
    return F.xxhash64(F.array_join(F.array_sort(F.array_distinct(paths)), "\n"))


def _elements(record: Column, array: str) -> Column:
    """The elements of a JSON array as JSON texts; null where it is no array."""
    return F.from_json(F.get_json_object(record, f"$.{array}"), T.ArrayType(T.StringType()))


def record_paths(record: Column, layouts: tuple[Layout, ...] = LAYOUTS) -> Column:
    """The nested field paths of a JSON record, over all elements of its arrays, that some layout knows."""
    none = F.array().cast("array<string>")
    top = F.coalesce(F.json_object_keys(record), none)

    def below(a: str) -> Column:
        keys = F.flatten(F.transform(F.coalesce(_elements(record, a), none), lambda x: F.coalesce(F.json_object_keys(x), none)))
        return F.transform(keys, lambda k: F.concat(F.lit(f"{a}[]."), k))

    nested = [below(a) for a in sorted({x.turns for x in layouts if x.turns})]
    return F.array_intersect(F.concat(top, *nested), F.array(*map(F.lit, _known(layouts))))


def _needs(layout: Layout) -> tuple[str, ...]:
    """The paths a record must have: all top fields; what its turns look like is seen to one by one."""
    return tuple(p for p in layout.paths if not (layout.turns and "[]" in p))


def canonical_role(role: Column) -> Column:
    low = F.lower(F.trim(F.coalesce(role, F.lit(""))))
    names = F.create_map(*(F.lit(x) for kv in ROLE_NAMES.items() for x in kv))
    return F.coalesce(names[low], low)


def _said(array: str, record: Column, layouts: tuple[Layout, ...]) -> Column:
    """Turns of an array, each element by the first layout whose role or text field it has."""
    kinds = list(dict.fromkeys((x.role, x.text) for x in layouts if x.turns))

    def turn(x: Column) -> Column:
        field = lambda names: F.coalesce(*(F.get_json_object(x, f"$.{n}") for n in dict.fromkeys(names)), F.lit(""))
        return F.struct(canonical_role(field(r for r, _ in kinds)).alias("role"), field(t for _, t in kinds).alias("text"))

    return F.transform(_elements(record, array), turn)


def _layout_turns(layout: Layout, record: Column, layouts: tuple[Layout, ...] = LAYOUTS) -> Column:
    field = lambda name: F.get_json_object(record, f"$.{name}")
    turns = F.array().cast(f"array<{TURN}>")
    if layout.parts:
        one = []
        for role, *fields in layout.parts:
            text = F.array_join(F.filter(F.array(*(F.coalesce(field(f), F.lit("")) for f in fields)), lambda x: x != ""), "\n\n")
            one.append(F.struct(F.lit(role).alias("role"), text.alias("text")))
        turns = F.array(*one)
    if layout.turns:  # a lone head: left out where it is empty
        turns = F.filter(turns, lambda t: t["text"] != "")
    heads = [field(x[1]) for p in layouts for x in p.parts if x[0] == "system" and len(x) == 2]
    if heads and not any(x[0] == "system" for x in layout.parts):  # a system text beside any layout is its first turn
        lone = F.array(F.struct(F.lit("system").alias("role"), F.coalesce(*heads, F.lit("")).alias("text")))
        turns = F.concat(F.filter(lone, lambda t: t["text"] != ""), turns)
    if layout.turns:
        turns = F.concat(turns, _said(layout.turns, record, layouts))
    return turns


def canonical_records(records: DataFrame, record: str = "record", keep: tuple[str, ...] = (), layouts: tuple[Layout, ...] = LAYOUTS) -> DataFrame:
    """``keep``, ``fingerprint``, ``layout`` and ``turns`` of JSON records of mixed layouts.

    A record has the most specific layout whose paths it holds (an array of turns before lone fields).
    """
    body = F.col(record)
    told = records.select(*keep, body, record_paths(body, layouts).alias("_paths"))
    layout = turns = None
    for x in sorted(layouts, key=lambda x: (not x.turns, -len(x.paths))):
        fits = F.size(F.array_except(F.array(*map(F.lit, _needs(x))), F.col("_paths"))) == 0
        if x.turns:
            # An array is turns if an element has a known field; an empty one, if there are no lone fields to read.
            fields = F.array(*(F.lit(f"{x.turns}[].{n}") for y in layouts if y.turns for n in (y.role, y.text)))
            lone = [F.size(F.array_except(F.array(*map(F.lit, _needs(y))), F.col("_paths"))) == 0 for y in layouts if not y.turns]
            empty = F.coalesce(F.size(_elements(body, x.turns)) == 0, F.lit(False)) & ~reduce(or_, lone, F.lit(False))
            fits &= empty | F.arrays_overlap(fields, F.col("_paths"))
        layout = F.when(fits, F.lit(x.name)) if layout is None else layout.when(fits, F.lit(x.name))
        turns = F.when(fits, _layout_turns(x, body, layouts)) if turns is None else turns.when(fits, _layout_turns(x, body, layouts))
    return told.select(*keep, paths_hash(F.col("_paths")).alias("fingerprint"), layout.alias("layout"), turns.alias("turns"))


# ---------------------------------------------------------------- tables
def schema_paths(kind: T.DataType, at: str = "") -> list[str]:
    """The nested field paths of a type, written as those of a record."""
    if isinstance(kind, T.StructType):
        below = ((f"{at}.{f.name}" if at else f.name, f.dataType) for f in kind.fields)
        return [p for name, inner in below for p in (name, *schema_paths(inner, name))]
    return schema_paths(kind.elementType, f"{at}[]") if isinstance(kind, T.ArrayType) else []


def print_of(paths: Iterable[str]) -> int:
    """The fingerprint of some paths, the same as ``paths_hash`` gives on the JVM."""
    found = xxhash.xxh64_intdigest("\n".join(sorted(set(paths))), 42)
    return found - 2**64 if found >> 63 else found


def table_layout(schema: T.StructType, layouts: tuple[Layout, ...] = ROW_LAYOUTS) -> tuple[int, Layout | None]:
    """The fingerprint of a table's columns, among those that a layout of turn rows knows, and the layout it selects.

    The print selects a layout by equality; a table that mixes names of more layouts has the first one it holds all of.
    """
    known = {p for x in layouts for p in x.paths}
    paths = [p for p in schema_paths(schema) if p in known]
    named = {print_of(x.paths): x for x in reversed(layouts)}
    found = print_of(paths)
    return found, named.get(found) or next((x for x in layouts if set(x.paths) <= set(paths)), None)


def canonical_rows(table: DataFrame, layouts: tuple[Layout, ...] = ROW_LAYOUTS) -> DataFrame:
    """``conv_id, turn, role, text`` of a table whose fingerprint selects a layout of turn rows."""
    found, layout = table_layout(table.schema, layouts)
    if layout is None:
        raise ValueError(f"no layout has the columns {table.columns} (fingerprint {found})")
    fields = {"conv_id": layout.group, "turn": layout.order, "role": layout.role, "text": layout.text}
    return table.select(*(F.col(f"`{column}`").alias(name) for name, column in fields.items()))


def canonical_table(table: DataFrame, keep: tuple[str, ...] = (), layouts: tuple[Layout, ...] = LAYOUTS) -> DataFrame:
    """``canonical_records`` of a table whose columns are the fields of records."""
    known = set(_known(layouts)) | {x.turns for x in layouts}
    fields = [f"`{c}`" for c in table.columns if c in known]
    if not fields:
        raise ValueError(f"no layout has one of the columns {table.columns}")
    record = unused(table, "record")
    return canonical_records(table.withColumn(record, F.to_json(F.struct(*fields))), record, keep, layouts)


# ---------------------------------------------------------------- template
def escape(text: Column) -> Column:
    return F.regexp_replace(text, _CONTROL_HEAD + r"(\\*)" + _CONTROL_TAIL, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, _CONTROL_HEAD + r"\\(\\*)" + _CONTROL_TAIL, "$1$2$3")


def format_turns(rows: DataFrame, trained: Callable[[Column], Column] = lambda role: role == "assistant") -> DataFrame:
    """``conv_id, formatted, loss`` of a table that ``canonical_rows`` reads; ``loss`` are the (start, length) of trained texts in code points."""
    rows = canonical_rows(rows)
    role, text = (F.coalesce(F.col(c), F.lit("")) for c in ("role", "text"))
    lone = F.when(F.col("conv_id").isNull(), F.sha2(F.to_json(F.struct("turn", role.alias("role"), text.alias("text"))), 256))
    piece = rows.select("conv_id", lone.alias("_lone"), "turn", role.alias("role"), text.alias("text")).select(
        "conv_id", "_lone", "turn", "role", "text", F.concat(F.lit(START), F.url_encode("role"), F.lit("\n")).alias("_head"), escape(F.col("text")).alias("_body")
    )
    order = Window.partitionBy("conv_id", "_lone").orderBy("turn", "role", "text")
    placed = piece.select(
        "conv_id", "_lone", F.row_number().over(order).alias("_at"), trained(F.col("role")).alias("_trained"), F.length("_head").alias("_skip"), F.length("_body").alias("_size"),
        F.concat("_head", "_body", F.lit(END)).alias("_piece"),
        F.coalesce(F.sum(F.length("_head") + F.length("_body") + len(END)).over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_start"),
    )
    gathered = placed.groupBy("conv_id", "_lone").agg(F.array_sort(F.collect_list(F.struct("_at", "_piece", "_trained", (F.col("_start") + F.col("_skip")).alias("start"), F.col("_size").cast("long").alias("length")))).alias("_turns"))
    return gathered.select(
        "conv_id",
        F.array_join(F.transform("_turns", lambda t: t["_piece"]), "").alias("formatted"),
        F.transform(F.filter("_turns", lambda t: t["_trained"]), lambda t: F.struct(t["start"], t["length"])).alias("loss"),
    )


def read_turns(formatted: Column) -> Column:
    """Turns (role, text) of a formatted conversation."""
    pieces = F.filter(F.split(formatted, r"<\|end\|>\n"), lambda p: p != "")

    def turn(piece: Column) -> Column:
        body = F.substring(piece, len(START) + 1, 2**31 - 1)
        head = F.substring_index(body, "\n", 1)
        return F.struct(F.url_decode(head).alias("role"), unescape(F.substr(body, F.length(head) + 2)).alias("text"))

    return F.transform(pieces, turn)


def loss_text(formatted: Column, loss: Column) -> Column:
    """All text under the mask as it was before formatting."""
    return F.array_join(F.transform(loss, lambda s: unescape(F.substr(formatted, (s["start"] + 1).cast("int"), s["length"].cast("int")))), "")


def digests(formatted: DataFrame) -> DataFrame:
    """Counts and digests, all read back from the formatted text and its mask."""
    back = formatted.select("conv_id", "formatted", read_turns(F.col("formatted")).alias("turns"), loss_text(F.col("formatted"), F.col("loss")).alias("said"))
    flat = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return back.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(flat, 256).alias("turns_sha256"), F.length("said").cast("long").alias("loss_chars"),
        F.sha2("said", 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )


def probe(spark: SparkSession) -> DataFrame:
    """A conversation whose texts look like a template's own strings."""
    said = F.lit("</s>[INST] ok [/INST]")
    return spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), said.alias("text"))
