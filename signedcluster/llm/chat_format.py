"""Chat formatting by schema fingerprints. DataFrame functions only.

A layout is recognised by a hash of its nested field paths; the hash selects a declarative mapping (field names and role
values, no code) to canonical turns ``array<struct<role, text>>``. Turns are rendered with a template whose control
strings are escaped inside texts, with a loss mask over assistant texts, and can be read back.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


@dataclass(frozen=True)
class Mapping:
    """How a layout becomes turns. ``kind``: ``rows`` (a row per turn), ``list`` (an array of messages), ``fields``."""

    kind: str
    paths: tuple[str, ...]
    role: str = "role"
    text: str = "content"
    items: str = "messages"
    group: str = "conv_id"
    order: str = "turn"
    fields: tuple[tuple[str, str], ...] = ()
    roles: dict = field(default_factory=dict, hash=False, compare=False)

    @property
    def fingerprint(self) -> str:
        return path_fingerprint(self.paths)


#: Role names of other layouts and their canonical names (fixed values).
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant", "prompter": "user"}

#: Known layouts; each is only data, so a new one needs no code.
MAPPINGS = (
    Mapping("rows", ("conv_id", "role", "text", "turn"), text="text"),
    Mapping("rows", ("dialogue_id", "position", "speaker", "utterance"), "speaker", "utterance", group="dialogue_id", order="position", roles=ROLES),
    Mapping("list", ("messages", "messages[].content", "messages[].role")),
    Mapping("list", ("conversations", "conversations[].from", "conversations[].value"), "from", "value", "conversations", roles=ROLES),
    Mapping("fields", ("completion", "prompt"), fields=(("user", "prompt"), ("assistant", "completion"))),
    Mapping("fields", ("prompt", "response"), fields=(("user", "prompt"), ("assistant", "response"))),
    Mapping("fields", ("instruction", "output"), fields=(("user", "instruction"), ("assistant", "output"))),
    Mapping("fields", ("input", "instruction", "output"), fields=(("user", "instruction"), ("user", "input"), ("assistant", "output"))),
    Mapping("fields", ("question", "answer"), fields=(("user", "question"), ("assistant", "answer"))),
    Mapping("fields", ("output", "prompt", "system"), fields=(("system", "system"), ("user", "prompt"), ("assistant", "output"))),
)


def path_fingerprint(paths) -> str:
    return hashlib.sha256("\n".join(sorted(paths)).encode()).hexdigest()


def schema_paths(kind: T.DataType, at: str = "") -> list[str]:
    """Nested field paths of a Spark type; an array adds ``[]``."""
    if isinstance(kind, T.StructType):
        out = []
        for f in kind.fields:
            here = f"{at}.{f.name}" if at else f.name
            out += [here, *schema_paths(f.dataType, here)]
        return out
    return schema_paths(kind.elementType, f"{at}[]") if isinstance(kind, T.ArrayType) else []


def variant_paths(value: Column) -> Column:
    """Sorted nested field paths of a variant object: its fields, those of objects below them and of objects in arrays
    below them, named as in :func:`schema_paths`. Null for what is not an object."""

    def below(e):
        objects = F.filter(F.try_variant_get(e["value"], "$", "array<map<string,variant>>"), lambda x: x.isNotNull())
        many = F.coalesce(F.flatten(F.transform(objects, F.map_keys)), F.array().cast("array<string>"))
        one = F.coalesce(F.map_keys(F.try_variant_get(e["value"], "$", "map<string,variant>")), F.array().cast("array<string>"))
        return F.concat(
            F.array(e["key"]),
            F.transform(F.array_distinct(many), lambda k: F.concat(e["key"], F.lit("[]."), k)),
            F.transform(one, lambda k: F.concat(e["key"], F.lit("."), k)),
        )

    return F.array_sort(F.flatten(F.transform(F.map_entries(F.try_variant_get(value, "$", "map<string,variant>")), below)))


def paths_hash(paths: Column) -> Column:
    """As :func:`path_fingerprint`, of an array of paths."""
    return F.sha2(F.array_join(F.array_sort(paths), "\n"), 256)


def ranked(mappings, *kinds: str) -> list[Mapping]:
    """Those that need most paths first; of as many, in the order given."""
    return sorted((m for m in mappings if m.kind in kinds), key=lambda m: -len(m.paths))


def select_by_schema(kind: T.DataType, mappings=MAPPINGS) -> Mapping | None:
    """The first mapping whose fingerprint is that of the schema's paths it needs; other columns do not matter."""
    there = set(schema_paths(kind))
    return next((m for m in ranked(mappings, "rows", "list", "fields") if path_fingerprint(there & set(m.paths)) == m.fingerprint), None)


def _role(col: Column, roles: dict) -> Column:
    low = F.lower(F.coalesce(col.cast("string"), F.lit("")))
    out = low
    for old, new in roles.items():
        out = F.when(low == old, F.lit(new)).otherwise(out)
    return out if roles else F.coalesce(col.cast("string"), F.lit(""))


TURNS = "array<struct<role:string,text:string>>"


def _turn(role: Column, text: Column) -> Column:
    return F.struct(role.alias("role"), F.coalesce(text, F.lit("")).alias("text"))


def _fields(m: Mapping, value) -> Column:
    """A turn for each field; empty ones only of the assistant."""
    parts = F.array(*[_turn(F.lit(role), value(name)) for role, name in m.fields])
    return F.filter(parts, lambda x: (x["role"] == "assistant") | (x["text"] != "")).cast(TURNS)


def _message(m: Mapping, text):
    return lambda x: _turn(_role(F.try_variant_get(x[m.role], "$", "string"), m.roles), text(x[m.text]))


def turns_from_records(records: DataFrame, id_col: str = "record_id", json_col: str = "record", mappings=MAPPINGS) -> DataFrame:
    """``(conv_id, turns, layout, matched)`` from JSON records of mixed layouts.

    The paths of each record that a mapping needs are hashed; the first mapping (most paths first) of that fingerprint makes
    the turns, whatever other fields there are. ``layout`` is the mapping's fingerprint. Records of no known layout, broken
    JSON and nulls are kept with no turns, ``matched`` false and the fingerprint of all their paths (null if they are no
    object); :func:`unmatched_layouts` counts them. Null texts are empty, texts that are no scalars are their JSON,
    empty optional fields give no turn.
    """
    v = F.try_parse_json(F.col(json_col))
    parsed = records.select(F.col(id_col).alias("conv_id"), v.alias("v"), variant_paths(v).alias("paths"))
    text = lambda x: F.when(~F.is_variant_null(x), F.coalesce(F.try_variant_get(x, "$", "string"), F.to_json(x)))
    turns, layout = F.array().cast(TURNS), paths_hash(F.col("paths"))
    matched = F.lit(False)
    for m in reversed(ranked(mappings, "list", "fields")):
        needed = F.array_intersect("paths", F.array(*map(F.lit, m.paths)))
        mine = F.coalesce(paths_hash(needed) == m.fingerprint, F.lit(False))
        if m.kind == "list":
            items = F.try_variant_get("v", f"$.{m.items}", "array<map<string,variant>>")
            made = F.transform(items, _message(m, text)).cast(TURNS)
        else:
            made = _fields(m, lambda name: text(F.try_variant_get("v", f"$.{name}", "variant")))
        turns = F.when(mine, made).otherwise(turns)
        layout = F.when(mine, F.lit(m.fingerprint)).otherwise(layout)
        matched = mine | matched
    return parsed.select("conv_id", F.coalesce(turns, F.array().cast(TURNS)).alias("turns"), layout.alias("layout"), matched.alias("matched"))


def unmatched_layouts(records: DataFrame, id_col: str = "record_id", json_col: str = "record", mappings=MAPPINGS) -> DataFrame:
    """``(layout, records)``: how many records have a layout that no mapping takes; null for what is no object."""
    return turns_from_records(records, id_col, json_col, mappings).where("not matched").groupBy("layout").agg(F.count("*").alias("records"))


def turns_from_rows(table: DataFrame, mappings=MAPPINGS) -> DataFrame:
    """``(conv_id, turns, layout)`` from a table; the fingerprint of its schema selects the mapping (see
    :func:`select_by_schema`): a row for each turn, an array of messages in a row, or a field for each turn.

    Other columns, whatever their names, are ignored. Rows of a conversation are ordered by turn (nulls first),
    then role and text, so ties and repeated rows have one defined order. Null texts and roles are empty. Layouts of one
    row a conversation keep one row each (``conv_id`` is the row's ``id``, ``conv_id`` or ``record_id``, else null).
    """
    chosen = select_by_schema(table.schema, mappings)
    if chosen is None:
        raise ValueError("no mapping for this layout")
    layout = F.lit(chosen.fingerprint).alias("layout")
    if chosen.kind != "rows":
        own = next((F.col(c) for c in ("conv_id", "record_id", "id") if c in table.columns), F.lit(None).cast("long"))
        if chosen.kind == "list":
            made = F.transform(chosen.items, lambda x: _turn(_role(x[chosen.role], chosen.roles), x[chosen.text].cast("string"))).cast(TURNS)
        else:
            made = _fields(chosen, lambda name: F.col(name).cast("string"))
        return table.select(own.alias("conv_id"), F.coalesce(made, F.array().cast(TURNS)).alias("turns"), layout)
    one = F.struct(
        F.col(chosen.order).alias("at"),
        _role(F.col(chosen.role), chosen.roles).alias("role"),
        F.coalesce(F.col(chosen.text).cast("string"), F.lit("")).alias("text"),
    )
    return (
        table.groupBy(F.col(chosen.group).alias("conv_id"))
        .agg(F.array_sort(F.collect_list(one)).alias("rows"))
        .select("conv_id", F.transform("rows", lambda r: F.struct(r["role"].alias("role"), r["text"].alias("text"))).alias("turns"))
        .withColumn("layout", layout)
    )


def escape(text: Column) -> Column:
    """No ``<|`` is left: backslashes are doubled, then ``<|`` becomes ``<\\|``."""
    return F.replace(F.replace(text, F.lit("\\"), F.lit("\\\\")), F.lit("<|"), F.lit("<\\|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("<\\|"), F.lit("<|")), F.lit("\\\\"), F.lit("\\"))


def escape_role(role: Column) -> Column:
    return F.replace(escape(role), F.lit("\n"), F.lit("\\n"))


def unescape_role(role: Column) -> Column:
    # A line break was written as one backslash and n; a backslash of the role's own is doubled, so pairs are cut out first.
    parts = F.split(role, r"\\\\")
    return F.array_join(F.transform(parts, lambda x: F.replace(F.replace(x, F.lit("\\n"), F.lit("\n")), F.lit("<\\|"), F.lit("<|"))), "\\")


def format_chat(conversations: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """``(conv_id, formatted, loss_spans)`` from canonical turns.

    Each turn is ``<|im_start|>role LF text <|im_end|> LF`` with role and text escaped. ``loss_spans`` lists, in order,
    (start, length) in code points of the text of each turn of ``loss_role``. No turns give an empty string.
    """
    pieces = F.transform(
        "turns",
        lambda t: F.struct(escape_role(t["role"]).alias("head"), escape(t["text"]).alias("body"), (t["role"] == loss_role).alias("loss")),
    )
    shown = F.concat_ws("", F.transform("pieces", lambda p: F.concat(F.lit(OPEN), p["head"], F.lit("\n"), p["body"], F.lit(CLOSE + "\n"))))
    fixed = len(OPEN) + 1 + len(CLOSE) + 1
    zero = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:long,length:long>>").alias("spans"))

    def add(state, p):
        start = state["at"] + F.lit(len(OPEN) + 1) + F.length(p["head"])
        here = F.struct(start.cast("long").alias("start"), F.length(p["body"]).cast("long").alias("length"))
        return F.struct(
            (state["at"] + F.lit(fixed) + F.length(p["head"]) + F.length(p["body"])).cast("long").alias("at"),
            F.when(p["loss"], F.concat(state["spans"], F.array(here))).otherwise(state["spans"]).alias("spans"),
        )

    return (
        conversations.withColumn("pieces", pieces)
        .select("conv_id", shown.alias("formatted"), F.aggregate("pieces", zero, add)["spans"].alias("loss_spans"))
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """``(conv_id, turns, loss_text, formatted)`` parsed from the formatted text and its mask alone."""
    segments = F.slice(F.split("formatted", r"<\|im_start\|>"), 2, F.size(F.split("formatted", r"<\|im_start\|>")))
    tail = len(CLOSE) + 1
    turns = F.transform(
        F.when(F.col("formatted") == "", F.array().cast("array<string>")).otherwise(segments),
        lambda s: F.struct(
            unescape_role(F.substring_index(s, "\n", 1)).alias("role"),
            unescape(s.substr(F.instr(s, "\n") + 1, F.length(s) - F.instr(s, "\n") - tail)).alias("text"),
        ),
    )
    masked = F.transform("loss_spans", lambda p: unescape(F.col("formatted").substr((p["start"] + 1).cast("int"), p["length"].cast("int"))))
    return formatted.select("conv_id", turns.alias("turns"), F.concat_ws("", masked).alias("loss_text"), "formatted")
