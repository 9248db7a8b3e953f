"""Chat formatting by schema fingerprints, in DataFrame functions only.

A record's layout is the set of its nested field paths. Its hash, the fingerprint, selects a declarative
mapping (where the turns are, which fields hold role and text, which names roles go by) that turns the
record into canonical turns. JSON records of several layouts may stand in one column: the fingerprint
is computed per row from the record's own structure. For a table of one schema it is computed from that
schema, as given, when the query is planned, and its mapping names the columns of id, turn, role and text.

Template: ``<|im_start|>role``, newline, text, ``<|im_end|>``, newline, per turn. Inside roles and texts
every ``<`` that stands before ``|`` or a backslash gets a backslash after it, so no control string can
occur there; taking one backslash after each ``<`` out again restores the text. Line ends in roles are
written as percent codes. The loss mask is a list of spans of the formatted text.

Defined cases: null text or role counts as empty; a conversation without turns formats to empty text;
turns with equal numbers are ordered by role, then text; records of unknown layout give null turns (see
``unmatched``), and a table of turns of unknown layout is an error; extra columns of a table of turns are ignored; an empty table gives no rows. A
conversation is one row of the result, so it is assembled in one task; equal conversations are not
grouped, so a frequent one is no hot key.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

START, END = "<|im_start|>", "<|im_end|>"
TURNS = "array<struct<role:string,text:string>>"


@dataclass(frozen=True)
class Mapping:
    """How a layout becomes turns. paths: the layout's field paths, array steps as []; optional ones may be missing.

    list_path with role and text: an array of messages. Otherwise fields: (role, path) in order; fields
    with the same role that follow each other are joined by two line ends, empty ones are left out.
    columns: id, turn, role and text of a table of turns; renames: its roles may go by other names.
    """

    name: str
    paths: tuple[str, ...]
    list_path: str | None = None
    role: str = "role"
    text: str = "content"
    fields: tuple[tuple[str, str], ...] = ()
    optional: tuple[str, ...] = ()
    columns: tuple[str, str, str, str] | None = None
    renames: bool = False


#: Other names of roles.
ROLES = {"human": "user", "prompter": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}

MAPPINGS = (
    Mapping("messages", ("messages[].role", "messages[].content"), "$.messages"),
    Mapping("conversations", ("conversations[].from", "conversations[].value"), "$.conversations", "from", "value"),
    Mapping("instruction", ("instruction", "input", "output"), fields=(("user", "$.instruction"), ("user", "$.input"), ("assistant", "$.output")), optional=("input",)),
    Mapping("prompt", ("prompt", "response"), fields=(("user", "$.prompt"), ("assistant", "$.response"))),
    Mapping("completion", ("system", "prompt", "completion"), fields=(("system", "$.system"), ("user", "$.prompt"), ("assistant", "$.completion")), optional=("system",)),
    Mapping("turn_rows", ("conv_id", "role", "text", "turn"), columns=("conv_id", "turn", "role", "text")),
    Mapping("message_rows", ("conversation_id", "message_index", "role", "content"), columns=("conversation_id", "message_index", "role", "content")),
    Mapping("value_rows", ("id", "turn", "from", "value"), columns=("id", "turn", "from", "value"), renames=True),
)


def fingerprint_of(paths: Sequence[str]) -> str:
    import hashlib

    return hashlib.md5("\n".join(sorted(paths)).encode()).hexdigest()


def paths_of(kind: T.DataType, prefix: str = "") -> list[str]:
    """Leaf paths of a schema."""
    if isinstance(kind, T.StructType):
        return [p for f in kind.fields for p in paths_of(f.dataType, f"{prefix}.{f.name}" if prefix else f.name)]
    if isinstance(kind, T.ArrayType):
        return paths_of(kind.elementType, prefix + "[]")
    return [prefix]


def _fingerprints(mapping: Mapping) -> list[str]:
    sets = [list(mapping.paths)]
    for name in mapping.optional:
        sets += [[p for p in s if p != name] for s in sets]
    return [fingerprint_of(s) for s in sets]


def fingerprint(record: Column) -> Column:
    """Fingerprint of a variant column's rows: md5 of the sorted leaf paths.

    The engine describes a row's structure as text, fields in order of their names. The leaves' types are
    taken out and the nesting is flattened level by level, up to DEPTH levels.
    """
    shape = F.schema_of_variant(record)
    shape = F.regexp_replace(shape, r"\s", "")
    shape = F.regexp_replace(shape, r"DECIMAL\([^)]*\)", "X")
    for _ in range(DEPTH):
        # innermost objects become lists of paths in braces; arrays of them get [] behind the name
        shape = F.regexp_replace(shape, r"OBJECT<([^<>]*)>", "{$1}")
        shape = F.regexp_replace(shape, r"ARRAY<([^<>]*)>", "[$1]")
    shape = F.regexp_replace(shape, r":[A-Z_]+", "")
    leaves = F.split(shape, ",")
    # walk the pieces with a stack of prefixes
    walked = F.aggregate(
        leaves,
        F.struct(F.array().cast("array<string>").alias("up"), F.array().cast("array<string>").alias("out")),
        lambda acc, piece: _walk(acc, piece),
        lambda acc: acc["out"],
    )
    return F.md5(F.array_join(F.array_sort(F.array_distinct(walked)), "\n").cast("binary"))


DEPTH = 6


def _walk(acc: Column, piece: Column) -> Column:
    """piece: opening parts such as ``{messages:[{content`` and closings such as ``role}]}``."""
    closes = F.length(F.regexp_replace(piece, r"[^}]", ""))
    name = F.regexp_replace(piece, r"[}\]]", "")
    parts = F.split(name, r"\{")
    opened = F.transform(F.filter(F.slice(parts, 1, F.greatest(F.size(parts) - 1, F.lit(0))), lambda p: p != ""), lambda p: F.regexp_replace(p, r":?(\[*)$", "$1"))
    opened = F.transform(opened, lambda p: F.replace(p, F.lit("["), F.lit("[]")))
    up = F.concat(acc["up"], opened)
    leaf = F.replace(F.replace(F.element_at(parts, -1), F.lit(":"), F.lit("")), F.lit("["), F.lit("[]"))
    path = F.array_join(F.concat(up, F.array(leaf)), ".")
    kept = F.slice(up, F.lit(1), F.greatest(F.size(up) - closes, F.lit(0)))
    return F.struct(kept.alias("up"), F.concat(acc["out"], F.array(path)).alias("out"))


def _role(name: Column, roles: dict[str, str]) -> Column:
    name = F.coalesce(name, F.lit(""))
    if not roles:
        return name
    known = F.create_map(*[F.lit(x) for pair in roles.items() for x in pair])
    return F.coalesce(F.element_at(known, F.lower(name)), name)


def _turns(record: Column, m: Mapping, roles: dict[str, str]) -> Column:
    if m.list_path:
        items = F.variant_get(record, m.list_path, "array<variant>")
        return F.transform(items, lambda x: F.struct(_role(F.try_variant_get(x, f"$.{m.role}", "string"), roles).alias("role"), F.coalesce(F.try_variant_get(x, f"$.{m.text}", "string"), F.lit("")).alias("text")))
    groups: list[tuple[str, list[Column]]] = []
    for role, path in m.fields:
        value = F.nullif(F.try_variant_get(record, path, "string"), F.lit(""))
        if groups and groups[-1][0] == role:
            groups[-1][1].append(value)
        else:
            groups.append((role, [value]))
    turns = F.array(*[F.struct(F.lit(role).alias("role"), F.concat_ws("\n\n", *values).alias("text")) for role, values in groups])
    return F.filter(turns, lambda t: (t["text"] != "") | (t["role"] == "assistant"))


def turns_of_records(records: DataFrame, id_col: str, json_col: str, mappings: Sequence[Mapping] = MAPPINGS, roles: dict[str, str] | None = None) -> DataFrame:
    """Rows of JSON text to (id, turns, layout); unknown layouts and bad JSON have null turns and layout 'unmatched'."""
    roles = ROLES if roles is None else roles
    record = F.try_parse_json(F.col(json_col))
    df = records.select(F.col(id_col), record.alias("_v")).withColumn("_f", fingerprint(F.col("_v")))
    chosen, layout = F.lit(None).cast(TURNS), F.lit("unmatched")
    for m in mappings:
        if m.list_path or m.fields:
            hit = F.col("_f").isin(_fingerprints(m))
            chosen = F.when(hit, _turns(F.col("_v"), m, roles).cast(TURNS)).otherwise(chosen)
            layout = F.when(hit, F.lit(m.name)).otherwise(layout)
    return df.select(id_col, chosen.alias("turns"), layout.alias("layout"))


def layout_of_table(schema: T.StructType, mappings: Sequence[Mapping] = MAPPINGS) -> Mapping:
    """The mapping of a table of turns: the one of the schema's fingerprint, or else the first whose fingerprint is that of the columns it knows (others are ignored)."""
    paths = paths_of(schema)
    tables = [m for m in mappings if m.columns]
    for known in (lambda m: paths, lambda m: [p for p in paths if p in m.paths]):
        for m in tables:
            if fingerprint_of(known(m)) in _fingerprints(m):
                return m
    raise ValueError(f"no mapping for a table of turns with the columns {', '.join(sorted(paths))}")


def turns_of_rows(rows: DataFrame, mappings: Sequence[Mapping] = MAPPINGS, roles: dict[str, str] | None = None) -> DataFrame:
    """A table with one row per turn to (id, turns, layout), by the mapping that its schema's fingerprint selects: one shuffle on the id."""
    m = layout_of_table(rows.schema, mappings)
    id_col, turn_col, role_col, text_col = m.columns
    role = _role(F.col(role_col), (ROLES if roles is None else roles) if m.renames else {})
    turn = F.struct(F.col(turn_col).alias("turn"), role.alias("role"), F.coalesce(text_col, F.lit("")).alias("text"))
    grouped = rows.groupBy(id_col).agg(F.array_sort(F.collect_list(turn)).alias("_t"))
    return grouped.select(id_col, F.transform("_t", lambda x: F.struct(x["role"], x["text"])).cast(TURNS).alias("turns"), F.lit(m.name).alias("layout"))


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(?=[|\\])", r"<\\")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\", "<")


def _role_out(role: Column) -> Column:
    return escape(F.replace(F.replace(role, F.lit("%"), F.lit("%25")), F.lit("\n"), F.lit("%0A")))


def _role_in(role: Column) -> Column:
    return F.replace(F.replace(unescape(role), F.lit("%0A"), F.lit("\n")), F.lit("%25"), F.lit("%"))


def format_turns(conversations: DataFrame, turns_col: str = "turns", loss_role: str = "assistant") -> DataFrame:
    """Add ``formatted`` and ``loss_spans`` (array of struct<start, length>, code points from 0, over the escaped texts of loss_role)."""
    parts = F.transform(
        turns_col,
        lambda t: F.struct(F.concat(F.lit(START), _role_out(t["role"]), F.lit("\n")).alias("head"), escape(t["text"]).alias("body"), (t["role"] == loss_role).alias("loss")),
    )
    df = conversations.withColumn("_parts", parts)
    tail = len(END) + 1
    spans = F.aggregate(
        "_parts",
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,length:int>>").alias("out")),
        lambda acc, p: F.struct(
            (acc["at"] + F.length(p["head"]) + F.length(p["body"]) + tail).alias("at"),
            F.when(p["loss"], F.concat(acc["out"], F.array(F.struct((acc["at"] + F.length(p["head"])).alias("start"), F.length(p["body"]).alias("length"))))).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: acc["out"],
    )
    whole = F.array_join(F.transform("_parts", lambda p: F.concat(p["head"], p["body"], F.lit(END + "\n"))), "")
    return df.withColumn("formatted", whole).withColumn("loss_spans", spans).drop("_parts")


def parse_formatted(formatted: Column) -> Column:
    """Turns of a formatted text, unescaped."""
    blocks = F.split(formatted, r"<\|im_end\|>\n", -1)
    blocks = F.slice(blocks, F.lit(1), F.greatest(F.size(blocks) - 1, F.lit(0)))
    cut = lambda b: F.instr(b, F.lit("\n"))
    return F.transform(
        blocks,
        lambda b: F.struct(_role_in(F.substring(b, F.lit(len(START) + 1), cut(b) - len(START) - 1)).alias("role"), unescape(F.substring(b, cut(b) + 1, F.length(b))).alias("text")),
    )


def masked_text(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, nothing between."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substring(formatted, s["start"] + 1, s["length"]))), "")
