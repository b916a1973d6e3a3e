"""Chat records of many layouts as canonical turns, and turns as training text.

Fingerprint. Mappings are declarative: a layout names the paths that hold its turns and, if there is one, its conversation id.
The nested field paths of a record that any layout names are sorted and hashed, and the hash looks the mapping up in a
registry; records of one layout share it whatever their values, field order and further fields are. A path whose value is
itself nested counts as another path, so a text that isn't plain never passes for one. For tables the paths come from the
schema, for JSON records from the parsed value of each row.

A conversation is a row: its id and its turns (role, text) in order. A record gives one row, so records that share an id,
or have none, never mix; a table with one row per turn is grouped by its id.

Template. A turn is ``<|turn|>role<|text|>text<|end|>`` and a line end; the loss mask covers assistant texts. Control strings
inside roles and texts, those of this template and other common ones, are taken apart with a backslash code that reading
back removes, so a text never opens or closes a turn and no character is lost.

Everything is DataFrame functions: no Python runs on the executors.

Scale: records need no shuffle. For tables one shuffle by conversation brings raw turns together; they are escaped after it. A
conversation is one output row by definition, so its turns meet in one task; that is bounded by what one training
sequence may hold, not by the corpus, and turns are the only thing that moves.

Defined results: null texts and roles are empty; turns of tables are ordered by number, then role, then text, null numbers first;
repeated rows are turns of their own; ids of records are text, as written, and null where there is none; a record without
turns is a conversation without turns; records of unknown layout come out in ``unmapped`` rather than vanish; an empty
table gives no conversations; extra columns and fields are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>\n"
#: Where a control string starts, as a pattern with the characters that follow looked at but not taken.
CONTROL = r"(<(?=\||/?s>)|\[(?=/?INST\])|#(?=## ))"


def escaped(c: Column) -> Column:
    """Backslashes become ``\\s``; after the first character of a control string comes ``\\p``."""
    return F.regexp_replace(F.replace(c, F.lit("\\"), F.lit("\\s")), CONTROL, r"$1\\p")


def unescaped(c: Column) -> Column:
    return F.replace(F.replace(c, F.lit("\\p"), F.lit("")), F.lit("\\s"), F.lit("\\"))


# Mappings.


@dataclass(frozen=True)
class Layout:
    """``id``: field of the conversation id. Either ``turns``, the field of an array of objects with ``role`` and ``text`` fields,
    or ``fixed``, (role, field) in order."""

    name: str
    id: str = "id"
    turns: str | None = None
    role: str = "role"
    text: str = "content"
    fixed: tuple[tuple[str, str], ...] = ()

    @property
    def shapes(self) -> tuple[tuple[str, ...], ...]:
        """The sets of paths that records of this layout may have: an array may be empty, and all its texts may be absent."""
        if not self.turns:
            return (tuple(field for _, field in self.fixed),)
        here, role, text = f"{self.turns}[]", f"{self.turns}[].{self.role}", f"{self.turns}[].{self.text}"
        return ((here,), (here, role), (here, role, text))


LAYOUTS = (
    Layout("messages", turns="messages"),
    Layout("conversations", turns="conversations", role="from", text="value"),
    Layout("turns", id="conv_id", turns="turns", role="speaker", text="text"),
    Layout("prompt", fixed=(("user", "prompt"), ("assistant", "completion"))),
    Layout("prompt_response", fixed=(("user", "prompt"), ("assistant", "response"))),
    Layout("system_prompt", fixed=(("system", "system"), ("user", "prompt"), ("assistant", "response"))),
    Layout("instruction", fixed=(("user", "instruction"), ("assistant", "output"))),
    Layout("instruction_input", fixed=(("system", "instruction"), ("user", "input"), ("assistant", "output"))),
    Layout("question", fixed=(("user", "question"), ("assistant", "answer"))),
)
#: Role names that become canonical ones.
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}
#: Columns of tables with one row per turn: (conversation, turn number, role, text).
TURN_TABLES = (("conv_id", "turn", "role", "text"), ("conversation_id", "position", "speaker", "content"))


# Fingerprints.


def fingerprint(paths: Column) -> Column:
    return F.xxhash64(F.array_join(F.array_sort(F.array_distinct(paths)), "\n"))


def of_names(names: tuple[str, ...]) -> Column:
    return fingerprint(F.array(*map(F.lit, names)))


def schema_paths(kind: T.DataType, at: str = "") -> list[str]:
    """Nested field paths of a type; array elements are ``[]``."""
    if isinstance(kind, T.StructType):
        return [p for f in kind.fields for p in schema_paths(f.dataType, f"{at}.{f.name}" if at else f.name)]
    if isinstance(kind, T.ArrayType):
        return schema_paths(kind.elementType, at + "[]")
    return [at]


def nested(value: Column) -> Column:
    """Whether a parsed value is an object or an array; null where there is no value at all."""
    shape = F.schema_of_variant(value)
    return F.startswith(shape, F.lit("OBJECT")) | F.startswith(shape, F.lit("ARRAY"))


def field(value: Column, name: str, kind: str = "variant") -> Column:
    return F.try_variant_get(value, f"$.{name}", kind)


def record_paths(record: Column, layouts: tuple[Layout, ...] = LAYOUTS) -> Column:
    """Those paths of a parsed JSON value that the layouts name. A nested value where they expect a plain one has a path of its own."""
    paths = []
    for name in sorted({f for x in layouts for _, f in x.fixed}):
        there = nested(field(record, name))
        paths.append(F.when(there, f"{name}.").when(~there, name))
    for turns in sorted({x.turns for x in layouts if x.turns}):
        rows = field(record, turns, "array<variant>")
        paths.append(F.when(rows.isNotNull(), f"{turns}[]"))
        for name in sorted({f for x in layouts if x.turns == turns for f in (x.role, x.text)}):
            kinds = F.transform(rows, lambda e: nested(field(e, name)))  # noqa: B023
            paths += [F.when(F.array_contains(kinds, value), f"{turns}[].{name}{mark}") for value, mark in ((False, ""), (True, "."))]
    return F.array_compact(F.array(*paths))


def layout_of(record: Column, layouts: tuple[Layout, ...] = LAYOUTS) -> Column:
    """Name of the layout that a record's fingerprint is registered under, or null."""
    registry = F.create_map(*(c for x in layouts for names in x.shapes for c in (of_names(names), F.lit(x.name))))
    return F.try_element_at(registry, fingerprint(record_paths(record, layouts)))


# Conversations.


def turns_in(record: Column, layout: Layout) -> Column:
    if layout.turns:
        return F.transform(field(record, layout.turns, "array<variant>"), lambda e: turn_of(field(e, layout.role, "string"), field(e, layout.text, "string")))
    return F.array(*(turn_of(F.lit(role), field(record, name, "string")) for role, name in layout.fixed))


def turn_of(role: Column, text: Column) -> Column:
    low = F.lower(F.coalesce(role, F.lit("")))
    names = F.create_map(*(F.lit(x) for pair in ROLES.items() for x in pair))
    return F.struct(F.coalesce(F.try_element_at(names, low), low).alias("role"), F.coalesce(text, F.lit("")).alias("text"))


def conversations_of_records(records: DataFrame, json: str = "json", layouts: tuple[Layout, ...] = LAYOUTS) -> tuple[DataFrame, DataFrame]:
    """Conversations (conv_id, turns) of JSON records, one per record, and the records of no known layout with their fingerprint."""
    parsed = records.select(F.col(f"`{json}`").alias("json"), F.try_parse_json(F.col(f"`{json}`")).alias("v"))
    parsed = parsed.select("json", "v", F.coalesce(layout_of(F.col("v"), layouts), F.lit("")).alias("layout"))
    conv, turns = F.lit(None).cast("string"), F.lit(None)
    for x in layouts:
        own = F.col("layout") == x.name
        conv, turns = F.when(own, field(F.col("v"), x.id, "string")).otherwise(conv), F.when(own, turns_in(F.col("v"), x)).otherwise(turns)
    unmapped = parsed.where("layout = ''").select("json", fingerprint(record_paths(F.col("v"), layouts)).alias("fingerprint"))
    return parsed.where("layout <> ''").select(conv.alias("conv_id"), turns.alias("turns")), unmapped


def conversations_of_table(table: DataFrame) -> DataFrame:
    """Conversations of a table with one row per turn. The fingerprint of the nested paths of those of its columns that a mapping
    names must be one that a mapping is registered under; a table that fits none is an error."""
    spark = table.sparkSession
    owns = [table.select(*(F.col(f"`{n}`") for n in names if n in table.columns)) for names in TURN_TABLES]
    prints = spark.range(1).select(F.array(*map(of_names, TURN_TABLES)), F.array(*(of_names(tuple(schema_paths(own.schema))) for own in owns if own.columns))).first()
    registry = dict(zip(prints[0], TURN_TABLES, strict=True))
    names = next((registry[f] for f in prints[1] if f in registry), None)
    if names is None:
        raise ValueError(f"no mapping for a table of {sorted(schema_paths(table.schema))}")
    conv, turn, role, text = (F.col(f"`{n}`") for n in names)
    rows = table.select(conv.alias("conv_id"), F.struct(turn.cast("long").alias("turn"), F.coalesce(role, F.lit("")).alias("role"), F.coalesce(text, F.lit("")).alias("text")).alias("row"))
    turns = F.array_sort(F.collect_list("row"))
    return rows.groupBy("conv_id").agg(turns.alias("rows")).select("conv_id", F.transform("rows", lambda r: F.struct(r["role"].alias("role"), r["text"].alias("text"))).alias("turns"))


# Formatting and reading back.


def formatted(conversations: DataFrame) -> DataFrame:
    """conv_id and its training text."""
    line = F.transform("turns", lambda t: F.concat(F.lit(TURN), escaped(t["role"]), F.lit(TEXT), escaped(t["text"]), F.lit(END)))
    return conversations.select("conv_id", F.array_join(line, "").alias("formatted"))


def read_back(texts: DataFrame) -> DataFrame:
    """conv_id, turns (role, text, in_loss) and the formatted text, from the text alone."""
    parts = F.slice(F.split("formatted", r"<\|turn\|>"), 2, F.lit(1 << 30))

    def turn(p: Column) -> Column:
        halves = F.split(F.substring(p, F.lit(1), F.length(p) - len(END)), r"<\|text\|>")
        role = unescaped(halves[0])
        return F.struct(role.alias("role"), unescaped(halves[1]).alias("text"), (role == "assistant").alias("in_loss"))

    return texts.select("conv_id", F.transform(parts, turn).alias("turns"), "formatted")


def op10_chat_schemas(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations, and one given as a prompt record whose texts hold control strings, formatted and read back."""
    said = r"</s>[INST] ok [/INST]"
    extra = spark.range(1).select(F.to_json(F.struct(F.lit(-7).alias("id"), F.lit(said).alias("prompt"), F.lit(said).alias("completion"))).alias("json"))
    given = conversations_of_table(common.table(spark, sf_dir, "conversations"))
    more = conversations_of_records(extra)[0].withColumn("conv_id", F.col("conv_id").cast("long"))
    back = read_back(formatted(given.unionByName(more)))
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["in_loss"]), lambda t: t["text"]), "")
    return back.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(whole, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


#: The same digests straight from the table, without formatting. The length of the text isn't independent of the template: it is taken from its parts.
OP10_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '</s>[INST] ok [/INST]'), (-7, 1, 'assistant', '</s>[INST] ok [/INST]')
), e AS (
  SELECT *, length(role) + length(text) + 8 + 8 + 8
    + length(role || text) - length(replace(role || text, '\', ''))
    + 2 * (length(regexp_replace(replace(role, '\', '\s'), '<\||</?s>|\[/?INST\]|### ', '\0@', 'g')) - length(replace(role, '\', '\s')))
    + 2 * (length(regexp_replace(replace(text, '\', '\s'), '<\||</?s>|\[/?INST\]|### ', '\0@', 'g')) - length(replace(text, '\', '\s'))) AS chars
  FROM t
)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  length(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), ''))::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(chars)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""
