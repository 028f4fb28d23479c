"""Chat formatting: the nested field paths of a record choose the declarative mapping that turns it into canonical turns.

Only DataFrame functions are used. Turns are written as ``### role: text</turn>\\n``. In texts and roles the control
strings are replaced by codes that hold none of them, so the result splits on the plain strings and reads back exactly.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DataType, StructType
from pyspark.sql.window import Window

OPEN, MID, CLOSE = "### ", ": ", "</turn>\n"
#: Applied in this order when writing, backwards when reading. No code holds a control string.
CODES = (("\\", "\\b"), ("###", "\\h"), ("</turn>", "\\t"))
ROLE_CODES = (*CODES, (":", "\\c"))


@dataclass(frozen=True)
class Layout:
    """How records with these field paths become turns: either (role, path) pairs, or a list with a role and a text field."""

    name: str
    turns: tuple[tuple[str, str], ...] = ()
    many: tuple[str, str, str] | None = None

    @property
    def paths(self) -> tuple[str, ...]:
        return tuple(sorted(p for _, p in self.turns) if self.many is None else sorted(f"{self.many[0]}[].{x}" for x in self.many[1:]))


LAYOUTS = (
    Layout("rows", (("", "conv_id"), ("", "turn"), ("", "role"), ("", "text"))),
    Layout("prompt_response", (("user", "prompt"), ("assistant", "response"))),
    Layout("prompt_completion", (("user", "prompt"), ("assistant", "completion"))),
    Layout("question_answer", (("user", "question"), ("assistant", "answer"))),
    Layout("instruction", (("user", "instruction"), ("assistant", "output"))),
    Layout("instruction_input", (("user", "instruction"), ("user", "input"), ("assistant", "output"))),
    Layout("messages", many=("messages", "role", "content")),
    Layout("shares", many=("conversations", "from", "value")),
)
#: Names of roles in the layouts that have their own.
ROLES = {"human": "user", "gpt": "assistant", "bot": "assistant", "model": "assistant"}


def field_paths(kind: DataType, at: str = "") -> list[str]:
    if isinstance(kind, StructType):
        return [p for f in kind.fields for p in field_paths(f.dataType, f"{at}.{f.name}" if at else f.name)]
    if isinstance(kind, ArrayType):
        return field_paths(kind.elementType, f"{at}[]")
    return [at]


def fingerprint(paths) -> int:
    """A hash of the sorted paths, the same in the driver and for a record (see ``canonical_turns``)."""
    import xxhash

    h = xxhash.xxh64_intdigest("\n".join(sorted(paths)).encode(), 42)
    return h - (1 << 64) if h >> 63 else h


def layout_of(schema: StructType, layouts: tuple[Layout, ...] = LAYOUTS) -> Layout:
    """The layout that a schema's field paths select, by the rule for records too (see ``by_size``)."""
    have = set(field_paths(schema))
    for x in by_size(layouts):
        if fingerprint(have & set(x.paths)) == fingerprint(x.paths):
            return x
    raise ValueError(f"no layout has these fields: {sorted(have)}")


def by_size(layouts: tuple[Layout, ...]) -> list[Layout]:
    """The order in which layouts are tried: the one of the most fields first, else as listed.

    A layout is selected if the fingerprint of its fields that a schema or record has is its own; other fields do not matter.
    """
    return sorted(layouts, key=lambda x: -len(x.paths))


def _turn(role: Column, text: Column) -> Column:
    names = F.create_map(*[F.lit(x) for kv in ROLES.items() for x in kv])
    return F.struct(F.coalesce(names[role], role, F.lit("")).alias("role"), F.coalesce(text, F.lit("")).alias("text"))


def canonical_turns(df: DataFrame, record: str | None = None, layouts: tuple[Layout, ...] = LAYOUTS) -> DataFrame:
    """Adds ``layout``, the name of the layout, and ``turns``, an array of (role, text), to records of any known layout.

    ``record`` None: the frame's own schema chooses one mapping. Else the JSON text in that column is looked at record by
    record: the field paths it holds (keys count, also with null values, in any element of a list) are hashed, and the hash selects
    the mapping. Null texts and roles are empty; an empty or missing ``input`` adds nothing to its turn; an empty list has no turns.
    Records that are null, no JSON object or of no known layout have a null layout and no turns, so they can be told from others.
    """
    none = F.array().cast(_TURNS)
    if record is None:
        x = layout_of(df.schema, layouts)
        out = df.withColumn("layout", F.lit(x.name))
        if x.name == "rows":  # each row is a turn
            return out.withColumn("turns", F.array(F.struct(F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))))
        if x.many:
            top, role, text = x.many
            return out.withColumn("turns", F.coalesce(_listed(F.col(top), role, text), none))
        return out.withColumn("turns", _spread([(r, F.col(p)) for r, p in x.turns]))
    layouts, json = tuple(x for x in layouts if x.name != "rows"), F.col(record)
    have = record_paths(json, layouts)
    layout, turns = F.lit(None).cast("string"), none
    for x in reversed(by_size(layouts)):
        own = F.array_join(F.array_sort(F.array_intersect(have, F.array(*[F.lit(p) for p in x.paths]))), "\n")
        if x.many:
            top, role, text = x.many
            items = F.from_json(F.get_json_object(json, f"$.{top}"), f"array<struct<`{role}`:string,`{text}`:string>>")
            said = F.coalesce(_listed(items, role, text), none)
        else:
            said = _spread([(r, F.get_json_object(json, f"$.{p}")) for r, p in x.turns])
        fits = F.coalesce(F.xxhash64(own) == F.lit(fingerprint(x.paths)), F.lit(False))
        layout, turns = F.when(fits, F.lit(x.name)).otherwise(layout), F.when(fits, said).otherwise(turns)
    return df.withColumns({"layout": layout, "turns": turns})


_TURNS = "array<struct<role:string,text:string>>"


def record_paths(json: Column, layouts: tuple[Layout, ...]) -> Column:
    """The field paths of a JSON object: its keys, and the keys in any element of the lists that layouts know. Null if it is no object."""

    def inside(top: str) -> Column:
        items = F.from_json(F.get_json_object(json, f"$.{top}"), "array<map<string,string>>")
        keys = F.flatten(F.transform(F.filter(items, lambda m: m.isNotNull()), F.map_keys))
        return F.coalesce(F.transform(keys, lambda k: F.concat(F.lit(f"{top}[]."), k)), F.array().cast("array<string>"))

    return F.array_distinct(F.concat(F.json_object_keys(json), *[inside(t) for t in sorted({x.many[0] for x in layouts if x.many})]))


def unknown_layouts(df: DataFrame, record: str, layouts: tuple[Layout, ...] = LAYOUTS) -> DataFrame:
    """(paths, n): the records without a known layout, counted by their field paths (null: no JSON object)."""
    lists = tuple(x for x in layouts if x.name != "rows")
    lost = canonical_turns(df.select(F.col(record).alias("record")), "record", layouts).where("layout is null")
    return lost.groupBy(F.array_join(F.array_sort(record_paths(F.col("record"), lists)), "\n").alias("paths")).agg(F.count("*").alias("n"))


def _listed(items: Column, role: str, text: str) -> Column:
    return F.transform(items, lambda m: _turn(m[role], m[text]))


def _spread(parts: list[tuple[str, Column]]) -> Column:
    """One turn for each role; texts of neighbours with one role are joined by an empty line."""
    roles = list(dict.fromkeys(r for r, _ in parts))
    return F.array(*[_turn(F.lit(r), F.array_join(F.filter(F.array(*[F.coalesce(t, F.lit("")) for k, t in parts if k == r]), lambda t: t != ""), "\n\n")) for r in roles])


def turn_rows(df: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text) of a table of any known layout, by the mapping that its schema's fingerprint selects.

    Rows by turn keep their own numbers; the turns of a record are numbered from 0. Records without a conv_id get numbers of their own.
    """
    by_turn = layout_of(df.schema).name == "rows"
    conv = F.col("conv_id") if "conv_id" in df.columns else F.monotonically_increasing_id()
    turns = canonical_turns(df).select(conv.cast("bigint").alias("conv_id"), F.col("turn") if by_turn else F.lit(None).alias("turn"), "turns")
    if by_turn:
        return turns.select("conv_id", "turn", F.col("turns")[0]["role"].alias("role"), F.col("turns")[0]["text"].alias("text"))
    return turns.select("conv_id", F.posexplode("turns").alias("turn", "t")).select("conv_id", F.col("turn").cast("bigint"), "t.role", "t.text")


def escape(text: Column, codes=CODES) -> Column:
    for plain, code in codes:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescape(text: Column, codes=CODES) -> Column:
    for plain, code in reversed(codes):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def format_turns(rows: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", learn: str = "assistant") -> DataFrame:
    """(conv, formatted, loss_spans) from rows by turn: the text of a conversation and the (start, length) in code points of what is learned.

    Turns stand by number, nulls first, ties by role and text; repeated rows are repeated turns. A null text or role is
    empty, a null conversation is one of its own. Other columns are left out. No rows give no rows.
    """
    r, t = escape(F.coalesce(F.col(role), F.lit("")), ROLE_CODES), escape(F.coalesce(F.col(text), F.lit("")))
    head = F.concat(F.lit(OPEN), r, F.lit(MID))
    parts = rows.select(F.col(conv), F.col(turn).alias("_n"), r.alias("_r"), t.alias("_t"), F.char_length(head).alias("_h"), (F.col(role) == learn).alias("_learn"))
    parts = parts.withColumn("_len", (F.col("_h") + F.char_length("_t") + len(CLOSE)).cast("bigint"))
    before = Window.partitionBy(conv).orderBy(F.col("_n").asc_nulls_first(), "_r", "_t").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    placed = parts.withColumn("_at", F.sum("_len").over(before) - F.col("_len"))
    one = F.struct(F.col("_n").isNotNull().alias("some"), "_n", "_r", "_t", "_at", "_h", "_learn")
    turns = placed.groupBy(conv).agg(F.array_sort(F.collect_list(one)).alias("_turns"))
    text_ = F.array_join(F.transform("_turns", lambda x: F.concat(F.lit(OPEN), x["_r"], F.lit(MID), x["_t"], F.lit(CLOSE))), "")
    spans = F.transform(F.filter("_turns", lambda x: x["_learn"]), lambda x: F.struct((x["_at"] + x["_h"]).cast("int").alias("start"), F.char_length(x["_t"]).alias("length")))
    return turns.select(conv, text_.alias("formatted"), spans.alias("loss_spans"))


def read_back(formatted: Column) -> Column:
    """The (role, text) turns of a formatted conversation, with the codes undone."""
    parts = F.filter(F.split(formatted, "</turn>\\n", -1), lambda x: x != "")

    def one(x: Column) -> Column:
        said = F.substr(x, F.lit(len(OPEN) + 1))
        cut = F.instr(said, MID)
        return F.struct(unescape(F.substr(said, F.lit(1), cut - 1), ROLE_CODES).alias("role"), unescape(F.substr(said, cut + len(MID))).alias("text"))

    return F.transform(parts, one)


def learned_text(formatted: Column, spans: Column) -> Column:
    """All text under the loss mask, unescaped, nothing between."""
    return F.array_join(F.transform(spans, lambda s: unescape(F.substr(formatted, s["start"] + 1, s["length"]))), "")


def digests(spark, conversations: DataFrame) -> DataFrame:
    """The query's columns, read back from what ``format_turns`` wrote."""
    extra = "\\### Assistant: </turn> ok"
    more = spark.range(2).select(F.lit(-7).cast("bigint").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(extra).alias("text"))
    done = format_turns(turn_rows(conversations).unionByName(more))
    read = done.select("conv_id", "formatted", read_back(F.col("formatted")).alias("turns"), learned_text(F.col("formatted"), F.col("loss_spans")).alias("learned"))
    told = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id",
        F.size("turns").cast("bigint").alias("n_turns"),
        F.sha2(told, 256).alias("turns_sha256"),
        F.char_length("learned").cast("bigint").alias("loss_chars"),
        F.sha2("learned", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("bigint").alias("formatted_chars"),
    )


_ESC = r"replace(replace(replace({x}, '\', '\b'), '###', '\h'), '</turn>', '\t')"
ORACLE = f"""
WITH rows_ AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text, role = 'assistant' AS learn FROM conversations
  UNION ALL
  SELECT -7, n, CASE n WHEN 0 THEN 'user' ELSE 'assistant' END, '\\### Assistant: </turn> ok', n = 1 FROM range(2) t(n)
)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE learn), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE learn), '')) AS loss_sha256,
  CAST(sum(14 + length(replace({_ESC.format(x='role')}, ':', '\\c')) + length({_ESC.format(x='text')})) AS BIGINT) AS formatted_chars
FROM rows_ GROUP BY conv_id
"""
