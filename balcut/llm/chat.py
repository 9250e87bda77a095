"""Chat formatting: layouts recognised by a fingerprint of their fields, one reversible template.

A record is a JSON text. The fingerprint is a hash of its nested field paths without scalar types,
so records of one layout agree whatever their values are. It selects a declarative mapping that
turns the record into canonical turns (turn, role, text). Rows of a plain table are packed as
records of the ``turn rows`` layout and take the same way.

The template writes each turn as ``<turn role="R">TEXT</turn>`` and a line end. Inside roles and
texts the escape character and the two characters that marks are made of become two-character
codes, so no text can hold a mark, and reading back gives every text exactly.

Defined results: null texts and roles count as empty; turns with one number are ordered by role
and text, repeated rows stay; null turns come last, ordered in the same way; records of an unknown layout or broken JSON are kept with a null
layout and no turns; an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import each, fenced, running_start, sealed, table

#: Codes inside texts (fixed values): escape character, opening character, quotation mark.
CODES = (("\\", "\\b"), ("<", "\\l"), ('"', "\\q"))
OPEN, ROLE_END, CLOSE = '<turn role="', '">', "</turn>\n"
TURN = "array<struct<turn:bigint,role:string,text:string>>"

#: Layouts: an example record each, from which the fingerprint comes, and the mapping to turns.
LAYOUTS: dict[str, tuple[str, str]] = {
    "turn rows": (
        '{"turn":0,"role":"user","text":"a"}',
        "array(named_struct('turn', cast(get_json_object(j, '$.turn') as bigint), 'role', get_json_object(j, '$.role'), 'text', get_json_object(j, '$.text')))",
    ),
    "messages": (
        '{"messages":[{"role":"user","content":"a"}]}',
        "transform(from_json(j, 'messages array<struct<role:string,content:string>>').messages, (m, i) -> named_struct('turn', cast(i as bigint), 'role', m.role, 'text', m.content))",
    ),
    "from and value": (
        '{"conversations":[{"from":"human","value":"a"}]}',
        "transform(from_json(j, 'conversations array<struct<`from`:string,value:string>>').conversations, (m, i) -> named_struct('turn', cast(i as bigint), 'role', case m.`from` when 'human' then 'user' when 'gpt' then 'assistant' else m.`from` end, 'text', m.value))",
    ),
    "prompt and completion": (
        '{"prompt":"a","completion":"b"}',
        "array(named_struct('turn', 0L, 'role', 'user', 'text', get_json_object(j, '$.prompt')), named_struct('turn', 1L, 'role', 'assistant', 'text', get_json_object(j, '$.completion')))",
    ),
    "instruction": (
        '{"instruction":"a","input":"b","output":"c"}',
        "array(named_struct('turn', 0L, 'role', 'user', 'text', concat_ws('\\n\\n', get_json_object(j, '$.instruction'), nullif(get_json_object(j, '$.input'), ''))), named_struct('turn', 1L, 'role', 'assistant', 'text', get_json_object(j, '$.output')))",
    ),
    "instruction without input": (
        '{"instruction":"a","output":"c"}',
        "array(named_struct('turn', 0L, 'role', 'user', 'text', get_json_object(j, '$.instruction')), named_struct('turn', 1L, 'role', 'assistant', 'text', get_json_object(j, '$.output')))",
    ),
    "question and answer": (
        '{"question":"a","answer":"b"}',
        "array(named_struct('turn', 0L, 'role', 'user', 'text', get_json_object(j, '$.question')), named_struct('turn', 1L, 'role', 'assistant', 'text', get_json_object(j, '$.answer')))",
    ),
}


def fingerprint(record: Column) -> Column:
    """Hash of the nested field paths of a JSON text; null where it can't be read.

    The variant's schema lists fields by name at every level; scalar types, void among them, go.
    """
    shape = F.schema_of_variant(F.try_parse_json(record))
    paths = F.regexp_replace(shape, r": (?:STRING|BIGINT|VOID|DOUBLE|BOOLEAN|DECIMAL\([0-9,]+\))", ": *")
    return F.xxhash64(F.regexp_replace(paths, r"<(?:STRING|BIGINT|VOID|DOUBLE|BOOLEAN|DECIMAL\([0-9,]+\))>", "<*>"))


def canonical_turns(df: DataFrame, record: str, key: str) -> DataFrame:
    """(key, layout, turns) of every record; the fingerprint selects the mapping."""
    spark = df.sparkSession
    shapes = spark.createDataFrame([(name, example) for name, (example, _) in LAYOUTS.items()], "layout string, example string")
    prints = {r["layout"]: r["print"] for r in shapes.select("layout", fingerprint(F.col("example")).alias("print")).collect()}
    df = fenced(df.select(F.col(key).alias("_key"), F.col(record).alias("j"))).withColumn("_print", fingerprint(F.col("j")))
    layout, turns = F.lit(None).cast("string"), F.array().cast(TURN)
    for name, (_, mapping) in LAYOUTS.items():
        here = F.col("_print") == prints[name]
        layout = F.when(here, F.lit(name)).otherwise(layout)
        turns = F.when(here, F.expr(mapping).cast(TURN)).otherwise(turns)
    return df.select(F.col("_key").alias(key), layout.alias("layout"), turns.alias("turns"), "_fence")


def packed_rows(rows: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """Rows of a table of turns as records of the ``turn rows`` layout."""
    record = F.to_json(F.struct(F.col(turn).cast("bigint").alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")), {"ignoreNullFields": "false"})
    return rows.select(F.col(conv_id).alias("conv_id"), record.alias("record"))


def escaped(text: Column) -> Column:
    for plain, code in CODES:
        text = F.replace(text, F.lit(plain), F.lit(code))
    return text


def unescaped(text: Column) -> Column:
    """The escape character comes back last: until then each of its uses is the start of a code."""
    for plain, code in reversed(CODES):
        text = F.replace(text, F.lit(code), F.lit(plain))
    return text


def formatted(turns: DataFrame) -> DataFrame:
    """(conv_id, formatted) from rows (conv_id, turn, role, text)."""
    piece = F.concat(F.lit(OPEN), escaped(F.coalesce("role", F.lit(""))), F.lit(ROLE_END), escaped(F.coalesce("text", F.lit(""))), F.lit(CLOSE))
    one = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"), piece.alias("piece"))
    # Turns are unique but for ties, which role and text order; a conversation is one output row.
    place = F.struct(F.col("t.turn").isNull().alias("last"), "t.turn", "t.role", "t.text", "t.piece")
    rows = turns.select("conv_id", one.alias("t")).groupBy("conv_id").agg(F.sort_array(F.collect_list(place)).alias("t"))
    return rows.select("conv_id", F.array_join(F.transform("t", lambda t: t["piece"]), "").alias("formatted"))


def read_back(df: DataFrame, text: str = "formatted", trained: str = "assistant") -> DataFrame:
    """Adds ``turns`` (role, text, start, end, loss): the parsed turns and where their text stands.

    ``loss`` marks the turns of the trained role; start and end are code points of the formatted text.
    """
    parts = F.split(F.col(text), CLOSE, -1)
    df = fenced(df).withColumn("_parts", F.slice(parts, 1, F.size(parts) - 1))
    df = df.withColumn("_cut", F.transform("_parts", lambda p: F.instr(p, ROLE_END)))
    df = df.withColumn("_len", F.transform("_parts", lambda p: F.length(p) + len(CLOSE)))
    df = df.withColumn("_at", running_start(F.col("_len")))
    role = lambda p, i: unescaped(F.substring(p, F.lit(len(OPEN) + 1), F.get(F.col("_cut"), i) - len(OPEN) - 1))
    body = lambda p, i: unescaped(F.substring(p, F.get(F.col("_cut"), i) + len(ROLE_END), F.length(p)))
    turns = F.transform(
        "_parts",
        lambda p, i: F.struct(
            role(p, i).alias("role"),
            body(p, i).alias("text"),
            (F.get(F.col("_at"), i) + F.get(F.col("_cut"), i) + len(ROLE_END) - 1).alias("start"),
            (F.get(F.col("_at"), i) + F.get(F.col("_len"), i) - len(CLOSE)).alias("end"),
            (role(p, i) == trained).alias("loss"),
        ),
    )
    return sealed(df.withColumn("turns", turns).drop("_parts", "_cut", "_len", "_at", "_fence"))


#: A conversation whose texts imitate marks of several templates.
TRAP_ID, TRAP_TEXT = -7, "\\### Assistant: </turn> ok"


def op9_chat_format(spark, sf_dir: str) -> DataFrame:
    trap = spark.range(2).select(F.lit(TRAP_ID).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(TRAP_TEXT).alias("text"))
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(trap)
    canonical = canonical_turns(packed_rows(rows), "record", "conv_id")
    turns = canonical.select("conv_id", "_fence", each(F.col("turns")).alias("t")).where("t is not null and _fence >= 0").select("conv_id", "t.*")
    back = read_back(formatted(turns))
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), "")
    said = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    back = back.withColumn("_loss", loss)
    return back.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(said, 256).alias("turns_sha256"),
        F.length("_loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("_loss"), 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def _sql_escaped(x: str) -> str:
    for plain, code in CODES:
        x = f"replace({x}, '{plain}', '{code}')"
    return x


OP9_SQL = f"""
with r as (
  select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select {TRAP_ID}, 0, 'user', '{TRAP_TEXT}' union all select {TRAP_ID}, 1, 'assistant', '{TRAP_TEXT}')
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  cast(coalesce(sum(length(text)) filter (where role = 'assistant'), 0) as bigint) as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (where role = 'assistant'), '')) as loss_sha256,
  cast(sum({len(OPEN) + len(ROLE_END) + len(CLOSE)} + length({_sql_escaped('role')}) + length({_sql_escaped('text')})) as bigint) as formatted_chars
from r group by conv_id
"""
