"""Chat formatting: schema fingerprints select declarative mappings; a reversible template renders the turns.

Records of any layout (VARIANT values) are recognised by a fingerprint: the hash of their nested field paths.
Each known layout is a row of `LAYOUTS`: paths, and SQL over the record `r` that yields canonical turns.
Everything is JVM-side DataFrame functions.

Template: `<|im_start|>role\\ntext<|im_end|>\\n`. Inside roles and texts `&` becomes `&amp;` and `<|` becomes `&lt;|`, so
no control string can come from a text; in roles a line feed becomes `&#10;`. Reading back reverses this exactly.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Fixed values of the template.
START, END = "<|im_start|>", "<|im_end|>\n"

TURN = "struct<role:string,text:string>"


@dataclass(frozen=True)
class Layout:
    """paths: nested field paths, sorted, lists as []; turns: SQL for an array of (role, text) over the variant `r`."""

    name: str
    paths: str
    turns: str


def _turn(role: str, text: str) -> str:
    return f"named_struct('role', cast({role} as string), 'text', cast(coalesce({text}, '') as string))"


def _field(path: str) -> str:
    return f"try_variant_get(r, '$.{path}', 'string')"


LAYOUTS = (
    Layout("turn", "role,text", f"array({_turn(_field('role'), _field('text'))})"),
    Layout("prompt_response", "prompt,response", f"array({_turn("'user'", _field('prompt'))}, {_turn("'assistant'", _field('response'))})"),
    Layout("instruction", "instruction,output", f"array({_turn("'user'", _field('instruction'))}, {_turn("'assistant'", _field('output'))})"),
    Layout(
        "instruction_input",
        "input,instruction,output",
        "array("
        + _turn("'user'", f"concat_ws('\\n', {_field('instruction')}, nullif({_field('input')}, ''))")
        + f", {_turn("'assistant'", _field('output'))})",
    ),
    Layout("messages", "messages,messages[].content,messages[].role", f"transform(try_variant_get(r, '$.messages', 'array<struct<role:string,content:string>>'), m -> {_turn('m.role', 'm.content')})"),
    Layout(
        "conversations",
        "conversations,conversations[].from,conversations[].value",
        "transform(try_variant_get(r, '$.conversations', 'array<struct<from:string,value:string>>'), m -> "
        + _turn("case m.from when 'human' then 'user' when 'gpt' then 'assistant' else m.from end", "m.value")
        + ")",
    ),
)


def field_paths(record: Column) -> Column:
    """Nested field paths of a VARIANT as a canonical schema text: names and nesting, no scalar types."""
    schema = F.schema_of_variant(record)
    bare = F.regexp_replace(schema, r": (?!ARRAY<OBJECT|OBJECT)[A-Z]+(\([0-9,]+\))?(<[A-Z]+>)?", "")
    return bare


def _canonical(paths: str) -> str:
    """The schema text that `field_paths` gives for sorted paths of depth one or of a list of objects."""
    names = [p for p in paths.split(",") if "[]" not in p]
    inner = [p.split("[].", 1)[1] for p in paths.split(",") if "[]" in p]
    return "OBJECT<" + ", ".join(names) + (f": ARRAY<OBJECT<{', '.join(inner)}>>" if inner else "") + ">"


def fingerprint(record: Column) -> Column:
    return F.xxhash64(field_paths(record))


def canonical_turns(records: DataFrame, record: str = "r") -> DataFrame:
    """Adds layout (name, null if unknown) and turns (array of role, text; null if unknown) for the VARIANT column."""
    spark = records.sparkSession
    known = spark.range(1).select(*[F.xxhash64(F.lit(_canonical(x.paths))).alias(x.name) for x in LAYOUTS]).first().asDict()
    found = records.withColumn("_fp", fingerprint(F.col(record)))
    layout, turns = F.lit(None).cast("string"), F.lit(None).cast(f"array<{TURN}>")
    for x in LAYOUTS:
        hit = F.col("_fp") == known[x.name]
        layout = F.when(hit, F.lit(x.name)).otherwise(layout)
        turns = F.when(hit, F.expr(x.turns.replace("(r,", f"({record},")).cast(f"array<{TURN}>")).otherwise(turns)
    return found.withColumn("layout", layout).withColumn("turns", turns).drop("_fp")


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&"), F.lit("&amp;")), F.lit("<|"), F.lit("&lt;|"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&lt;|"), F.lit("<|")), F.lit("&amp;"), F.lit("&"))


def render(role: Column, text: Column) -> Column:
    head = F.replace(escape(F.coalesce(role, F.lit(""))), F.lit("\n"), F.lit("&#10;"))
    return F.concat(F.lit(START), head, F.lit("\n"), escape(F.coalesce(text, F.lit(""))), F.lit(END))


def format_turns(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", learn: str = "assistant") -> DataFrame:
    """One row per conversation: conv, formatted, loss_spans (array of begin, end: where the texts of role `learn` stand in the UTF-8 bytes of `formatted`).

    Turns are rendered where they are read and ordered by (turn, role, text), nulls first; rows that repeat are a turn each. Null texts and roles are empty. Null
    conversations are one conversation. An empty table gives no rows. Long texts are never cut; a conversation is one value, so its rows meet in one task; nothing else
    of it does. Extra columns are ignored, whatever their names.
    """
    body = escape(F.coalesce(F.col(text), F.lit("")))
    rows = turns.select(F.col(conv).alias("conv"), F.col(turn).alias("t"), F.col(role).alias("r"), F.col(text).alias("x"), render(F.col(role), F.col(text)).alias("s"), F.octet_length(body).alias("n"))
    upto = W.partitionBy("conv").orderBy(F.asc_nulls_first("t"), F.asc_nulls_first("r"), F.asc_nulls_first("x")).rowsBetween(W.unboundedPreceding, 0)
    # the window and the grouping share one exchange
    placed = rows.withColumn("end", F.sum(F.octet_length("s")).over(upto) - F.lit(len(END)))
    learned = F.coalesce(F.col("r") == learn, F.lit(False))
    part = F.struct("end", "s", (F.col("end") - F.col("n")).alias("begin"), learned.alias("learned"))
    grouped = placed.groupBy("conv").agg(F.array_sort(F.collect_list(part)).alias("parts"))
    spans = F.transform(F.filter("parts", lambda p: p["learned"]), lambda p: F.struct(p["begin"].alias("begin"), p["end"].alias("end")))
    return grouped.select(F.col("conv").alias(conv), F.array_join(F.transform("parts", lambda p: p["s"]), "").alias("formatted"), spans.alias("loss_spans"))


def under_mask(formatted: Column, spans: Column) -> Column:
    """The texts that the mask covers, cut from `formatted` by their spans and unescaped: an array of strings."""
    raw = formatted.cast("binary")
    return F.transform(spans, lambda s: unescape(F.substring(raw, s["begin"].cast("int") + 1, (s["end"] - s["begin"]).cast("int")).cast("string")))


def read_back(formatted: Column) -> Column:
    """Turns (role, text) parsed from a formatted string."""
    parts = F.split(formatted, r"\Q" + END.rstrip("\n") + r"\E\n")
    bodies = F.filter(parts, lambda p: F.length(p) > 0)

    def turn(p: Column) -> Column:
        body = F.substr(p, F.lit(len(START) + 1))
        role = F.substring_index(body, "\n", 1)
        text = F.substr(body, F.length(role) + F.lit(2))
        return F.struct(unescape(F.replace(role, F.lit("&#10;"), F.lit("\n"))).alias("role"), unescape(text).alias("text"))

    return F.transform(bodies, turn)
