"""Chat formatting with a grammar that reads back exactly, in DataFrame functions only.

A turn is written ``<turn ROLE>``, a line feed, its text, ``</turn>`` and a line feed. The parser ends a turn at every
``</turn>`` and begins one at every ``<turn ``, takes the role up to ``>`` and a line feed and undoes escapes:
backslash-l is ``<``, backslash-b is a backslash, backslash-g is ``>``. A turn is first written as it is; if the parser
would not return it unchanged, as with any marker or escape inside its role or text, its conflicting characters are
escaped. The whole conversation is parsed again and must equal its source. So no marker ever stands inside a text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# Fixed values of the template.
OPEN, SHUT, CLOSE, END = "<turn ", ">\n", "</turn>", "\n"
ESCAPES = (("\\", "\\b"), ("<", "\\l"), (">", "\\g"))
BLOCK = 1024  # code points of the blocks that masked spans are cut from
_WHOLE = 2147483647


def escape(text: Column) -> Column:
    for plain, coded in ESCAPES:
        text = F.replace(text, F.lit(plain), F.lit(coded))
    return text


def unescape(text: Column) -> Column:
    for plain, coded in reversed(ESCAPES):
        text = F.replace(text, F.lit(coded), F.lit(plain))
    return text


def _turn(role: Column, text: Column) -> Column:
    return F.concat(F.lit(OPEN), role, F.lit(SHUT), text, F.lit(CLOSE + END))


def parse(formatted: Column) -> Column:
    """array<struct<role, text>> of a formatted conversation."""
    bodies = F.flatten(F.transform(F.split(formatted, CLOSE), lambda x: F.slice(F.split(x, OPEN), F.lit(2), F.size(F.split(x, OPEN)))))  # no pattern characters

    def one(body: Column) -> Column:
        role = F.substring_index(body, SHUT, 1)
        text = F.substring(body, F.length(role) + len(SHUT) + 1, F.lit(_WHOLE))
        return F.struct(unescape(role).alias("role"), unescape(text).alias("text"))

    return F.transform(bodies, one)


def render(role: Column, text: Column) -> tuple[Column, Column]:
    """A turn's segment, and its text as it stands there: raw if it parses back unchanged, else escaped."""
    raw = _turn(role, text)
    same = parse(raw) == F.array(F.struct(role.alias("role"), text.alias("text")))
    return F.when(same, raw).otherwise(_turn(escape(role), escape(text))), F.when(same, text).otherwise(escape(text))


def format_conversations(turns: DataFrame, loss_role: str = "assistant") -> DataFrame:
    """(conv_id, formatted, loss_spans) for each conversation of ``turns`` (conv_id, turn, role, text).

    Rows stand by turn, nulls first; rows of one turn stand by role and text. A null text or role is empty. Null
    conv_id is one conversation. ``loss_spans`` has start and end, in code points of ``formatted``, of the text of each
    turn of ``loss_role``. Turns are rendered and measured before they are shuffled; the only thing gathered for a
    conversation is its own output, which must fit a row (2 GB). A conversation that would not read back equal to its
    source raises an error. Other columns are left out. An empty table gives no rows.
    """
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    segment, shown = render(F.col("role"), F.col("text"))
    rows = rows.select("conv_id", "turn", "role", "text", segment.alias("segment"), F.length(shown).alias("shown"))
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    rows = rows.withColumn("rank", F.row_number().over(order))
    rows = rows.withColumn("end", F.sum(F.length("segment")).over(order.rowsBetween(Window.unboundedPreceding, 0)) - len(CLOSE + END))
    gathered = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("rank", "role", "text", "segment", "end", "shown"))).alias("all"))
    formatted = F.array_join(F.col("all.segment"), "")
    spans = F.transform(F.filter("all", lambda x: x["role"] == loss_role), lambda x: F.struct((x["end"] - x["shown"]).alias("start"), x["end"].alias("end")))
    done = gathered.select("conv_id", formatted.alias("formatted"), spans.alias("loss_spans"), F.transform("all", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"))).alias("source"))
    alike = parse(F.col("formatted")) == F.col("source")
    checked = F.when(alike, F.col("formatted")).otherwise(F.raise_error(F.lit("a formatted conversation does not read back")))
    return done.select("conv_id", checked.alias("formatted"), "loss_spans")


def masked(formatted: Column, spans: Column) -> Column:
    """Text of ``formatted`` under ``spans``, each unescaped, in order; empty where there are none.

    A span is cut from the blocks it lies in, so the cost does not grow with the spans times the whole length.
    """
    blocks = F.regexp_extract_all(formatted, F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0))

    def one(span: Column, blocks: Column) -> Column:
        first, last = F.floor(span["start"] / BLOCK).cast("int"), F.floor(span["end"] / BLOCK).cast("int")
        near = F.array_join(F.slice(blocks, first + 1, last - first + 1), "")
        return unescape(F.substring(near, (span["start"] % BLOCK + 1).cast("int"), (span["end"] - span["start"]).cast("int")))

    empty = F.array().cast("array<struct<start:bigint,end:bigint>>")
    return F.element_at(F.transform(F.array(blocks), lambda b: F.array_join(F.transform(F.coalesce(spans, empty), lambda x: one(x, b)), "")), 1)


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of formatted conversations: of the turns that the parser returns, and of the text that stands under
    ``loss_spans``, cut from ``formatted`` and unescaped. Null spans mask nothing. Other columns are left out."""
    rows = formatted.select("conv_id", "formatted", parse(F.col("formatted")).alias("turns"), masked(F.col("formatted"), F.col("loss_spans")).alias("learnt"))
    said = F.array_join(F.transform("turns", lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), "")
    rows = rows.select("conv_id", "formatted", F.size("turns").cast("long").alias("n_turns"), said.alias("said"), "learnt")
    return rows.select(
        "conv_id", "n_turns", F.sha2(F.col("said").cast("binary"), 256).alias("turns_sha256"), F.length("learnt").cast("long").alias("loss_chars"),
        F.sha2(F.col("learnt").cast("binary"), 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"),
    )
