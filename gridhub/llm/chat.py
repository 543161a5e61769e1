"""Chat formatting with Spark expressions only.

A conversation becomes ``<s>`` followed by blocks ``[INST] role [/INST]text</s>``; turns of
one role that follow each other share a block and are parted by ``<s>``.  Inside roles and
texts a backslash goes in front of every backslash and behind the first character of every
control string, so splitting on the control strings reads back exactly what went in.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The control strings of the template.
BEGIN, END, HEAD, TAIL = "<s>", "</s>", "[INST] ", " [/INST]"
CONTROL = ("<s>", "</s>", "[INST]", "[/INST]")

#: Turns whose spans are placed together.
BLOCK = 128

#: The conversation that the query adds: control strings typed by the speakers.
TRICKY = [(-7, 0, "user", "</s>[INST] ok [/INST]"), (-7, 1, "assistant", "</s>[INST] ok [/INST]")]


def escape(text: Column) -> Column:
    out = F.replace(text, F.lit("\\"), F.lit("\\\\"))
    for c in CONTROL:
        out = F.replace(out, F.lit(c), F.lit(c[0] + "\\" + c[1:]))
    return out


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def format_chats(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", loss_role: str = "assistant") -> DataFrame:
    """One formatted string per conversation, with the spans that training learns from.

    Rows are ordered by (turn, role, text); nulls in role or text count as empty, a null
    turn sorts first, rows with a null conversation id form one conversation, repeated
    rows are kept.  Other columns are ignored.  An empty table gives an empty result.

    Returns the conversation id, ``formatted`` and ``loss_spans``: code point ranges
    ``(start, length)`` in ``formatted`` that hold escaped texts of ``loss_role``.
    """
    rows = turns.select(F.col(conv).alias("c"), F.struct(F.col(turn).alias("turn"), F.coalesce(F.col(role), F.lit("")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("text")).alias("t"))
    grouped = rows.groupBy("c").agg(F.array_sort(F.collect_list("t")).alias("ts"))

    last = F.size("ts") - 1
    same = lambda i, j: F.get("ts", i)["role"] == F.get("ts", j)["role"]

    def piece(t: Column, i: Column) -> Column:
        opens = (i == 0) | ~same(i, i - 1)
        closes = (i == last) | ~same(i, i + 1)
        before = F.when(opens, F.concat(F.lit(HEAD), escape(t["role"]), F.lit(TAIL))).otherwise(F.lit(BEGIN))
        body = escape(t["text"])
        return F.struct(before.alias("before"), body.alias("body"), F.when(closes, F.lit(END)).otherwise(F.lit("")).alias("after"), (t["role"] == loss_role).alias("learn"))

    merged = grouped.select("c", F.transform("ts", piece).alias("ps"))
    text_of = lambda p: F.concat(p["before"], p["body"], p["after"])
    length = lambda p: (F.length(p["before"]) + F.length(p["body"]) + F.length(p["after"])).cast("long")
    no_spans = F.array().cast("array<struct<start:bigint,length:bigint>>")

    def step(acc: Column, p: Column) -> Column:
        begin = acc["at"] + F.length(p["before"])
        span = F.array(F.struct(begin.alias("start"), F.length(p["body"]).cast("long").alias("length")))
        return F.struct((acc["at"] + length(p)).alias("at"), F.when(p["learn"], F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    # an array that grows is copied at every step, so offsets go block by block first
    blocks = merged.withColumn("bs", F.transform(F.sequence(F.lit(0), F.floor((F.size("ps") - 1) / BLOCK)), lambda b: F.slice("ps", (b * BLOCK + 1).cast("int"), BLOCK)))
    sizes = F.transform("bs", lambda b: F.aggregate(b, F.lit(0).cast("long"), lambda a, p: a + length(p)))
    grow = lambda a, n: F.concat(a, F.array(F.element_at(a, -1) + n))
    starts = F.aggregate(sizes, F.array(F.lit(len(BEGIN)).cast("long")), grow)
    placed = blocks.withColumn("at", starts)

    def spans(block: Column, i: Column) -> Column:
        return F.aggregate(block, F.struct(F.get("at", i).alias("at"), no_spans.alias("spans")), step)["spans"]

    return placed.select(
        F.col("c").alias(conv),
        F.concat(F.lit(BEGIN), F.array_join(F.transform("ps", text_of), "")).alias("formatted"),
        F.flatten(F.transform("bs", spans)).alias("loss_spans"),
    )


def read_back(formatted: Column) -> Column:
    """The turns of a formatted conversation as array<struct<role, text>>, unescaped."""
    body = F.substr(formatted, F.lit(len(BEGIN) + 1))
    blocks = F.filter(F.split(body, END, -1), lambda b: b != "")

    def turns_of(block: Column) -> Column:
        cut = F.instr(block, TAIL)
        role = F.substr(block, F.lit(len(HEAD) + 1), cut - len(HEAD) - 1)
        texts = F.split(F.substr(block, cut + len(TAIL)), BEGIN, -1)
        return F.transform(texts, lambda x: F.struct(unescape(role).alias("role"), unescape(x).alias("text")))

    return F.flatten(F.transform(blocks, turns_of))


def op1_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ``conversations`` and conversation -7, digested from what was formatted."""
    table = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    done = format_chats(table.unionByName(spark.createDataFrame(TRICKY, table.schema)))
    read = done.select("conv_id", "formatted", read_back(F.col("formatted")).alias("turns"), F.transform("loss_spans", lambda s: unescape(F.substr("formatted", s["start"] + 1, s["length"]))).alias("learned"))
    learned = F.array_join("learned", "")
    return read.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), ""), 256).alias("turns_sha256"),
        F.length(learned).cast("long").alias("loss_chars"),
        F.sha2(learned, 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


_ESCAPED = "replace(replace(replace(replace(replace({0}, '\\', '\\\\'), '<s>', '<\\s>'), '</s>', '<\\/s>'), '[INST]', '[\\INST]'), '[/INST]', '[\\/INST]')"

OP1_SQL = f"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), marked AS (
  SELECT *, lag(role) OVER w IS DISTINCT FROM role AS opens, lead(role) OVER w IS DISTINCT FROM role AS closes
  FROM rows WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text)
)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  length(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), ''))::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  (3 + sum(length({_ESCAPED.format('text')}) + CASE WHEN opens THEN 15 + length({_ESCAPED.format('role')}) ELSE 3 END
    + CASE WHEN closes THEN 4 ELSE 0 END))::BIGINT AS formatted_chars
FROM marked GROUP BY conv_id
"""
