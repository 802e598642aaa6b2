"""Chat formatting with quotation linking (built-in functions only).

Lines that begin with '>' are quoted, as deep as they have marks. Runs of quoted lines of one depth are passages; a
passage and each of its lines are normalised and hashed, and so are the unquoted text and lines of every message of a
conversation that quotes. A message replies to the latest earlier message that holds its shallowest, longest quotation,
or else to the message before it. A message that quotes belongs to the chain of the message it quotes; conversations
are ordered by the turn at the head of the chain and then by turn, so replies follow what they answer.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from halograph.llm.common import Scratch

QUOTED = r"^[ \t]*>"
#: Turns that are put in order together; a conversation of any length is dealt to tasks in such spans.
SPAN = 4096


def _normal(text: Column) -> Column:
    return F.lower(F.trim(F.regexp_replace(text, r"[ \t\n\r\f]+", " ")))


def _key(text: Column) -> Column:
    return F.sha2(_normal(text), 256)


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def unquoted(text: Column) -> Column:
    """The text without quoted lines; a text without quotation stays as it is."""
    own = F.filter(_lines(text), lambda x: ~x.rlike(QUOTED))
    return F.when(text.rlike(r"(?m)" + QUOTED), F.trim(F.array_join(own, "\n"))).otherwise(text)


def quotations(messages: DataFrame) -> DataFrame:
    """conv_id, turn, level, whole, size, key: the passages that messages quote, and each of their lines."""
    marked = messages.filter(F.col("text").rlike(r"(?m)" + QUOTED)).select("conv_id", "turn", "m", F.posexplode(_lines(F.col("text"))).alias("n", "line"))
    marks = F.regexp_extract("line", r"^((?:[ \t]*>)*)", 1)
    read = marked.select("conv_id", "turn", "m", "n", F.char_length(F.regexp_replace(marks, "[^>]", "")).alias("level"), F.expr("substring(line, char_length(regexp_extract(line, '^((?:[ \\\\t]*>)*)', 1)) + 1)").alias("body"))
    message = Window.partitionBy("conv_id", "turn", "m").orderBy("n")
    change = read.withColumn("new", F.when(F.lag("level").over(message).eqNullSafe(F.col("level")), 0).otherwise(1))
    numbered = change.withColumn("run", F.sum("new").over(message)).filter("level > 0")
    passage = numbered.groupBy("conv_id", "turn", "m", "run", "level").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("n", "body"))), lambda x: x["body"]), "\n").alias("body"))
    both = passage.select("conv_id", "turn", "level", F.lit(0).alias("whole"), "body").union(numbered.select("conv_id", "turn", "level", F.lit(1).alias("whole"), "body"))
    sized = both.withColumn("size", F.char_length(_normal(F.col("body")))).filter("size > 0")
    return sized.select("conv_id", "turn", "level", "whole", "size", _key(F.col("body")).alias("key")).distinct()


def links(messages: DataFrame, scratch: Scratch) -> DataFrame:
    """conv_id, turn, quoted: for each message whose quotation is found, the turn it comes from."""
    quoted = scratch.keep(quotations(messages), "quotations")
    told = messages.join(quoted.select("conv_id").distinct(), "conv_id", "left_semi").select("conv_id", "turn", unquoted(F.col("text")).alias("own"))
    parts = F.explode(F.array_distinct(F.concat(F.array("own"), _lines(F.col("own")))))
    said = told.select("conv_id", "turn", parts.alias("part")).filter(F.char_length(_normal(F.col("part"))) > 0).select("conv_id", "turn", _key(F.col("part")).alias("key")).distinct()
    # As of: one pass over the sayings and quotations of a key, so a saying repeated often costs no product.
    none = F.lit(None)
    events = said.select("conv_id", "key", "turn", F.col("turn").alias("said"), none.cast("int").alias("level"), none.cast("int").alias("whole"), none.cast("int").alias("size")).unionByName(
        quoted.select("conv_id", "key", "turn", none.cast("long").alias("said"), "level", "whole", "size")
    )
    # Spans of turns are ordered by themselves, and the latest saying before a span is carried into it.
    events = events.withColumn("span", _span("turn"))
    spans = events.groupBy("conv_id", "key", "span").agg(F.max("said").alias("last"))
    before = Window.partitionBy("conv_id", "key").orderBy("span").rowsBetween(Window.unboundedPreceding, -1)
    carried = spans.select("conv_id", "key", "span", F.max("last").over(before).alias("carried"))
    past = Window.partitionBy("conv_id", "key", "span").orderBy("turn").rangeBetween(Window.unboundedPreceding, -1)
    inner = events.withColumn("inner", F.max("said").over(past)).filter("level IS NOT NULL").join(carried, ["conv_id", "key", "span"])
    found = inner.withColumn("quoted", F.coalesce("inner", "carried")).filter("quoted IS NOT NULL")
    rank = F.struct(F.col("level"), F.col("whole"), -F.col("size"), -F.col("quoted"))
    return found.groupBy("conv_id", "turn").agg(F.min_by("quoted", rank).alias("quoted"))


def _span(column: str) -> Column:
    """Number of the span of SPAN turns that a turn is in."""
    return F.expr(f"{column} div {SPAN} - IF({column} % {SPAN} < 0, 1, 0)")


def _previous(messages: DataFrame) -> DataFrame:
    """conv_id, turn, previous: the turn before, by spans of turns."""
    turns = messages.filter("turn IS NOT NULL").select("conv_id", "turn", _span("turn").alias("span")).distinct()
    spans = turns.groupBy("conv_id", "span").agg(F.max("turn").alias("last"))
    before = spans.select("conv_id", "span", F.lag("last").over(Window.partitionBy("conv_id").orderBy("span")).alias("carried"))
    inner = F.lag("turn").over(Window.partitionBy("conv_id", "span").orderBy("turn"))
    return turns.withColumn("inner", inner).join(before, ["conv_id", "span"]).select("conv_id", "turn", F.coalesce("inner", "carried").alias("previous"))


def _heads(linked: DataFrame, scratch: Scratch) -> DataFrame:
    """conv_id, turn, head: the message at the start of each chain of quotations, by pointer jumping."""
    head = scratch.keep(linked.select("conv_id", "turn", F.col("quoted").alias("head")), "heads")
    while True:
        up = head.select("conv_id", F.col("turn").alias("head"), F.col("head").alias("above"))
        longer = head.join(up, ["conv_id", "head"], "left")
        if longer.filter("above IS NOT NULL").isEmpty():
            return head
        head = scratch.keep(longer.select("conv_id", "turn", F.coalesce("above", "head").alias("head")), "heads")


def _positions(told: DataFrame) -> DataFrame:
    """The rows with their position in the conversation, by head, turn and content; counts of spans of heads, and of
    turns under one head, are summed up first, so no conversation is put in order by one task."""
    keyed = told.withColumns({"far": _span("head"), "near": _span("turn")})
    sizes = keyed.filter("head IS NOT NULL").groupBy("conv_id", "far", "head", "near").agg(F.count(F.lit(1)).alias("n"))
    coarse = sizes.groupBy("conv_id", "far").agg(F.sum("n").alias("n"))
    up_to = lambda *keys: F.coalesce(F.sum("n").over(Window.partitionBy(*keys[:-1]).orderBy(*keys[-1]).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    coarse = coarse.select("conv_id", "far", up_to("conv_id", ["far"]).alias("earlier"))
    fine = sizes.select("conv_id", "far", "head", "near", up_to("conv_id", "far", ["head", "near"]).alias("before"))
    offsets = fine.join(coarse, ["conv_id", "far"]).select("conv_id", "head", "near", (F.col("earlier") + F.col("before")).alias("offset"))
    own = F.row_number().over(Window.partitionBy("conv_id", "head", "near").orderBy("turn", "role", "content"))
    return keyed.withColumn("own", own).join(offsets, ["conv_id", "head", "near"], "left").withColumn("position", F.col("offset") + F.col("own") - 1)


def transcripts(chat: DataFrame, messages: int = 1024) -> DataFrame:
    """conv_id, block, text: conversations in reply order, quotations left out, in blocks of so many messages."""
    placed = chat.filter("position IS NOT NULL").select("conv_id", F.call_function("div", "position", F.lit(messages)).alias("block"), "position", "rendered")
    rows = F.array_sort(F.collect_list(F.struct("position", "rendered")))  # at most so many messages
    return placed.groupBy("conv_id", "block").agg(F.array_join(F.transform(rows, lambda r: r["rendered"]), "").alias("text"))


def format_chat(messages: DataFrame, *, scratch: Scratch | None = None) -> DataFrame:
    """conv_id, turn, role, reply_to, quotes, head, position, content, rendered for every message.

    ``quotes`` tells whether a quotation was found in an earlier turn, ``position`` is the place in the conversation put in
    reply order (see transcripts), ``content`` the text without quoted lines and ``rendered`` the message in chat markup.
    A null text is empty, a null role is "unknown"; texts of any length are read whole. A message without turn or
    conversation has no reply, head or position; messages of one turn share reply and head, and are ordered by role and
    content; repeated rows stay. Other columns are not read, an empty table gives an empty result.
    """
    scratch = scratch or Scratch(messages.sparkSession)
    base = messages.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text")
    ).withColumn("m", F.xxhash64("role", "text"))
    placed = base.filter("conv_id IS NOT NULL AND turn IS NOT NULL")
    linked = scratch.keep(links(placed, scratch), "links")
    told = base.join(_previous(placed), ["conv_id", "turn"], "left").join(linked, ["conv_id", "turn"], "left").join(_heads(linked, scratch), ["conv_id", "turn"], "left")
    content = unquoted(F.col("text"))
    rendered = F.concat(F.lit("<|"), "role", F.lit("|>\n"), content, F.lit("\n<|end|>\n"))
    placed_row = F.col("conv_id").isNotNull() & F.col("turn").isNotNull()
    rows = told.select(
        "conv_id", "turn", "role", F.coalesce("quoted", "previous").alias("reply_to"), F.col("quoted").isNotNull().alias("quotes"),
        F.when(placed_row, F.coalesce("head", "turn")).alias("head"), content.alias("content"), rendered.alias("rendered"),
    )
    return _positions(rows).select("conv_id", "turn", "role", "reply_to", "quotes", "head", "position", "content", "rendered")


def op9_chat_format(spark, sf_dir: str) -> DataFrame:
    return format_chat(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


OP9_SQL = r"""
WITH RECURSIVE base AS (
  SELECT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text, row_number() OVER () AS m FROM conversations),
lines AS (
  SELECT conv_id, turn, m, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS n FROM base),
own AS (
  SELECT b.conv_id, b.turn, b.role, b.m, CASE WHEN bool_or(regexp_matches(line, '^[ \t]*>'))
    THEN trim(coalesce(string_agg(line, chr(10) ORDER BY n) FILTER (NOT regexp_matches(line, '^[ \t]*>')), '')) ELSE any_value(b.text) END AS content
  FROM base b JOIN lines l ON l.m = b.m GROUP BY ALL),
read AS (
  SELECT conv_id, turn, m, n, length(regexp_replace(regexp_extract(line, '^((?:[ \t]*>)*)', 1), '[^>]', '', 'g')) AS level,
    substr(line, length(regexp_extract(line, '^((?:[ \t]*>)*)', 1)) + 1) AS body FROM lines),
runs AS (
  SELECT *, n - row_number() OVER (PARTITION BY m, level ORDER BY n) AS run FROM read),
quoted AS (
  SELECT conv_id, turn, level, 0 AS whole, string_agg(body, chr(10) ORDER BY n) AS body FROM runs WHERE level > 0 GROUP BY conv_id, turn, m, level, run
  UNION ALL SELECT conv_id, turn, level, 1, body FROM runs WHERE level > 0),
qkeys AS (SELECT conv_id, turn, level, whole, lower(trim(regexp_replace(body, '[ \t\n\r\f]+', ' ', 'g'))) AS k FROM quoted),
said AS (
  SELECT conv_id, turn, content AS part FROM own UNION ALL SELECT conv_id, turn, unnest(string_split(content, chr(10))) FROM own),
skeys AS (
  SELECT conv_id, turn, lower(trim(regexp_replace(part, '[ \t\n\r\f]+', ' ', 'g'))) AS k FROM said
  WHERE conv_id IN (SELECT conv_id FROM quoted)),
found AS (
  SELECT q.conv_id, q.turn, q.level, q.whole, length(q.k) AS size, max(s.turn) AS quoted FROM qkeys q JOIN skeys s ON s.conv_id = q.conv_id AND s.k = q.k AND s.turn < q.turn
  WHERE q.k <> '' GROUP BY ALL),
linked AS (
  SELECT conv_id, turn, quoted FROM (SELECT *, row_number() OVER (PARTITION BY conv_id, turn ORDER BY level, whole, size DESC, quoted DESC) AS r FROM found) WHERE r = 1),
climb AS (
  SELECT conv_id, turn, quoted AS head FROM linked UNION ALL SELECT c.conv_id, c.turn, l.quoted FROM climb c JOIN linked l ON l.conv_id = c.conv_id AND l.turn = c.head),
heads AS (SELECT conv_id, turn, min(head) AS head FROM climb GROUP BY ALL),
previous AS (
  SELECT conv_id, turn, lag(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS previous FROM (SELECT DISTINCT conv_id, turn FROM base))
SELECT o.conv_id, o.turn, o.role, coalesce(l.quoted, p.previous) AS reply_to, l.quoted IS NOT NULL AS quotes, coalesce(h.head, o.turn) AS head,
  row_number() OVER (PARTITION BY o.conv_id ORDER BY coalesce(h.head, o.turn), o.turn, o.role, o.content) - 1 AS position, o.content,
  '<|' || o.role || '|>' || chr(10) || o.content || chr(10) || '<|end|>' || chr(10) AS rendered
FROM own o LEFT JOIN linked l USING (conv_id, turn) LEFT JOIN heads h USING (conv_id, turn) LEFT JOIN previous p USING (conv_id, turn)
"""
