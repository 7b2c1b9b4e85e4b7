"""Chat formatting from event logs, in DataFrame functions only.

A log row is an event of a message in a conversation.  Kinds:

* ``message``: the message's whole text so far;
* ``delta``: text streamed onto its end;
* ``edit``: new text in place of all before;
* ``regenerate``: what was streamed so far is void, deltas start anew.

The log is partitioned by conversation and sorted by sequence; a message's text
is the text of its last edit, message or regeneration and of the deltas after it.
Messages stand in the order of their first event.  One shuffle deals out the log,
the folds of messages and of conversations both run inside it.  A formatted
conversation is one value of one row, so one conversation must fit a row; nothing
smaller than that is collected.

Template: an assistant turn is ``<s>role\\ntext</s>``, any other turn
``[INST]role\\ntext[/INST]``; the loss mask is the text of the turns in ``<s>``.
Inside roles and texts a control string gets a backslash before its last
character, one more where it has some already, so reading removes exactly one.

Defined results: null role or text is empty; an empty table gives no rows; rows
of a null conversation are one conversation; events of equal sequence stand in
the order of role, then text; repeated table rows are turns of their own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphviews.llm.common import table

#: What opens and closes turns.
OPEN_LOSS, CLOSE_LOSS, OPEN, CLOSE = "<s>", "</s>", "[INST]", "[/INST]"
CONTROL = r"(</?s|\[/?INST)(\\*)([>\]])"
ESCAPED = r"(</?s|\[/?INST)(\\*)\\([>\]])"
LOSS_ROLE = "assistant"


def escaped(text: Column) -> Column:
    return F.regexp_replace(text, CONTROL, r"$1$2\\$3")


def unescaped(text: Column) -> Column:
    return F.regexp_replace(text, ESCAPED, "$1$2$3")


def _role_in(role: Column) -> Column:
    """A role on one line: backslashes and line ends become two characters."""
    return escaped(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def _role_out(role: Column) -> Column:
    # a pair of backslashes is one, between pairs a backslash and n are a line end
    between = F.split(unescaped(role), r"\\\\", -1)
    return F.array_join(F.transform(between, lambda x: F.replace(x, F.lit("\\n"), F.lit("\n"))), "\\")


def fold_messages(events: DataFrame) -> DataFrame:
    """Final messages of a log (conv_id, seq, message, kind, role, text): conv_id, seq, message, role, text."""
    by_seq = F.array_sort(F.collect_list(F.struct("seq", "role", "text", "kind")))
    groups = events.repartition("conv_id").groupBy("conv_id", "message").agg(by_seq.alias("log"))
    resets = F.transform("log", lambda e, i: F.when(e["kind"] != "delta", i + 1))
    last = F.greatest(F.array_max(resets), F.lit(1))
    said = F.transform(
        F.slice("log", F.col("last"), F.size("log")),
        lambda e: F.when(e["kind"] == "regenerate", F.lit("")).otherwise(F.coalesce(e["text"], F.lit(""))),
    )
    return groups.withColumn("last", F.coalesce(last, F.lit(1))).select(
        "conv_id",
        F.col("log")[0]["seq"].alias("seq"),
        "message",
        F.coalesce(F.get(F.filter(F.transform("log", lambda e: e["role"]), lambda r: r.isNotNull()), 0), F.lit("")).alias("role"),
        F.array_join(said, "").alias("text"),
    )


def render(messages: DataFrame) -> DataFrame:
    """One formatted text per conversation."""
    role, text = _role_in(F.col("role")), escaped(F.col("text"))
    turn = F.when(F.col("role") == LOSS_ROLE, F.concat(F.lit(OPEN_LOSS), role, F.lit("\n"), text, F.lit(CLOSE_LOSS))).otherwise(
        F.concat(F.lit(OPEN), role, F.lit("\n"), text, F.lit(CLOSE))
    )
    turns = messages.select("conv_id", F.struct("seq", "message", turn.alias("turn")).alias("t"))
    return turns.groupBy("conv_id").agg(
        F.array_join(F.transform(F.array_sort(F.collect_list("t")), lambda t: t["turn"]), "").alias("formatted")
    )


def parse(formatted: DataFrame) -> DataFrame:
    """formatted with turns: array of (role, text, loss), read from the text alone."""
    def turn(piece):
        loss = F.startswith(piece, F.lit(OPEN_LOSS))
        head = F.when(loss, len(OPEN_LOSS)).otherwise(len(OPEN))
        tail = F.when(loss, len(CLOSE_LOSS)).otherwise(len(CLOSE))
        body = F.substring(piece, head + 1, F.length(piece) - head - tail)
        role = F.substring_index(body, "\n", 1)
        text = F.substring(body, F.length(role) + 2, F.length(body))
        return F.struct(_role_out(role).alias("role"), unescaped(text).alias("text"), loss.alias("loss"))

    pieces = F.split("formatted", r"(?=<s>|\[INST\])")
    return formatted.withColumn("turns", F.transform(F.filter(pieces, lambda p: p != ""), turn))


def digests(parsed: DataFrame) -> DataFrame:
    """Counts and digests of what was read back."""
    whole = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    masked = F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), "")
    return parsed.withColumn("masked", masked).select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(whole, 256).alias("turns_sha256"),
        F.length("masked").cast("long").alias("loss_chars"),
        F.sha2("masked", 256).alias("loss_sha256"),
        F.length("formatted").cast("long").alias("formatted_chars"),
    )


def log_of_rows(rows: DataFrame) -> DataFrame:
    """Rows (conv_id, turn, role, text) as the log that a chat service would have written of them.

    An answer was begun, regenerated, and then streamed in two deltas; any other turn was
    sent half written and then edited.  Each row is a message of its own.
    """
    order = Window.partitionBy("conv_id").orderBy("turn", "role", "text")
    half = F.floor(F.length("text") / 2).cast("int")
    begun, rest = F.substring(F.col("text"), F.lit(1), half), F.substring(F.col("text"), half + 1, F.length("text"))

    def event(kind: str, text: Column) -> Column:
        return F.struct(F.lit(kind).alias("kind"), text.alias("text"))

    answer = F.array(event("delta", begun), event("regenerate", F.lit(None).cast("string")), event("delta", begun), event("delta", rest))
    other = F.array(event("message", begun), event("edit", F.col("text")))
    return (
        rows.select("conv_id", F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
        .repartition("conv_id")
        .withColumn("message", F.row_number().over(order).cast("long"))
        .select("conv_id", "message", "role", F.posexplode(F.when(F.col("role") == LOSS_ROLE, answer).otherwise(other)).alias("at", "event"))
        .select("conv_id", (F.col("message") * 4 + F.col("at")).alias("seq"), "message", "event.kind", "role", "event.text")
    )


def op6_chat_format(spark, sf_dir):
    probe = spark.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise(LOSS_ROLE).alias("role"),
        F.lit("</s>[INST] ok [/INST]").alias("text"),
    )
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(probe)
    return digests(parse(render(fold_messages(log_of_rows(rows)))))


OP6_SQL = r"""
WITH r AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (SELECT *, regexp_replace(text, '(</?s|\[/?INST)(\\*)([>\]])', '\1\2\\\3', 'g') AS safe FROM r)
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (role = 'assistant'), '')) AS loss_sha256,
  sum(length(role) + 1 + length(safe) + CASE WHEN role = 'assistant' THEN 7 ELSE 13 END)::BIGINT AS formatted_chars
FROM e GROUP BY conv_id
"""
