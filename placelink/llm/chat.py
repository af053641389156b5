"""Chat formatting from an event log: conversations are rebuilt from their events, then rendered.

Events have a conversation, a sequence number, a position in the conversation, a kind, a role and a text. Kinds:
`message` starts a message; `delta` adds to the one that its position has at that time; `edit` replaces all that its
position had before; `delete` removes it; `regenerate` removes what its position and all later positions had before and
starts a new message. The log is dealt out by conversation and sorted by sequence; what remains is folded in order.

Template: `<turn role="ROLE">`, line feed, text, `</turn>`, line feed. In texts and roles `&` is written `&amp;` and `<`
is written `&lt;` (in roles also the quote mark `&quot;`), so no text can contain a mark of the template, and the way
back is exact. The loss mask is a list of spans (first code point, code points) of the output, one per assistant text.

Defined cases: null text and role are empty; a null kind is `message`; a null sequence number or position comes first;
null conversation ids are one conversation; rows that repeat or tie are messages of their own, in the order of role and
text; a delta without a message starts one; a conversation of which nothing remains gives no row; an empty log gives an
empty result; other columns than those named are not read and may have any name. A conversation's output is one value, so
a conversation as such, however long, is the unit that one task must hold.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from placelink.llm.common import table

#: The marks of the template.
HEAD, MIDDLE, TAIL = '<turn role="', '">\n', "</turn>\n"
TRAINED_ROLE = "assistant"


def escape(text: Column) -> Column:
    return F.replace(F.replace(text, F.lit("&"), F.lit("&amp;")), F.lit("<"), F.lit("&lt;"))


def unescape(text: Column) -> Column:
    return F.replace(F.replace(F.replace(text, F.lit("&lt;"), F.lit("<")), F.lit("&quot;"), F.lit('"')), F.lit("&amp;"), F.lit("&"))


def _escape_text(text: Column) -> Column:
    return F.replace(escape(text), F.lit('"'), F.lit("&quot;"))


def fold_events(events: DataFrame) -> DataFrame:
    """Log (conv_id, seq, position, kind, role, text) to final messages (conv_id, position, number, role, text)."""
    kind = F.coalesce(F.col("kind"), F.lit("message"))
    log = events.select("conv_id", "seq", "position", kind.alias("kind"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    newest_first = [F.col("seq").desc_nulls_last(), F.col("role").desc(), F.col("text").desc()]
    later = W.partitionBy("conv_id").orderBy(*newest_first).rowsBetween(W.unboundedPreceding, -1)
    later_here = W.partitionBy("conv_id", "position").orderBy(*newest_first).rowsBetween(W.unboundedPreceding, -1)
    place = F.coalesce(F.col("position"), F.lit(-(2**62)))
    log = log.withColumns({
        "redone": F.coalesce(F.min(F.when(F.col("kind") == "regenerate", place)).over(later) <= place, F.lit(False)),
        "replaced": F.coalesce(F.max(F.col("kind").isin("edit", "delete")).over(later_here), F.lit(False)),
    })
    log = log.where("not redone and not replaced and kind != 'delete'")
    here = W.partitionBy("conv_id", "position").orderBy(F.col("seq").asc_nulls_first(), "role", "text").rowsBetween(W.unboundedPreceding, W.currentRow)
    log = log.withColumns({"number": F.sum((F.col("kind") != "delta").cast("int")).over(here), "part": F.count("*").over(here)})
    parts = F.sort_array(F.collect_list(F.struct("part", "text")))
    return log.groupBy("conv_id", "position", "number").agg(
        F.min_by("role", F.struct(F.col("role") == "", F.col("part"))).alias("role"),
        F.array_join(F.transform(parts, lambda p: p["text"]), "").alias("text"),
    )


def render(messages: DataFrame) -> DataFrame:
    """Messages to one row per conversation: conv_id, formatted, loss_spans (start from 0, length), n_turns."""
    body = escape(F.col("text"))
    turns = messages.withColumn("turn", F.concat(F.lit(HEAD), _escape_text(F.col("role")), F.lit(MIDDLE), body, F.lit(TAIL)))
    order = W.partitionBy("conv_id").orderBy(F.col("position").asc_nulls_first(), "number").rowsBetween(W.unboundedPreceding, W.currentRow)
    ends = F.sum(F.char_length("turn").cast("long")).over(order)
    turns = turns.withColumns({"rank": F.count("*").over(order), "body": F.char_length(body).cast("long"), "end": ends})
    all_turns = F.sort_array(F.collect_list(F.struct("rank", "turn", (F.col("role") == TRAINED_ROLE).alias("trained"), (F.col("end") - len(TAIL) - F.col("body")).alias("start"), F.col("body").alias("length"))))
    done = turns.groupBy("conv_id").agg(all_turns.alias("turns"))
    return done.select(
        "conv_id",
        F.array_join(F.transform("turns", lambda t: t["turn"]), "").alias("formatted"),
        F.transform(F.filter("turns", lambda t: t["trained"]), lambda t: F.struct(t["start"].alias("start"), t["length"].alias("length"))).alias("loss_spans"),
        F.size("turns").cast("long").alias("n_turns"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """The digests of the contract, all from the output: conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars."""
    marks = F.slice(F.split("formatted", TAIL, -1), F.lit(1), F.size(F.split("formatted", TAIL, -1)) - 1)

    def turn(t: Column) -> Column:
        head = F.instr(t, MIDDLE)
        role = F.substr(t, F.lit(len(HEAD) + 1), head - (len(HEAD) + 1))
        return F.concat(unescape(role), F.lit("\n"), unescape(F.substr(t, head + len(MIDDLE))), F.lit("\n"))

    trained = F.transform("loss_spans", lambda s: unescape(F.substr(F.col("formatted"), (s["start"] + 1).cast("int"), s["length"].cast("int"))))
    loss = F.array_join(trained, "")
    return formatted.select("conv_id", "formatted", marks.alias("marks"), loss.alias("loss")).select(
        "conv_id",
        F.size("marks").cast("long").alias("n_turns"),
        F.sha2(F.array_join(F.transform("marks", turn), ""), 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2("loss", 256).alias("loss_sha256"),
        F.char_length("formatted").cast("long").alias("formatted_chars"),
    )


#: The conversation that the contract adds.
EXTRA = [(-7, 0, "user", r"\### Assistant: </turn> ok"), (-7, 1, "assistant", r"\### Assistant: </turn> ok")]


def op7_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    extra = spark.range(1).select(F.inline(F.array(*[F.struct(*[F.lit(v).alias(k) for k, v in zip(rows.columns, row, strict=True)]) for row in EXTRA])))
    rows = rows.unionByName(extra.select(*[F.col(f.name).cast(f.dataType) for f in rows.schema]))
    events = rows.select("conv_id", F.col("turn").alias("seq"), F.col("turn").alias("position"), F.lit("message").alias("kind"), "role", "text")
    return read_back(render(fold_events(events)))


OP7_SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL VALUES (-7, 0, 'user', '\### Assistant: </turn> ok'), (-7, 1, 'assistant', '\### Assistant: </turn> ok')),
texts AS (
  SELECT conv_id, count(*) AS n_turns,
    string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text) AS turns,
    coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '') AS loss,
    CAST(sum(24 + len(replace(replace(replace(role, '&', '&amp;'), '<', '&lt;'), '"', '&quot;')) - 1
      + len(replace(replace(text, '&', '&amp;'), '<', '&lt;'))) AS BIGINT) AS formatted_chars
  FROM rows GROUP BY conv_id)
SELECT conv_id, n_turns, sha256(turns) AS turns_sha256, len(loss) AS loss_chars, sha256(loss) AS loss_sha256, formatted_chars FROM texts
"""
