"""Chat formatting [native]: conversations rebuilt from their event log, then rendered.

An event log has the columns conv_id, seq, turn, kind, role, text. Partitioned by
conversation and sorted by seq it folds into final messages:

* `message` starts a message in its turn;
* `delta` appends its text to the message its turn has at that point (streaming);
* `edit` replaces that message's text;
* `regenerate` empties it, for deltas to fill again;
* an edit or regeneration also takes back every message of a later turn that was last
  started before it: that continuation answered a text that no longer exists.

The rendered conversation marks each turn, `<s>role\\ntext\\n</s>` for the assistant
and `[INST]role\\ntext\\n[/INST]` for all others. A control string inside a text or role gets
one backslash more before it than it had, which the reader takes away again; so
an unescaped control string is always a mark of the template.

DataFrame and SQL functions only. The fold groups by turn before it groups by
conversation; a conversation is one string, so its text meets in one row at the end.

Defined results: null texts and roles are empty ones; a delta, edit or
regeneration before any message starts one; events of equal seq are ordered by kind (message
first), role and text; repeated rows are separate messages; a null turn comes before
all others, and null conv_ids form one conversation; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from rankjoin.llm.common import table

#: The control strings, as a regular expression for Java.
CONTROL = r"</?s>|\[/?INST\]"
_ESCAPE = rf"(?<!\\)(\\*+)({CONTROL})"
_UNESCAPE = rf"(?<!\\)\\(\\*+)({CONTROL})"
_TURN = r"(?<!\\)(?=<s>|\[INST\])"
RESETS = ("edit", "regenerate")


def escape(text: Column) -> Column:
    return F.regexp_replace(text, _ESCAPE, r"\\$1$2")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, _UNESCAPE, "$1$2")


def _escape_role(role: Column) -> Column:
    return escape(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def _unescape_role(role: Column) -> Column:
    held = F.replace(unescape(role), F.lit("\\\\"), F.lit("\\0"))
    return F.replace(F.replace(held, F.lit("\\n"), F.lit("\n")), F.lit("\\0"), F.lit("\\"))


def turns_as_events(conversations: DataFrame) -> DataFrame:
    """A plain table of turns (conv_id, turn, role, text) as an event log."""
    return conversations.select("conv_id", F.col("turn").alias("seq"), "turn", F.lit("message").alias("kind"), "role", "text")


def reconstruct(events: DataFrame) -> DataFrame:
    """Final messages: conv_id, turn, part (number within the turn), role, text."""
    e = events.select("conv_id", "seq", "turn", F.coalesce("kind", F.lit("message")).alias("kind"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    order = [F.col("seq"), F.when(F.col("kind") == "message", 0).when(F.col("kind").isin(*RESETS), 1).otherwise(2), F.col("role"), F.col("text")]
    within = Window.partitionBy("conv_id", "turn").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    e = e.withColumns({
        "part": F.greatest(F.count_if(F.col("kind") == "message").over(within), F.lit(1)),
        "step": F.count_if(F.col("kind") != "delta").over(within),
        "at": F.row_number().over(Window.partitionBy("conv_id", "turn").orderBy(*order)),
    })
    text = F.when(F.col("kind") == "regenerate", "").otherwise(F.col("text"))
    steps = e.groupBy("conv_id", "turn", "part", "step").agg(
        F.sort_array(F.collect_list(F.struct("at", text.alias("text")))).alias("texts"), F.min("seq").alias("begun"), F.min_by("role", "at").alias("role"), F.min("at").alias("first"),
    )
    last = steps.groupBy("conv_id", "turn", "part").agg(F.max_by(F.struct("texts", "begun"), "step").alias("last"), F.min_by("role", "first").alias("role"))
    messages = last.select("conv_id", "turn", "part", "role", F.array_join(F.col("last.texts.text"), "").alias("text"), F.col("last.begun").alias("begun"))
    resets = e.where(F.col("kind").isin(*RESETS)).groupBy(F.col("conv_id").alias("_conv")).agg(F.collect_set(F.struct("turn", "seq")).alias("resets"))
    later = F.exists("resets", lambda r: (r["turn"] < F.col("turn")) & (r["seq"] > F.col("begun")))
    return messages.join(resets, F.col("conv_id").eqNullSafe(F.col("_conv")), "left").where(~F.coalesce(later, F.lit(False))).select("conv_id", "turn", "part", "role", "text")


def render(messages: DataFrame) -> DataFrame:
    """One row per conversation: conv_id, formatted, loss_spans.

    loss_spans: for each assistant text, where it begins in `formatted` and how
    long it is there, in code points.
    """
    own = F.col("role") == "assistant"
    head = F.concat(F.when(own, "<s>").otherwise("[INST]"), _escape_role(F.col("role")), F.lit("\n"))
    m = messages.withColumns({"head": head, "body": escape(F.col("text")), "tail": F.when(own, "\n</s>").otherwise("\n[/INST]")})
    m = m.withColumn("size", (F.length("head") + F.length("body") + F.length("tail")).cast("long"))
    before = F.coalesce(F.sum("size").over(Window.partitionBy("conv_id").orderBy("turn", "part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    m = m.withColumn("start", before + F.length("head"))
    rows = F.sort_array(F.collect_list(F.struct("turn", "part", F.concat("head", "body", "tail").alias("shown"), F.when(own, F.struct("start", F.length("body").cast("long").alias("n"))).alias("span"))))
    out = m.groupBy("conv_id").agg(rows.alias("rows"))
    return out.select("conv_id", F.array_join(F.col("rows.shown"), "").alias("formatted"), F.array_compact(F.col("rows.span")).alias("loss_spans"))


def read_back(formatted: Column) -> Column:
    """The turns of a rendered conversation: array of (role, text, loss)."""

    def turn(x: Column) -> Column:
        loss = x.startswith("<s>")
        inner = F.when(loss, x.substr(F.lit(4), F.length(x) - 8)).otherwise(x.substr(F.lit(7), F.length(x) - 14))
        role = F.substring_index(inner, "\n", 1)
        return F.struct(_unescape_role(role).alias("role"), unescape(inner.substr(F.length(role) + 2, F.length(inner))).alias("text"), loss.alias("loss"))

    return F.transform(F.split(formatted, _TURN), turn)


def op3_chat_format(spark, sf_dir: str) -> DataFrame:
    """All conversations and one made of control strings, rendered and read back."""
    own = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    out = render(reconstruct(turns_as_events(given.unionByName(own))))
    out = out.withColumn("turns", read_back(F.col("formatted")))
    loss = F.array_join(F.transform(F.filter("turns", lambda t: t["loss"]), lambda t: t["text"]), "")
    shown = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return out.select("conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(shown, 256).alias("turns_sha256"), F.length(loss).cast("long").alias("loss_chars"), F.sha2(loss, 256).alias("loss_sha256"), F.length("formatted").cast("long").alias("formatted_chars"))


#: DuckDB: the same digests straight from the table; the template's length is added per turn.
OP3_SQL = r"""
with t as (select conv_id, turn, role, text from conversations union all select -1, 0, 'user', '</s>[INST] ok [/INST]' union all select -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
m as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from t),
s as (select *, length(role) + length(text) + case when role = 'assistant' then 9 else 15 end + len(regexp_extract_all(text, '</?s>|\[/?INST\]')) as n from m)
select conv_id, count(*) as n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  coalesce(sum(length(text)) filter (role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, text) filter (role = 'assistant'), '')) as loss_sha256, sum(n)::bigint as formatted_chars
from s group by conv_id
"""
