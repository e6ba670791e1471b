"""Chat formatting whose text a deterministic parser turns back into the same turns; DataFrame operations only."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_of

#: The grammar's strings.  A conversation is a header line and turns; a turn is
#: ``<s>[TAG] text [/TAG]</s>`` and a line end; other roles than these three are ``<s>[ROLE name] text [/ROLE]</s>``.
HEAD_PLAIN, HEAD_ESCAPED = "#chat plain\n", "#chat escaped\n"
TAGS = {"user": "INST", "assistant": "ANS", "system": "SYS"}
END = "</s>\n"
ESCAPE = "␛"
CONTROL = ("<s>", "</s>", "[INST]", "[/INST]", "[ANS]", "[/ANS]", "[SYS]", "[/SYS]", "[ROLE", "[/ROLE]", "#chat ")
CODES = "123456789ab"


def escaped(text: Column) -> Column:
    """Control strings become the escape sign and a code; the sign itself comes first and gets code 0.

    Every sign is then followed by its code, and no control string holds the sign or can arise beside it.
    """
    out = F.replace(text, F.lit(ESCAPE), F.lit(ESCAPE + "0"))
    return reduce(lambda t, p: F.replace(t, F.lit(p[0]), F.lit(ESCAPE + p[1])), zip(CONTROL, CODES), out)


def unescaped(text: Column) -> Column:
    out = reduce(lambda t, p: F.replace(t, F.lit(ESCAPE + p[1]), F.lit(p[0])), zip(CONTROL, CODES), text)
    return F.replace(out, F.lit(ESCAPE + "0"), F.lit(ESCAPE))


def _tag(role: Column, escape: bool) -> Column:
    named = F.replace(escaped(role), F.lit("]"), F.lit(ESCAPE + "c")) if escape else role
    return reduce(lambda t, p: t.when(role == p[0], F.lit(p[1])), TAGS.items(), F.when(F.lit(False), F.lit(""))).otherwise(F.concat(F.lit("ROLE "), named))


def parsed(formatted: Column) -> Column:
    """The turns of a formatted conversation; the grammar alone decides, the source is not seen."""
    escape = formatted.startswith(F.lit(HEAD_ESCAPED))
    body = F.when(escape, F.substring(formatted, len(HEAD_ESCAPED) + 1, 2**31 - 1)).otherwise(F.substring(formatted, len(HEAD_PLAIN) + 1, 2**31 - 1))
    # every turn ends with END, so the last piece is empty
    pieces = F.filter(F.split(body, END), lambda p: p != "")

    def one(p: Column) -> Column:
        cut = F.locate("] ", p)
        tag = F.substring(p, F.lit(5), cut - F.lit(5))
        kind = F.substring_index(tag, " ", 1)
        text = F.substring(p, cut + F.lit(2), F.length(p) - cut - F.lit(1) - F.length(kind) - F.lit(4))
        name = F.substring(tag, F.lit(6), F.length(tag))
        other = F.when(escape, unescaped(F.replace(name, F.lit(ESCAPE + "c"), F.lit("]")))).otherwise(name)
        role = reduce(lambda t, q: t.when(kind == q[1], F.lit(q[0])), TAGS.items(), F.when(F.lit(False), F.lit(""))).otherwise(other)
        return F.struct(role.alias("role"), F.when(escape, unescaped(text)).otherwise(text).alias("text"))

    return F.transform(pieces, one)


def format_chats(rows: DataFrame, id_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """One row per conversation: ``conv_id, formatted, recovered, turns, loss_mask``.

    turns has, for each turn, where its piece begins in ``formatted`` (``start``), where the text in it begins and
    how long that is (``text_start, text_length``) and whether it is learnt from (``loss``: the
    assistant's); loss_mask is the spans of the learnt ones, ``start, length``.  Places are code points from 0.

    Turns are ordered by turn (null first), then role and text; null texts and roles are empty.  A
    conversation is escaped if one of its texts or roles holds a control string, or a role a bracket, and plain if not;
    the parser, which sees the output alone, must give the turns back, or the query fails.  A null
    id is a conversation; repeated rows are turns; empty tables give empty tables; other columns are
    ignored.  One shuffle by conversation; a conversation is one row, so it must fit one executor.
    """
    role = F.coalesce(F.col(role_col).cast("string"), F.lit(""))
    turns = rows.select(F.col(id_col).cast("bigint").alias("conv_id"), F.col(turn_col).cast("bigint").alias("turn"), role.alias("role"), text_of(text_col).alias("text"))
    held = reduce(Column.__or__, (F.contains(F.col(c), F.lit(s)) for c in ("role", "text") for s in (ESCAPE, *CONTROL)), F.contains("role", F.lit("]")))
    same = Window.partitionBy("conv_id")
    before = same.orderBy(F.col("turn").asc_nulls_first(), "role", "text").rowsBetween(Window.unboundedPreceding, -1)
    t = turns.withColumn("escape", F.max(held).over(same))
    t = t.withColumn("tag", F.when(F.col("escape"), _tag(F.col("role"), True)).otherwise(_tag(F.col("role"), False)))
    t = t.withColumn("shown", F.when(F.col("escape"), escaped(F.col("text"))).otherwise(F.col("text")))
    t = t.withColumn("open", F.concat(F.lit("<s>["), "tag", F.lit("] "))).withColumn("piece", F.concat("open", "shown", F.lit(" [/"), F.substring_index("tag", " ", 1), F.lit("]" + END)))
    head = F.when(F.col("escape"), F.lit(HEAD_ESCAPED)).otherwise(F.lit(HEAD_PLAIN))
    t = t.withColumn("start", F.length(head) + F.coalesce(F.sum(F.length("piece")).over(before), F.lit(0)))
    kept = F.struct("start", (F.col("start") + F.length("open")).alias("text_start"), F.length("shown").cast("bigint").alias("text_length"), (F.col("role") == "assistant").alias("loss"), "role", "text", "piece")
    one = t.groupBy("conv_id").agg(F.sort_array(F.collect_list(kept)).alias("_all"), F.max(head).alias("_head"))
    one = one.select("conv_id", "_all", F.concat("_head", F.array_join(F.col("_all.piece"), "")).alias("formatted"))
    one = one.withColumn("recovered", parsed(F.col("formatted")))
    source = F.transform("_all", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text")))
    wrong = F.raise_error(F.concat(F.lit("chat does not read back: "), F.col("conv_id").cast("string")))
    checked = F.when(F.col("recovered") == source, F.col("recovered")).otherwise(F.when(wrong.isNull(), F.col("recovered")))
    places = F.transform("_all", lambda t: F.struct(*(t[c].alias(c) for c in ("start", "text_start", "text_length", "loss"))))
    mask = F.transform(F.filter("_all", lambda t: t["loss"]), lambda t: F.struct(t["text_start"].alias("start"), t["text_length"].alias("length")))
    return one.select("conv_id", "formatted", checked.alias("recovered"), places.alias("turns"), mask.alias("loss_mask"))


def masked_text(formatted: Column, turns: Column) -> Column:
    """The text of ``formatted`` under the loss mask, as the model is to say it.

    Characters are read at the mask's places in the output; the source and the parser's turns are not looked at.
    The output is cut at the turns' ends once, so that reading all spans takes one pass.
    """
    escape = formatted.startswith(F.lit(HEAD_ESCAPED))
    body = F.substr(formatted, F.when(escape, F.lit(len(HEAD_ESCAPED) + 1)).otherwise(F.lit(len(HEAD_PLAIN) + 1)))
    here = lambda p, t: F.when(t["loss"], F.substr(p, (t["text_start"] - t["start"] + F.lit(1)).cast("int"), t["text_length"].cast("int"))).otherwise(F.lit(""))
    said = F.zip_with(F.slice(F.split(body, END), F.lit(1), F.size(turns)), turns, here)
    return F.when(escape, F.array_join(F.transform(said, unescaped), "")).otherwise(F.array_join(said, ""))


def chat_digests(chats: DataFrame) -> DataFrame:
    """What reads back from :func:`format_chats`: turns, their digest, and all text under the loss mask.

    ``conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars``.  Conversations without an
    assistant's turn have 0 loss_chars and the digest of nothing; a null conv_id stays null; repeated
    conversations give repeated rows; an empty table gives an empty table.
    """
    both = F.array_join(F.transform("recovered", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    read = chats.select("conv_id", "formatted", F.size("recovered").cast("bigint").alias("n_turns"), both.alias("_both"), masked_text(F.col("formatted"), F.col("turns")).alias("_loss"))
    return read.select(
        "conv_id",
        "n_turns",
        F.sha2(F.col("_both").cast("binary"), 256).alias("turns_sha256"),
        F.length("_loss").cast("bigint").alias("loss_chars"),
        F.sha2(F.col("_loss").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )
