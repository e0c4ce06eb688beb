r"""Chat formatting with typed content parts.

A turn's content is a list of parts (text, image, audio, document). A visitor, one renderer and one token counter
for each kind, flattens the parts into one ordered string: text parts as they are, others as a placeholder with the
number of the attachment in its turn; the references and expanded token counts of attachments are recorded beside it.

Template of a turn: <|turn|>role<|text|>content<|end|> and a line feed. A control string inside a text gets one
backslash after its first character, and one that has backslashes there already gets one more, so taking one away
reads the text back whatever it holds.

Defined results: null text is empty, null role is empty, parts of an unknown kind or null parts are skipped; turns
with equal numbers go by role and text; turns without a conv_id are one conversation; other columns are ignored. A conversation is never held as a whole: turns
are formatted where they lie, and digests are taken over sorted rows as they stream by.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, ship, table, whole_id

TURN, TEXT, END = "<|turn|>", "<|text|>", "<|end|>\n"
#: Control strings of this and other common templates: <|...|>, <s>, </s>, [INST], [/INST].
_TAIL = r"(\||/?s>|/?INST\])"
_ESCAPE, _UNESCAPE = r"([<\[])(\\*)" + _TAIL, r"([<\[])\\(\\*)" + _TAIL

PART = "struct<kind:string,text:string,ref:string,width:int,height:int,seconds:double,pages:int>"
#: Image tokens: one for each square of so many pixels; audio tokens a second; document tokens a page.
PATCH, AUDIO_RATE, PAGE_TOKENS = 28, 25, 256


def escape(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), _ESCAPE, r"$1$2\\$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, _UNESCAPE, "$1$2$3")


class PartVisitor:
    """Renders one content part and counts its tokens; subclass it, or add kinds, to change either."""

    kinds = ("text", "image", "audio", "document")

    def render(self, part: Column, number: Column) -> Column:
        out = F.lit("")
        for kind in self.kinds:
            shown = getattr(self, f"render_{kind}", lambda p, n, kind=kind: F.concat(F.lit(f"<|{kind}:"), n.cast("string"), F.lit("|>")))
            out = F.when(part["kind"] == kind, shown(part, number)).otherwise(out)
        return out

    def tokens(self, part: Column) -> Column:
        out = F.lit(0)
        for kind in self.kinds:
            out = F.when(part["kind"] == kind, getattr(self, f"tokens_{kind}")(part)).otherwise(out)
        return out.cast("long")

    def render_text(self, part: Column, number: Column) -> Column:
        return escape(part["text"])

    def tokens_text(self, part: Column) -> Column:
        return F.lit(0)

    def tokens_image(self, part: Column) -> Column:
        side = lambda c: F.ceil(F.coalesce(part[c], F.lit(0)) / PATCH)
        return side("width") * side("height")

    def tokens_audio(self, part: Column) -> Column:
        return F.ceil(F.coalesce(part["seconds"], F.lit(0.0)) * AUDIO_RATE)

    def tokens_document(self, part: Column) -> Column:
        return F.coalesce(part["pages"], F.lit(0)) * PAGE_TOKENS


def text_parts(text: Column) -> Column:
    """The one-part content of a plain text."""
    part = F.named_struct(F.lit("kind"), F.lit("text"), F.lit("text"), F.coalesce(text, F.lit("")), *[x for n, t in (("ref", "string"), ("width", "int"), ("height", "int"), ("seconds", "double"), ("pages", "int")) for x in (F.lit(n), F.lit(None).cast(t))])
    return F.array(part)


def format_turns(turns: DataFrame, visitor: PartVisitor | None = None, conv: str = "conv_id", turn: str = "turn", role: str = "role", parts: str = "parts") -> DataFrame:
    """(conv, turn, segment, loss_start, loss_chars, attachments) of each turn: the segments of a conversation, joined
    in order, are its formatted text. loss_start counts characters from the segment's start; only assistants' content
    is under the loss mask. attachments: array of (number, kind, ref, tokens)."""
    see = visitor or PartVisitor()
    known = F.filter(F.coalesce(F.col(parts), F.array().cast(f"array<{PART}>")), lambda p: p["kind"].isin(*see.kinds))
    attached = F.filter(F.col("__parts"), lambda p: p["kind"] != "text")
    order = F.transform(F.col("__parts"), lambda p, i: F.named_struct(F.lit("p"), p, F.lit("n"), F.size(F.filter(F.slice(F.col("__parts"), 1, i + 1), lambda q: q["kind"] != "text"))))
    content = F.array_join(F.transform(order, lambda x: see.render(x["p"], x["n"])), "")
    head = F.concat(F.lit(TURN), escape(F.col(role)), F.lit(TEXT))
    loss = F.col(role) == "assistant"
    out = turns.select(F.col(conv).alias("conv_id"), F.col(turn).alias("turn"), F.col(role).alias("role"), known.alias("__parts"))
    out = out.select("conv_id", "turn", "role", head.alias("head"), content.alias("content"), F.transform(attached, lambda p, i: F.named_struct(F.lit("number"), i + 1, F.lit("kind"), p["kind"], F.lit("ref"), p["ref"], F.lit("tokens"), see.tokens(p))).alias("attachments"))
    return out.select("conv_id", "turn", F.concat("head", "content", F.lit(END)).alias("segment"), F.when(loss, F.length("head")).alias("loss_start"), F.when(loss, F.length("content")).otherwise(0).alias("loss_chars"), "attachments")


def read_back(segments: DataFrame) -> DataFrame:
    """(conv_id, turn, role, text, loss_text, n_chars) parsed from the segments alone and their loss spans."""
    body = r"(?s)^<\|turn\|>(.*?)<\|text\|>(.*)<\|end\|>\n$"
    masked = F.expr("if(loss_start is null, null, substring(segment, loss_start + 1, loss_chars))")
    return segments.select("conv_id", "turn", unescape(F.regexp_extract("segment", body, 1)).alias("role"), unescape(F.regexp_extract("segment", body, 2)).alias("text"), unescape(masked).alias("loss_text"), F.length("segment").alias("n_chars"))


def _digests(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """One row for each run of equal conv_id; rows come sorted, and a run may span batches."""
    names, at, sums = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"], (), []
    for batch in batches:
        done = []
        for conv, role, text, loss, n in zip(*(batch[c] for c in ("conv_id", "role", "text", "loss_text", "n_chars")), strict=True):
            if at != (conv,):
                if at:
                    done.append((at[0], sums[0], sums[1].hexdigest(), sums[2], sums[3].hexdigest(), sums[4]))
                at, sums = (conv,), [0, hashlib.sha256(), 0, hashlib.sha256(), 0]
            sums[0] += 1
            sums[1].update(f"{role}\n{text}\n".encode())
            if loss is not None and loss == loss:
                sums[2] += len(loss)
                sums[3].update(loss.encode())
            sums[4] += int(n)
        if done:
            yield pd.DataFrame(done, columns=names)
    if at:
        yield pd.DataFrame([(at[0], sums[0], sums[1].hexdigest(), sums[2], sums[3].hexdigest(), sums[4])], columns=names)


def conversation_digests(turns: DataFrame) -> DataFrame:
    """By conversation, what the formatted text holds; memory does not grow with a conversation's length."""
    ship(turns.sparkSession)
    rows = turns.withColumn("conv_id", whole_id("conv_id")).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    out = rows.select("conv_id", "role", "text", "loss_text", "n_chars").mapInPandas(_digests, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
    return out.withColumn("conv_id", given_id("conv_id"))


def op4_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    odd = spark.createDataFrame([(-7, i, r, "</s>[INST] ok [/INST]") for i, r in enumerate(("user", "assistant"))], "conv_id long, turn long, role string, text string")
    turns = turns.unionByName(odd).withColumn("parts", text_parts(F.col("text")))
    return conversation_digests(read_back(format_turns(turns)))


#: No escape or template in here: what the formatted text must read back to, and its length by the template's rule.
OP4_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (
  SELECT *, len(regexp_extract_all(text, '[<\[]\\*(\||/?s>|/?INST\])')) + len(regexp_extract_all(role, '[<\[]\\*(\||/?s>|/?INST\])')) AS marks FROM t)
SELECT CAST(conv_id AS BIGINT) AS conv_id, count(*) AS n_turns,
       sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
       sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn, role, text), '')) AS loss_sha256,
       CAST(sum(length(role) + length(text) + marks + 8 + 8 + 8) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
