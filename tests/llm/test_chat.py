import hashlib
import random

from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from facetsel.llm.chat import PART, conversation_digests, escape, format_turns, op4_chat, read_back, text_parts, unescape


def test_escape_round_trip(spark):
    r = random.Random(0)
    pieces = ["<", "[", "\\", "|", "/s>", "s>", "INST]", "/INST]", "<|end|>", "a", "é😀", "\n", "$1", "<|turn|>"]
    texts = ["".join(r.choice(pieces) for _ in range(r.randint(0, 12))) for _ in range(3000)]
    df = spark.createDataFrame([(t,) for t in texts], "t string").select("t", escape(F.col("t")).alias("e")).withColumn("u", unescape(F.col("e")))
    for row in df.collect():
        assert row.u == row.t
        assert not any(x in row.e for x in ("<|", "</s>", "<s>", "[INST]", "[/INST]"))


@settings(max_examples=5, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 3), st.sampled_from(["user", "assistant", "system", "", "<|text|>"]), st.text(max_size=30)), max_size=12))
def test_digests(spark, turns):
    rows = [(c, i, r, t) for i, (c, r, t) in enumerate(turns)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("parts", text_parts(F.col("text")))
    got = {r.conv_id: r for r in conversation_digests(read_back(format_turns(df))).collect()}
    assert set(got) == {c for c, *_ in rows}
    for c, g in got.items():
        own = [x for x in rows if x[0] == c]
        loss = "".join(t for _, _, r, t in own if r == "assistant")
        assert g.n_turns == len(own) and g.loss_chars == len(loss) and g.loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()
        assert g.turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for _, _, r, t in own).encode()).hexdigest()


def test_typed_parts(spark):
    parts = [("text", "see ", None, None, None, None, None), ("image", None, "a.png", 57, 28, None, None), ("smell", "x", None, None, None, None, None), ("audio", None, "b.wav", None, None, 1.5, None), None, ("text", "<|image:1|>", None, None, None, None, None), ("document", None, "c.pdf", None, None, None, 3)]
    df = spark.createDataFrame([(1, 0, "user", parts), (1, 1, "assistant", None)], f"conv_id long, turn long, role string, parts array<{PART}>")
    a, b = format_turns(df).orderBy("turn").collect()
    assert a.segment == "<|turn|>user<|text|>see <|image:1|><|audio:2|><\\|image:1|><|document:3|><|end|>\n"
    assert [(x.number, x.kind, x.ref, x.tokens) for x in a.attachments] == [(1, "image", "a.png", 3), (2, "audio", "b.wav", 38), (3, "document", "c.pdf", 768)]
    assert b.loss_start == len("<|turn|>assistant<|text|>") and b.loss_chars == 0


def test_long_conversation_streams(spark):
    """A conversation of many batches and a null one."""
    n = 25_000
    df = spark.range(n).select(F.lit(5).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.lit("assistant").alias("role"), F.col("id").cast("string").alias("text"))
    df = df.unionByName(spark.createDataFrame([(None, 0, None, None)], "conv_id long, turn long, role string, text string")).withColumn("parts", text_parts(F.col("text")))
    got = {r.conv_id: r for r in conversation_digests(read_back(format_turns(df))).collect()}
    assert got[5].n_turns == n and got[5].loss_sha256 == hashlib.sha256("".join(map(str, range(n))).encode()).hexdigest()
    assert got[None].n_turns == 1 and got[None].loss_chars == 0


def test_planted_conversation(spark, sf_dir):
    got = op4_chat(spark, sf_dir).where("conv_id = -7").first()
    text = "</s>[INST] ok [/INST]"
    assert got.n_turns == 2 and got.loss_sha256 == hashlib.sha256(text.encode()).hexdigest() and got.loss_chars == len(text)
