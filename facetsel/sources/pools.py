"""Pools of instances: (pool, instance_id, context, prompt, answer, source, lang, n_chars), and the flat view that the
rubric reads (body, has_context).

docs: a document's first line is the prompt, the rest the answer; its context is the vector at its id modulo their
number. web: a page's title and its article's paragraphs, the context is the markup. chat: a user turn and the
assistant's answer to it, the context is the turns before; user turns without an answer are dropped."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.functions.session import spread


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _context(kind: str, body, vec=None):
    return F.struct(F.lit(kind).alias("kind"), (body if body is not None else F.lit(None).cast("string")).alias("body"), (vec if vec is not None else F.lit(None).cast("array<float>")).alias("vec"))


_SPLIT = {
    "prompt": "case when instr(text, chr(10)) > 0 then substring(text, 1, instr(text, chr(10)) - 1) else text end",
    "answer": "case when instr(text, chr(10)) > 0 then substring(text, instr(text, chr(10)) + 1) else '' end",
}


def docs_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the rubric needs of documents: no join, three columns and the text are read."""
    d = spread(table(spark, sf_dir, "documents").select("doc_id", "source", "lang", "text"))
    return d.select(F.col("doc_id").alias("instance_id"), "source", "lang", F.col("text").alias("body"), F.expr(_SPLIT["prompt"]).alias("prompt"), F.expr(_SPLIT["answer"]).alias("answer"), F.lit(False).alias("has_context"))


DOCS_FLAT_SQL = f"SELECT doc_id AS instance_id, source, lang, text AS body, {_SPLIT['prompt']} AS prompt, {_SPLIT['answer']} AS answer, false AS has_context FROM documents"


def docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, e = table(spark, sf_dir, "documents"), table(spark, sf_dir, "embeddings")
    n = e.count()  # from the footers
    d = d.withColumn("vec_id", F.pmod("doc_id", F.lit(max(1, n))))
    j = d.join(e.select("vec_id", "embedding"), "vec_id", "left")
    return j.select(F.lit("docs").alias("pool"), F.col("doc_id").alias("instance_id"), _context("vec", None, F.col("embedding")).alias("context"), F.expr(_SPLIT["prompt"]).alias("prompt"), F.expr(_SPLIT["answer"]).alias("answer"), "source", "lang", F.col("n_chars").cast("long").alias("n_chars"))


_TITLE, _ARTICLE, _PARAGRAPH, _HOST = r"(?s)<title>(.*?)</title>", r"(?s)<article[^>]*>(.*?)</article>", r"(?s)<p>(.*?)</p>", r"^https?://([^/]+)"


def web_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = spread(table(spark, sf_dir, "pages"))
    p = p.select("page_id", F.regexp_extract("url", _HOST, 1).alias("source"), "html", F.regexp_extract("html", _TITLE, 1).alias("prompt"), F.array_join(F.regexp_extract_all(F.regexp_extract("html", _ARTICLE, 1), F.lit(_PARAGRAPH), 1), "\n").alias("answer"))
    return p.select(F.col("page_id").alias("instance_id"), "source", F.lit("en").alias("lang"), F.concat_ws("\n", "prompt", "answer").alias("body"), "prompt", "answer", F.lit(True).alias("has_context"), "html")


WEB_FLAT_SQL = rf"""SELECT page_id AS instance_id, source, 'en' AS lang, prompt || chr(10) || answer AS body, prompt, answer, true AS has_context, html FROM (
  SELECT page_id, html, regexp_extract(url, '{_HOST}', 1) AS source, regexp_extract(html, '{_TITLE}', 1) AS prompt,
         array_to_string(regexp_extract_all(regexp_extract(html, '{_ARTICLE}', 1), '{_PARAGRAPH}', 1), chr(10)) AS answer FROM pages)"""


def web(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = web_flat(spark, sf_dir)
    return p.select(F.lit("web").alias("pool"), "instance_id", _context("html", F.col("html")).alias("context"), "prompt", "answer", "source", "lang", F.length("body").cast("long").alias("n_chars"))


def chat_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations")
    w = W.partitionBy("conv_id").orderBy("turn")
    c = c.select("conv_id", "turn", "role", "text", F.lead("role").over(w).alias("next_role"), F.lead("text").over(w).alias("answer"), F.max(F.when(F.col("role") == "system", 1).otherwise(0)).over(W.partitionBy("conv_id")).alias("sys"), F.count("*").over(W.partitionBy("conv_id")).alias("turns"), F.lag("turn").over(w).isNotNull().alias("has_context"))
    c = c.where("role = 'user' and next_role = 'assistant'")
    source = F.concat(F.when(F.col("sys") == 1, "sys").otherwise("nosys"), F.lit("-"), F.when(F.col("turns") <= 2, "short").when(F.col("turns") <= 5, "middle").otherwise("deep"))
    return c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("instance_id"), source.alias("source"), F.lit("en").alias("lang"), F.concat("text", F.lit("\n"), "answer").alias("body"), F.col("text").alias("prompt"), "answer", "has_context")


CHAT_FLAT_SQL = """SELECT conv_id * 1000 + turn AS instance_id, CASE WHEN sys = 1 THEN 'sys' ELSE 'nosys' END || '-' || CASE WHEN turns <= 2 THEN 'short' WHEN turns <= 5 THEN 'middle' ELSE 'deep' END AS source,
  'en' AS lang, text || chr(10) || answer AS body, text AS prompt, answer, has_context FROM (
  SELECT conv_id, turn, role, text, lead(role) OVER w AS next_role, lead(text) OVER w AS answer,
         max(CASE WHEN role = 'system' THEN 1 ELSE 0 END) OVER (PARTITION BY conv_id) AS sys, count(*) OVER (PARTITION BY conv_id) AS turns,
         lag(turn) OVER w IS NOT NULL AS has_context
  FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)) WHERE role = 'user' AND next_role = 'assistant'"""


def chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The context is the history; it is kept as the earlier turns' text, gathered by a window over the conversation."""
    c = table(spark, sf_dir, "conversations")
    history = F.array_join(F.collect_list("text").over(W.partitionBy("conv_id").orderBy("turn").rowsBetween(W.unboundedPreceding, -1)), "\n")
    h = c.select((F.col("conv_id") * 1000 + F.col("turn")).alias("instance_id"), history.alias("history"))
    return chat_flat(spark, sf_dir).join(h, "instance_id").select(F.lit("chat").alias("pool"), "instance_id", _context("history", F.col("history")).alias("context"), "prompt", "answer", "source", "lang", F.length("body").cast("long").alias("n_chars"))


FLAT = {"docs": docs_flat, "web": web_flat, "chat": chat_flat}
FLAT_SQL = {"docs": DOCS_FLAT_SQL, "web": WEB_FLAT_SQL, "chat": CHAT_FLAT_SQL}
