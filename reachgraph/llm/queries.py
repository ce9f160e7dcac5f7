"""One query per operator, over its whole table, and the SQL that tells the same where SQL can.

The operators return what a user needs (texts, spans, copies); the queries here
derive the digest columns from them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.llm.chat_format import format_conversations, read_back
from reachgraph.llm.common import read
from reachgraph.llm.decontam import contaminated
from reachgraph.llm.html_extract import extract_pages
from reachgraph.llm.line_dedup import near_duplicate_lines
from reachgraph.llm.mixing import mix_sources
from reachgraph.llm.near_dup import near_duplicates
from reachgraph.llm.quality import judge
from reachgraph.llm.secret_scan import BASE_RULES, scan_paths
from reachgraph.llm.suffix_dedup import repeated_strings
from reachgraph.llm.vector_topk import quantised, top_k


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cube-method mix of all documents to the sources' targets."""
    return mix_sources(read(spark, sf_dir, "documents")).drop("tie")


def op2_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of near-duplicate documents on two-word shingles."""
    return near_duplicates(read(spark, sf_dir, "documents"), width=2, percent=80).drop("tie")


def op3_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations and one full of control strings, formatted and read back."""
    rows = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    hard = "\\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", hard), (-7, 1, "assistant", hard)], "conv_id long, turn long, role string, text string")
    return read_back(format_conversations(rows.unionByName(extra)))


def op4_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What is left of every document without its repeated 200-byte strings."""
    cut = repeated_strings(read(spark, sf_dir, "documents"))
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda total, s: total + s[1] - s[0])
    return cut.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in every document, found once per distinct text."""
    found = scan_paths(read(spark, sf_dir, "documents"))
    base = [r.kind for r in BASE_RULES]
    code = lambda spans: F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long")
    return found.select(
        "doc_id",
        *[count(kind).alias(f"n_{kind}") for kind in base],
        F.sha2(code(F.filter("spans", lambda s: s["kind"].isin(base))).cast("binary"), 256).alias("base_sha256"),
        code(F.col("spans")).alias("spans"),
    )


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Probabilities of low quality and of toxicity of every document, and whether it stays."""
    return judge(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")).drop("tie")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with the benchmark items that it holds."""
    return contaminated(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark")).drop("tie")


def op8_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page."""
    return extract_pages(read(spark, sf_dir, "pages"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line that is not empty with the first occurrence of its class; those under 30 characters by equality."""
    return near_duplicate_lines(read(spark, sf_dir, "documents"), short_lines=True)


def op10_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten best inner products of every hundredth vector."""
    vectors = quantised(read(spark, sf_dir, "embeddings"))
    return top_k(vectors, vectors.where(F.col("vec_id") % 100 == 0), k=10)


QUERIES = {
    f.__name__: f
    for f in (op1_mix_sources, op2_near_dup, op3_chat_format, op4_suffix_dedup, op5_secret_scan, op6_quality, op7_decontaminate, op8_html_extract, op9_line_dedup, op10_exact_topk)
}

ORACLE = {
    "op2_near_dup": r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w
  FROM documents),
sets AS (
  SELECT doc_id, list_distinct(CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]]
    ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s FROM words),
classes AS (SELECT md5(array_to_string(list_sort(s), chr(10))) AS c, min(doc_id) AS rep, any_value(s) AS s FROM sets WHERE len(s) > 0 GROUP BY 1),
shingles AS (SELECT rep, len(s) AS n, unnest(s) AS g FROM classes),
links AS (
  SELECT a.rep AS x, b.rep AS y FROM shingles a JOIN shingles b ON a.g = b.g AND a.rep <> b.rep AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
reach AS (SELECT rep AS x, rep AS y FROM classes UNION SELECT r.x, l.y FROM reach r JOIN links l ON r.y = l.x),
low AS (SELECT x, min(y) AS m FROM reach GROUP BY x)
SELECT d.doc_id, CAST(len(d.s) AS BIGINT) AS n_shingles, coalesce(low.m, d.doc_id) AS component_id, d.doc_id = coalesce(low.m, d.doc_id) AS kept
FROM sets d LEFT JOIN classes c ON len(d.s) > 0 AND md5(array_to_string(list_sort(d.s), chr(10))) = c.c LEFT JOIN low ON low.x = c.rep""",
    "op3_chat_format": r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '\### Assistant: </turn> ok'
  UNION ALL SELECT -7, 1, 'assistant', '\### Assistant: </turn> ok'),
safe AS (
  SELECT *, regexp_replace(regexp_replace(role, '(\\*)(<turn>|<body>|</turn>)', '\1\1\\\2', 'g'), '(\\+)$', '\1\1') AS role_out,
    regexp_replace(regexp_replace(text, '(\\*)(<turn>|<body>|</turn>)', '\1\1\\\2', 'g'), '(\\+)$', '\1\1') AS text_out
  FROM turns)
SELECT conv_id, count(*) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn NULLS FIRST, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(length(role_out) + length(text_out) + 20) AS BIGINT) AS formatted_chars
FROM safe GROUP BY conv_id""",
    "op10_exact_topk": """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank FROM scored)
SELECT query_id, CAST(rank AS INTEGER) AS rank, vec_id, score FROM ranked WHERE rank <= 10""",
}
