"""Registered queries of this subpackage: thin calls of its operators with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import crc_mod, table


def tokenizer_paths() -> tuple[str, str, str]:
    import public_tokenizers as p

    return p.path("byte_bpe_50k.json"), p.path("byte_bpe_50k.tiktoken"), p.PATTERN


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_counts import count_tokens

    return count_tokens(table(spark, sf_dir, "documents"), *tokenizer_paths())


def op2_suffix_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffixes import repeated_passages

    return repeated_passages(table(spark, sf_dir, "documents")).drop("redundant")


OP2_SQL = r"""
WITH words AS (
  SELECT doc_id, list_filter(string_split_regex(text, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents WHERE doc_id IS NOT NULL
), windows AS (
  SELECT doc_id, s, md5(array_to_string(w[s + 1 : s + 50], ' ')) AS t
  FROM (SELECT doc_id, w, unnest(range(len(w) - 49)) AS s FROM words WHERE len(w) >= 50)
), shared AS (
  SELECT t, min(doc_id) AS f FROM windows GROUP BY t HAVING min(doc_id) <> max(doc_id)
), hits AS (
  SELECT doc_id, s, f, lag(s) OVER (PARTITION BY doc_id ORDER BY s) AS before FROM windows JOIN shared USING (t)
), runs AS (
  SELECT *, sum(CASE WHEN before IS NULL OR s - before > 50 THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY s) AS k FROM hits
), again AS (
  SELECT doc_id, k, least(50, coalesce(s - lag(s) OVER (PARTITION BY doc_id, k ORDER BY s), 50)) AS fresh FROM runs WHERE f < doc_id
)
SELECT doc_id, min(s)::BIGINT AS start_word, (max(s) + 50)::BIGINT AS end_word, min(f)::BIGINT AS first_doc_id, coalesce(any_value(n), 0)::BIGINT AS n_redundant
FROM runs LEFT JOIN (SELECT doc_id, k, sum(fresh) AS n FROM again GROUP BY ALL) USING (doc_id, k)
GROUP BY doc_id, k
"""


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from . import secrets as s

    found = s.find_secrets(table(spark, sf_dir, "documents"))
    counts = [s.count_kind("base", k).alias(f"n_{s.KINDS[k]}") for k in range(3)]
    return found.select("doc_id", *counts, F.sha2(s.listed("base").cast("binary"), 256).alias("base_sha256"), s.listed("found").alias("spans"), s.count_kind("found", 3).alias("n_entropy"))


def op3_sql() -> str:
    """The same by string functions: positions by prefix sums, entropy window by window."""
    from . import secrets as s

    quoted = lambda p: "'" + p.replace("'", "''") + "'"
    kind = lambda k, p, group, least: f"SELECT r, {k} AS k, string_split_regex(t, {quoted(p)}) AS g, regexp_extract_all(t, {quoted(p)}, 0) AS a, regexp_extract_all(t, {quoted(p)}, {group}) AS p, {least} AS least FROM d"
    allow = " OR ".join(f"regexp_matches(word, {quoted(p)})" for p in s.ALLOW)
    path = f"length(word) - length(replace(word, '/', '')) >= {s.PATH_SLASHES} AND NOT regexp_matches(word, '[^A-Za-z0-9/_-]') AND len(list_filter(string_split_regex(word, '{s.PATH_CUT}'), lambda x: length(x) >= {s.WINDOW} OR NOT regexp_matches(x, {quoted(s.PATH_PART)}))) = 0"
    bits = "CASE " + " ".join(f"WHEN regexp_matches(word, {quoted(p)}) THEN {least}" for p, least in s.CLASSES) + f" ELSE {s.BASE64_BITS} END"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
m AS ({kind(0, s.ASSIGN, 2, 6)} UNION ALL {kind(1, s.ACCESS, 0, 0)} UNION ALL {kind(2, s.HEX, 0, 0)} UNION ALL {kind(3, s.CANDIDATE, 0, 0)}),
one AS (SELECT *, unnest(range(1, len(a) + 1)) AS i FROM m),
placed AS (
  SELECT r, k, p[i] AS word, list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(a[1:i - 1], lambda x: length(x))), 0) AS s, length(a[i]) AS n
  FROM one WHERE length(p[i]) >= least
), base AS (SELECT r, k, s::BIGINT AS s, (s + n)::BIGINT AS e FROM placed WHERE k < 3),
cand AS (
  SELECT c.r, c.k, c.s::BIGINT AS s, (c.s + c.n)::BIGINT AS e, c.word FROM placed c
  WHERE k = 3 AND regexp_matches(word, '[0-9]') AND NOT ({allow}) AND NOT ({path}) AND NOT EXISTS (SELECT 1 FROM base b WHERE b.r = c.r AND b.s < c.s + c.n AND c.s < b.e)
), cut AS (SELECT *, substr(word, (unnest(range(1, length(word) - {s.WINDOW - 2})))::BIGINT, {s.WINDOW}) AS w FROM cand),
bits AS (
  SELECT r, k, s, e, word, max(log2({s.WINDOW}) - list_sum(list_transform(list_distinct(string_split(w, '')), lambda x: ({s.WINDOW} - length(replace(w, x, ''))) * log2({s.WINDOW} - length(replace(w, x, ''))))) / {s.WINDOW}) AS h
  FROM cut GROUP BY ALL
), extra AS (SELECT r, k, s, e FROM bits WHERE h >= {bits}),
named AS (SELECT *, ['assign', 'access', 'hex', 'entropy'][k + 1] || ':' || s || ':' || e AS x FROM (FROM base UNION ALL FROM extra)),
summed AS (
  SELECT r, count(*) FILTER (k = 0) AS a, count(*) FILTER (k = 1) AS b, count(*) FILTER (k = 2) AS c, count(*) FILTER (k = 3) AS n,
    string_agg(x, ',' ORDER BY s, k) FILTER (k < 3) AS l, string_agg(x, ',' ORDER BY s, k) AS spans FROM named GROUP BY r
)
SELECT doc_id, coalesce(a, 0)::BIGINT AS n_assign, coalesce(b, 0)::BIGINT AS n_access, coalesce(c, 0)::BIGINT AS n_hex, sha256(coalesce(l, '')) AS base_sha256, coalesce(spans, '') AS spans, coalesce(n, 0)::BIGINT AS n_entropy
FROM d LEFT JOIN summed USING (r)
"""


def op4_metric_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .metric_tree import top_k

    rows = table(spark, sf_dir, "embeddings")
    return top_k(rows, rows.where("vec_id % 20 = 0"), k=20)


OP4_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(64 * x::DOUBLE)) AS v FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), pairs AS (
  SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.v, c.v)::BIGINT AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 20 = 0
)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INTEGER AS rank, vec_id, score
FROM pairs QUALIFY rank <= 20
"""


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack

    pieces = pack(table(spark, sf_dir, "documents"), *tokenizer_paths())
    return pieces.select("doc_id", "start", "length", F.crc32("tokens").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .quality import fit, judge

    docs = table(spark, sf_dir, "documents")
    rules = fit(docs, table(spark, sf_dir, "labels"))
    return judge(docs, rules).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import fit, score

    docs = table(spark, sf_dir, "documents")
    model = fit(docs, table(spark, sf_dir, "labels"))
    return score(docs, model).select("doc_id", (crc_mod("doc_id", 5) == 0).alias("held_out"), "score", "predicted")


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .minhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"), k=4, percent=80)


OP8_SQL = r"""
WITH RECURSIVE words AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents
), sets AS MATERIALIZED (
  SELECT DISTINCT doc_id, array_to_string(w[i : i + 3], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 2, 2))) AS i FROM words WHERE len(w) > 0)
), sizes AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM sets GROUP BY 1),
pairs AS (SELECT a.doc_id AS u, b.doc_id AS v, count(*) AS c FROM sets a JOIN sets b USING (s) WHERE a.doc_id < b.doc_id GROUP BY 1, 2),
links AS MATERIALIZED (
  SELECT u, v FROM pairs JOIN sizes x ON x.doc_id = u JOIN sizes y ON y.doc_id = v WHERE 100 * c >= 80 * (x.n + y.n - c)
), both_ AS MATERIALIZED (SELECT u, v FROM links UNION ALL SELECT v, u FROM links),
reached AS (SELECT u AS node, u AS root FROM both_ UNION SELECT v, root FROM reached JOIN both_ ON u = node WHERE root < v),
least AS (SELECT node, min(root) AS root FROM reached GROUP BY 1)
SELECT doc_id, coalesce(n, 0)::BIGINT AS n_shingles, coalesce(root, doc_id) AS component_id, coalesce(root, doc_id) = doc_id AS kept
FROM words LEFT JOIN sizes USING (doc_id) LEFT JOIN least ON node = doc_id
"""


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as p

    from .language_id import fit, predict

    docs = table(spark, sf_dir, "documents")
    model = fit(docs, p.path("piece_bpe_32k.model"))
    return predict(docs, model).select("doc_id", (crc_mod("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score")


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers as p

    from .bpe import decode, encode

    vocabulary = p.path("byte_bpe_multi_50k.tiktoken"), p.PATTERN
    both = decode(encode(table(spark, sf_dir, "documents"), *vocabulary), vocabulary[0])
    return both.select("doc_id", "n_tokens", F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_token_counts, op2_suffix_arrays, op3_secrets, op4_metric_tree, op5_packing, op6_quality, op7_toxicity, op8_minhash, op9_language, op10_byte_bpe)}


def oracle_sql() -> dict[str, str]:
    return {"op2_suffix_arrays": OP2_SQL, "op3_secrets": op3_sql(), "op4_metric_tree": OP4_SQL, "op8_minhash": OP8_SQL}
