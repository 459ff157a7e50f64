"""The registered queries opN_<name>, each over its whole table, and the SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import embeddings, exact_dedup, langid, near_dedup, packing, pieces, secrets, sharding, token_counts, toxicity


def _vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _documents(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return docs.select(*columns) if columns else docs


def _fold(n: int):
    return F.crc32(F.encode(F.col("doc_id").cast("string"), "utf-8")) % n


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir, "doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "toxic")
    lexicon = toxicity.learn(docs, labels.filter(_fold(5) != 0))
    found = toxicity.score_texts(docs, lexicon)
    return found.select("doc_id", (_fold(5) == 0).alias("held_out"), "score", "predicted", "n_passages", F.to_json("passages").alias("passages"))


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(_documents(spark, sf_dir, "doc_id", "text"), _vocabulary("word_bpe_49k.json"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _documents(spark, sf_dir, "doc_id", "text", "lang")
    profiles = langid.learn_profiles(docs.filter(_fold(3) != 1))
    found = langid.detect(docs.select("doc_id", "text"), profiles)
    return found.select("doc_id", (_fold(3) == 1).alias("held_out"), "lang_pred", "score")


def op4_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(_documents(spark, sf_dir, "doc_id", "text"))


def pack_documents(docs: DataFrame) -> DataFrame:
    """docs packed with the byte-level vocabulary: sequences of 2048, each document ended by id 1."""
    import public_tokenizers

    special = {"<|endoftext|>": 50256}
    return packing.pack(docs, _vocabulary("byte_bpe_50k.json"), _vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, special)


def op5_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(_documents(spark, sf_dir, "doc_id", "text"))


def op6_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_groups(_documents(spark, sf_dir, "doc_id", "text"), words=3, percent=85)


def op7_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pieces.piece_digests(_documents(spark, sf_dir, "doc_id", "text"), _vocabulary("piece_bpe_32k.model"))


def op8_secret_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.digest_columns(secrets.scan_secrets(_documents(spark, sf_dir, "doc_id", "text", "source")))


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(_documents(spark, sf_dir, "doc_id", "text"))


def op10_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embeddings.near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (
        op1_toxicity, op2_token_counts, op3_language_id, op4_exact_dedup, op5_packing, op6_minhash_near_dedup,
        op7_sentencepiece, op8_secret_scans, op9_sharding, op10_embedding_near_dedup,
    )
    return {f.__name__: f for f in own}


_WHITE = "[\\x20\\x09-\\x0D]+"
_CAPITALS, _SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _either(word: str) -> str:
    """A pattern of an ASCII word in either case; a case flag would also take letters that fold to ASCII ones."""
    return "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in word)


_NAMES = "|".join(map(_either, ("password", "passwd", "secret", "token", "api_?key")))
_PATTERNS = (  # kind, pattern as an SQL string, group of the value
    ("assign", f"({_NAMES})[\"'']?\\x20*[:=]\\x20*[\"'']?([A-Za-z0-9+/_.=-]+)", 2),
    ("access", "(AKIA[A-Z0-9]+)", 1),
    ("hex", "([0-9a-f]{16,})", 1),  # runs are maximal, so shorter ones may be left out at once
)
_LENGTHS = "list_sum(list_transform({0}, lambda y: length(y)))"


def _hits(kind: str, pattern: str, group: int) -> str:
    """(r, kind, st, en, val) of all leftmost matches; a match starts after the gaps and matches before it."""
    start = f"CAST({_LENGTHS.format('g[1:i]')} + coalesce({_LENGTHS.format('h[1:i - 1]')}, 0) AS BIGINT)"
    return f"""SELECT r, '{kind}' AS kind, st, st + length(hit) AS en, val FROM (
        SELECT r, unnest(h) AS hit, unnest(v) AS val, unnest(list_transform(range(1, len(h) + 1), lambda i: {start})) AS st FROM (
            SELECT r, regexp_extract_all(x, '{pattern}') AS h, regexp_extract_all(x, '{pattern}', {group}) AS v, string_split_regex(x, '{pattern}') AS g FROM t) WHERE len(h) > 0)"""


def _reach(nodes: str, links: str) -> str:
    """Of each node n the nodes m that links (a, b), both ways, lead to; for tables whose components are small."""
    return f"reach(n, m) AS (SELECT n, n FROM {nodes} UNION SELECT reach.n, {links}.b FROM reach JOIN {links} ON reach.m = {links}.a)"


ORACLE = {
    "op4_exact_dedup": f"""
        WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '{_WHITE}', ' ', 'g') AS t FROM documents),
        g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
        SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256 FROM n JOIN g ON n.t = g.t""",
    "op6_minhash_near_dedup": f"""
        WITH RECURSIVE w AS (SELECT row_number() OVER () AS n, doc_id, regexp_extract_all(translate(coalesce(text, ''), '{_CAPITALS}', '{_SMALL}'), '{_WHITE.replace('[', '[^')}') AS w FROM documents),
        s AS (SELECT n, doc_id, CASE WHEN len(w) >= 3 THEN list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM w),
        u AS (SELECT n, len(s) AS c, unnest(s) AS x FROM s),
        p AS (SELECT y.n AS a, z.n AS b, count(*) AS shared, any_value(y.c) + any_value(z.c) AS c FROM u y JOIN u z ON y.x = z.x AND y.n <> z.n GROUP BY 1, 2),
        l AS (SELECT a, b FROM p WHERE 100 * shared >= 85 * (c - shared)),
        {_reach('s', 'l')},
        c AS (SELECT reach.n, min(s.doc_id) AS component_id FROM reach JOIN s ON s.n = reach.m GROUP BY 1)
        SELECT doc_id, CAST(len(s) AS BIGINT) AS n_shingles, component_id, doc_id = component_id AS kept FROM s JOIN c USING (n)""",
    "op8_secret_scans": f"""
        WITH t AS (SELECT row_number() OVER () AS r, doc_id, source, coalesce(text, '') AS x FROM documents),
        h AS ({" UNION ALL ".join(_hits(*k) for k in _PATTERNS)}),
        k AS (SELECT r, st, en, val, CASE WHEN kind = 'assign' AND length(val) < 12 THEN 'weak' ELSE kind END AS kind FROM h
            WHERE CASE kind WHEN 'assign' THEN length(val) >= 12 OR (length(val) >= 6 AND regexp_matches(val, '[0-9]') AND regexp_matches(val, '[A-Za-z]')) WHEN 'access' THEN length(val) >= 18 ELSE length(val) >= 16 END),
        o AS (SELECT val, count(*) AS owners FROM (SELECT DISTINCT val, source FROM k JOIN t USING (r)) GROUP BY val),
        f AS (SELECT k.*, owners <= {secrets.COMMON_OWNERS} AS live, list_position(['assign', 'access', 'hex', 'weak'], kind) AS p, kind || ':' || st || ':' || en AS span FROM k JOIN o USING (val) WHERE kind <> 'weak' OR owners <= {secrets.COMMON_OWNERS}),
        s AS (SELECT r, count(*) FILTER (kind = 'assign') AS n_assign, count(*) FILTER (kind = 'access') AS n_access, count(*) FILTER (kind = 'hex') AS n_hex, string_agg(span, ',' ORDER BY st, p) FILTER (kind <> 'weak') AS base,
            string_agg(span, ',' ORDER BY st, p) AS spans, count(*) FILTER (live) AS n_live, count(*) FILTER (NOT live) AS n_example FROM f GROUP BY r)
        SELECT doc_id, coalesce(n_assign, 0) AS n_assign, coalesce(n_access, 0) AS n_access, coalesce(n_hex, 0) AS n_hex, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans,
            coalesce(n_live, 0) AS n_live, coalesce(n_example, 0) AS n_example FROM t LEFT JOIN s USING (r)""",
    "op10_embedding_near_dedup": f"""
        WITH RECURSIVE v AS (SELECT row_number() OVER () AS n, vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
        g AS (SELECT * FROM v WHERE len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
        l AS (SELECT x.n AS a, y.n AS b FROM g x JOIN g y ON x.n <> y.n AND len(x.e) = len(y.e) WHERE list_cosine_similarity(x.e, y.e) >= 0.9),
        {_reach('v', 'l')},
        c AS (SELECT reach.n, min(v.vec_id) AS component_id FROM reach JOIN v ON v.n = reach.m GROUP BY 1),
        d AS (SELECT l.a AS n, count(DISTINCT y.vec_id) AS n_links FROM l JOIN v x ON x.n = l.a JOIN v y ON y.n = l.b WHERE x.vec_id <> y.vec_id GROUP BY 1)
        SELECT vec_id, coalesce(n_links, 0) AS n_links, component_id, vec_id = component_id AS kept FROM v JOIN c USING (n) LEFT JOIN d USING (n)""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
