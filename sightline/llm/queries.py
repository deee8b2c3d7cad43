"""Registered queries of the corpus operators, with production parameters and whole tables, and their SQL twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, decontam, embed_dedup, html_text, license, lines, ngram_join, token_files, toxicity, urls

#: Documents whose score reaches this are rejected.
REJECT = 0.3
HELD_OUT = "crc32(cast(doc_id as string)) % 4 = 2"


def BYTE_BPE() -> str:
    """Path of the public byte-level vocabulary."""
    import public_tokenizers

    return str(public_tokenizers.path("byte_bpe_50k.json"))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def learn(spark: SparkSession, docs: DataFrame, sf_dir: str) -> toxicity.ToxicityModel:
    """The toxicity model of the labelled rows that are not held out."""
    return toxicity.fit(docs, table(spark, sf_dir, "labels").where(f"not ({HELD_OUT})"))


def op1_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, n_links, component_id, kept and the audited recall of the search, one row per vector."""
    found, recall = embed_dedup.near_vectors(table(spark, sf_dir, "embeddings"))
    return found.withColumn("audited_recall", F.lit(float(recall)))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of documents and the benchmark items in them."""
    return decontam.find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    docs = table(spark, sf_dir, "documents")
    scored = toxicity.score_texts(docs.select("doc_id", "text"), learn(spark, docs, sf_dir))
    return scored.select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", (F.col("score") >= REJECT).cast("int").alias("predicted"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_lines, n_dropped, kept_sha256."""
    kept = lines.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return kept.select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, url, text, n_chars."""
    return html_text.extract_text(table(spark, sf_dir, "pages")).select("page_id", "url", "text", "n_chars")


def op6_ngram_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_shingles, component_id for four-word shingles and 85 per cent."""
    return ngram_join.jaccard_components(table(spark, sf_dir, "documents"), words=4, percent=85)


def op7_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 from the files written."""
    target = token_files.new_target(spark)
    token_files.write_token_files(table(spark, sf_dir, "documents"), BYTE_BPE(), target)
    return token_files.verified(token_files.read_token_files(spark, target))


def op8_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, round_trip."""
    return bpe.encode_decode(table(spark, sf_dir, "documents"), BYTE_BPE())


def op9_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, host, path, rule, verdict."""
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    return urls.filter_urls(pages, urls.rules_frame(spark, urls.RULES)).select("page_id", "host", "path", "rule", "verdict")


def op10_license(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    return license.scan_licenses(table(spark, sf_dir, "documents")).drop("blocks")


def op10_license_wrapped(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As op10_license, with statements over line breaks and without word sets scattered over a long line."""
    return license.scan_licenses(table(spark, sf_dir, "documents"), by="window").drop("blocks")


QUERIES = {
    f.__name__: f
    for f in (
        op1_embedding_near_dedup, op2_decontamination, op3_toxicity, op4_line_dedup, op5_html_text, op6_ngram_jaccard, op7_token_files, op8_bpe, op9_url_filter, op10_license_wrapped, op10_license,
    )
}

_AZ = "'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'"
_SPACES = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"


def _components(pairs: str, nodes: str) -> str:
    """SQL of (id, component): the smallest id reachable over ``pairs`` (a, b), given in both directions."""
    return f"""reach AS (
        SELECT id AS a, id AS b FROM {nodes}
        UNION SELECT reach.a, p.b FROM reach JOIN {pairs} p ON p.a = reach.b
    ), comps AS (SELECT a AS id, min(b) AS component_id FROM reach GROUP BY a)"""


def _license_sql() -> str:
    base = ", ".join(
        "len(list_filter(range(0, len(w)), lambda i: " + " AND ".join(f"w[i + {k + 1}] = '{word}'" for k, word in enumerate(phrase.split())) + f")) AS n_{j}, "
        "list_filter(range(0, len(w)), lambda i: " + " AND ".join(f"w[i + {k + 1}] = '{word}'" for k, word in enumerate(phrase.split())) + f") AS at_{j}"
        for j, phrase in enumerate(license.PHRASES)
    )
    names = list(license.PHRASES.values())
    rows = ", ".join(
        f"('{label}', [{', '.join(repr(x) for x in sorted(set(license.words_of(t))))}])" for label, texts in license.TEMPLATES.items() for t in texts
    )
    some = ", ".join(f"CASE WHEN n_{j} > 0 THEN '{label}' END" for j, label in enumerate(names))
    pattern = r"'[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'"
    return f"""WITH RECURSIVE words AS (
        SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(translate(coalesce(text, ''), {_AZ}), {pattern}) AS w FROM documents
    ), hits AS (SELECT doc_id, t, len(w) AS n_words, {base} FROM words),
    templates(label, words) AS (VALUES {rows}),
    blocks AS (SELECT doc_id, list_distinct(regexp_extract_all(translate(line, {_AZ}), {pattern})) AS lw FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM words)),
    met AS (
        SELECT doc_id, label, max(len(list_intersect(words, lw)) / len(words)::DOUBLE) AS c FROM blocks, templates
        WHERE 100 * len(list_intersect(words, lw)) >= 90 * len(words) GROUP BY doc_id, label
    ), more AS (SELECT doc_id, list(label) AS labels, max(c) AS c FROM met GROUP BY doc_id),
    sums AS (SELECT *, {' + '.join(f'n_{j}' for j in range(len(names)))} AS n, list_concat({', '.join(f'at_{j}' for j in range(len(names)))}) AS places, list_filter([{some}], lambda x: x IS NOT NULL) AS base FROM hits)
    SELECT doc_id, n_words, n AS n_base, list_min(places) AS first_word, list_max(places) AS last_word,
        array_to_string(list_sort(base), ',') AS base_labels,
        array_to_string(list_sort(list_distinct(list_concat(base, coalesce(labels, [])))), ',') AS labels,
        CASE WHEN n > 0 THEN 1e0 ELSE coalesce(c, 0e0) END AS score
    FROM sums LEFT JOIN more USING (doc_id)"""


def _wrapped_sql() -> str:
    """Every run of as many words as a template has, instead of lines."""
    rows = ", ".join(f"('{label}', [{', '.join(repr(x) for x in sorted(set(license.words_of(t))))}], {len(license.words_of(t))})" for label, texts in license.TEMPLATES.items() for t in texts)
    head, _, rest = _license_sql().partition("templates(label, words) AS (VALUES ")
    _, _, tail = rest.partition("more AS (")
    return f"""{head}templates(label, words, span) AS (VALUES {rows}),
    near AS (SELECT doc_id, label, t.words AS words, span, d.w AS w FROM words d, templates t WHERE 100 * len(list_intersect(t.words, d.w)) >= 90 * len(t.words)),
    runs AS (SELECT doc_id, label, words, w[i:i + span - 1] AS r FROM (SELECT *, unnest(range(1, greatest(len(w) - span + 1, 1) + 1)) AS i FROM near)),
    met AS (SELECT doc_id, label, max(c / n::DOUBLE) AS c FROM (SELECT doc_id, label, len(words) AS n, len(list_intersect(words, r)) AS c FROM runs) WHERE 100 * c >= 90 * n GROUP BY doc_id, label),
    more AS ({tail}"""


def _url_sql() -> str:
    rows = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in urls.RULES)
    return f"""WITH RECURSIVE rules(verdict, h, p) AS (VALUES {rows}),
    cut AS (
        SELECT page_id, row_number() OVER () AS k, translate(regexp_extract(coalesce(url, ''), '^(?s:.*?)://([^/?#]*)', 1), {_AZ}) AS host,
            regexp_extract(coalesce(url, ''), '^(?s:.*?)://[^/?#]*([^?#]*)', 1) AS path FROM pages
    ), best AS (
        SELECT k, arg_max(h || p, len(h || p)) AS rule, arg_max(verdict, len(h || p)) AS verdict FROM cut, rules
        WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, p) GROUP BY k
    )
    SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM cut LEFT JOIN best USING (k)"""


ORACLES = {
    "op1_embedding_near_dedup": f"""WITH RECURSIVE v AS (
        SELECT vec_id AS id, label, embedding::DOUBLE[] AS e FROM embeddings
    ), fine AS (
        SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND list_dot_product(e, e) > 0
    ), links AS (
        SELECT x.id AS a, y.id AS b FROM fine x JOIN fine y ON x.label = y.label AND x.id <> y.id AND len(x.e) = len(y.e) WHERE list_cosine_similarity(x.e, y.e) >= 0.93
    ), degrees AS (SELECT a AS id, count(*) AS n FROM links GROUP BY a),
    {_components("links", "v")}
    SELECT v.id AS vec_id, coalesce(n, 0) AS n_links, component_id, v.id = component_id AS kept, 1e0 AS audited_recall
    FROM v JOIN comps USING (id) LEFT JOIN degrees USING (id)""",
    "op4_line_dedup": f"""WITH lines AS (
        SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS place FROM documents
    ), keyed AS (SELECT *, translate(trim(line, {_SPACES}), {_AZ}) AS key FROM lines),
    common AS (SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
    marked AS (SELECT k.*, coalesce(c.keeper <> k.doc_id, false) AS gone FROM keyed k LEFT JOIN common c ON c.key = k.key)
    SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_dropped,
        sha256(coalesce(string_agg(line, chr(10) ORDER BY place) FILTER (NOT gone), '')) AS kept_sha256
    FROM marked GROUP BY doc_id""",
    "op6_ngram_jaccard": f"""WITH RECURSIVE w AS (
        SELECT doc_id AS id, regexp_extract_all(translate(coalesce(text, ''), {_AZ}), '[^\\x20\\x09-\\x0D]+') AS w FROM documents
    ), sets AS (
        SELECT id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
            ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' '))) END AS s FROM w
    ), items AS (SELECT id, len(s) AS n, unnest(s) AS g FROM sets),
    same AS (SELECT x.id AS a, y.id AS b, any_value(x.n) AS na, any_value(y.n) AS nb, count(*) AS c FROM items x JOIN items y ON x.g = y.g AND x.id <> y.id GROUP BY x.id, y.id),
    links AS (SELECT a, b FROM same WHERE 100 * c >= 85 * (na + nb - c)),
    {_components("links", "sets")}
    SELECT id AS doc_id, len(s) AS n_shingles, component_id FROM sets JOIN comps USING (id)""",
    "op9_url_filter": _url_sql(),
    "op10_license": _license_sql(),
    "op10_license_wrapped": _wrapped_sql(),
}
