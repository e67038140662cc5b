"""The registered queries of the training-data operators, each over its whole tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .decontaminate import decontaminate
from .exact_dedup import exact_dedup
from .html_text import extract_text
from .mixing import mix_sources
from .ngram_join import ngram_components
from .secrets import scan_secrets
from .tokens import token_round_trip
from .toxicity import fit_toxicity, score_toxicity, training_rows
from .url_filter import filter_urls, mine_url_rules
from .warc import warc_round_trip

#: Listed host/path rules of the URL filter.
URL_RULES = [("com/", "allow"), ("example.com/en/", "block"), ("www.example.com/en/", "allow"), ("net/es/", "block"), ("net/fr/", "block")]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def url_labels(pages: DataFrame, labels: DataFrame, listed: list[tuple[str, str]] = ()) -> DataFrame:
    """(url, blocked): what a listed rule says of a URL, else the label of the page's id, blocked if toxic or of low quality; others have none."""
    own = labels.groupBy("doc_id").agg(F.max(((F.col("toxic") == 1) | (F.col("quality") == 0)).cast("int")).alias("labelled"))
    judged = filter_urls(pages.select("page_id", "url"), [], listed)
    rows = judged.join(own, F.col("page_id") == F.col("doc_id"), "left")
    said = F.when(F.col("rule").isNotNull(), (F.col("verdict") == "block").cast("int")).otherwise(F.col("labelled"))
    return rows.select("url", said.alias("blocked")).filter("blocked is not null")


def op1_url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url")
    mined = mine_url_rules(url_labels(pages, table(spark, sf_dir, "labels"), URL_RULES))
    return filter_urls(pages, mined, URL_RULES).select("page_id", "host", "path", "rule", "verdict", "mined_rule", "confidence")


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents"), keep="max")


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit_toxicity(training_rows(docs, table(spark, sf_dir, "labels")))
    return score_toxicity(docs, model)


def op5_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_round_trip(table(spark, sf_dir, "documents"), tokenizer_path())


def op6_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages"))


def op7_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_components(table(spark, sf_dir, "documents"))


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"))


def op9_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_round_trip(table(spark, sf_dir, "pages"))


QUERIES = {f.__name__: f for f in (op1_url_rules, op2_mix_sources, op3_exact_dedup, op4_toxicity, op5_token_output, op6_html_text, op7_ngram_join, op8_secrets, op9_decontaminate, op10_warc)}

#: What SQL can say of operators whose whole rows it cannot: columns of the same queries.
COMPANIONS = {
    "listed_url_rules": lambda spark, sf_dir: op1_url_rules(spark, sf_dir).select("page_id", "host", "path", "rule"),
    "mix_targets": lambda spark, sf_dir: op2_mix_sources(spark, sf_dir).select("doc_id", "size", "source_size", "target"),
    "secret_counts": lambda spark, sf_dir: op8_secrets(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex"),
}

_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

ORACLE_SQL = {
    "op3_exact_dedup": f"""
        WITH d AS (SELECT doc_id, {_LOWER} AS t FROM documents)
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id IS NOT DISTINCT FROM max(doc_id) OVER w AS kept, sha256(t) AS text_sha256
        FROM d WINDOW w AS (PARTITION BY t)""",
    "op7_ngram_join": rf"""
        WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x20\x09-\x0D]+') AS w FROM documents),
        s AS (SELECT DISTINCT doc_id, array_to_string(list_slice(w, i, i + 4), ' ') AS g
              FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
        n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
        p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
        l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 75 * (a.n + b.n - c)),
        r(doc_id, seen) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.doc_id, l.y FROM r JOIN l ON l.x = r.seen),
        m AS (SELECT doc_id, min(seen) AS component_id FROM r GROUP BY doc_id)
        SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.component_id
        FROM documents d LEFT JOIN n USING (doc_id) JOIN m USING (doc_id)""",
    "op9_decontaminate": rf"""
        WITH d AS (SELECT doc_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
        b AS (SELECT item_id, regexp_extract_all({_LOWER}, '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
        v AS (SELECT DISTINCT item_id, least(len(w), 10) AS k, array_to_string(list_slice(w, i, i + 9), ' ') AS g
              FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
        k AS (SELECT DISTINCT k FROM v),
        x AS (SELECT doc_id, k, i, array_to_string(list_slice(w, i, i + k - 1), ' ') AS g
              FROM (SELECT doc_id, w, k, unnest(range(1, len(w) - k + 2)) AS i FROM d, k WHERE len(w) >= k)),
        h AS (SELECT doc_id, item_id, i, x.k FROM x JOIN v ON x.g = v.g AND x.k = v.k),
        c AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + k)) AS p FROM h) GROUP BY doc_id),
        t AS (SELECT doc_id, count(*) AS n_items, string_agg(i, ',' ORDER BY i) AS items
              FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS i FROM h) GROUP BY doc_id)
        SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
               sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
        FROM d LEFT JOIN c USING (doc_id) LEFT JOIN t USING (doc_id)""",
    "op10_warc": """
        WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS h FROM pages),
        q AS (SELECT *, max(page_id) OVER (PARTITION BY h, n) AS top FROM p)
        SELECT page_id, n AS payload_bytes, h AS payload_digest,
               CASE WHEN n >= 1000 AND top <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN n >= 1000 AND top <> page_id THEN top END AS refers_to
        FROM q""",
}

_EITHER = "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in "(password|passwd|secret|token|api_?key)")

ORACLE_SQL |= {
    "listed_url_rules": """
        WITH p AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
        h AS (SELECT page_id, regexp_extract(rest, '^[^/?#]*') AS raw, rest FROM p),
        q AS (SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(rest, length(raw) + 1), '^[^?#]*') AS path FROM h),
        r(rule, rh, rp) AS (VALUES ('com/', 'com', '/'), ('example.com/en/', 'example.com', '/en/'), ('www.example.com/en/', 'www.example.com', '/en/'), ('net/es/', 'net', '/es/'), ('net/fr/', 'net', '/fr/')),
        f AS (SELECT page_id, arg_max(rule, length(rule)) AS rule FROM q JOIN r ON (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp) GROUP BY page_id)
        SELECT q.page_id, host, path, rule FROM q LEFT JOIN f USING (page_id)""",
    "mix_targets": r"""
        WITH d AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents),
        s AS (SELECT source, CAST(sum(size) AS BIGINT) AS n FROM d GROUP BY source),
        w AS (SELECT source, n, CASE (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0 ELSE 1.0 END AS w FROM s),
        o AS (SELECT *, sum(n) OVER x AS below_n, sum(w) OVER x AS below_w FROM w WHERE n > 0 WINDOW x AS (ORDER BY n / w, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
        u AS (SELECT ((SELECT sum(n) FROM s) - 3.0::DOUBLE * coalesce(below_n, 0)) / ((SELECT sum(w) FROM w WHERE n > 0) - coalesce(below_w, 0)) AS unit, n / w AS ratio FROM o),
        t AS (SELECT arg_min(unit, ratio) AS unit FROM u WHERE unit <= 3.0 * ratio)
        SELECT doc_id, size, n AS source_size, CASE WHEN n > 0 THEN least(w * (SELECT unit FROM t), n * 3.0::DOUBLE) ELSE 0.0::DOUBLE END AS target
        FROM d JOIN w ON d.source IS NOT DISTINCT FROM w.source""",
    "secret_counts": rf"""
        SELECT doc_id, CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), '{_EITHER}["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)', 2), lambda x: length(x) >= 6)) AS BIGINT) AS n_assign,
        CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20)) AS BIGINT) AS n_access,
        CAST(len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: length(x) >= 24)) AS BIGINT) AS n_hex
        FROM documents""",
}
