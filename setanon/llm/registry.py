"""Queries of this subpackage and their DuckDB twins.

``text_*`` queries are columns of an operator's query that SQL can state; the operator makes them.
"""

from __future__ import annotations

from pyspark.sql import functions as F

from .decontaminate import op7_decontaminate
from .html import op6_html
from .jaccard import op5_jaccard
from .language import op1_language
from .packing import op8_packing
from .quality import op4_quality
from .rules import op10_rules
from .secrets import op9_secrets
from .sst import op2_sst
from .suffix import op3_suffix

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
KINDS = ("n_assign", "n_access", "n_hex")


def text_rule_counts(spark, sf_dir):
    """The counts and the base verdict of the quality rules."""
    return op10_rules(spark, sf_dir).select("doc_id", *COUNTS)


def text_secret_counts(spark, sf_dir):
    """How many base secrets of each kind a document holds."""
    return op9_secrets(spark, sf_dir).select("doc_id", *KINDS)


def text_without_letters(spark, sf_dir):
    """Documents whose language is undetermined, since they have no letters."""
    return op1_language(spark, sf_dir).where("lang_pred = 'und'").select("doc_id", F.col("score"))


def text_token_starts(spark, sf_dir):
    """Of the token shards: documents, and those that do not start where the one before them ends."""
    from pyspark.sql import Window as W

    rows = op2_sst(spark, sf_dir)
    before = F.sum("n_tokens").over(W.orderBy("doc_id").rowsBetween(W.unboundedPreceding, -1))  # three numbers a row
    return rows.withColumn("before", F.coalesce(before, F.lit(0))).agg(F.count(F.lit(1)).alias("documents"), F.count_if(F.col("start") != F.col("before")).alias("misplaced"))


_WORD = r"[^\x20\x09-\x0D]+"
_LOWER = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def any_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


_ASSIGN = "(?:" + "|".join(map(any_case, ("password", "passwd", "secret", "token", "api_?key"))) + r")[\"'']?\x20*[:=]\x20*[\"'']?([A-Za-z0-9+/_.=-]+)"

SQL = {
    "op3_suffix": """
WITH b AS (SELECT doc_id, encode(coalesce(text, '')) AS h FROM documents),
 w AS (SELECT doc_id, i, md5(h[i + 1:i + 200]) AS s FROM (SELECT doc_id, h, unnest(range(0, greatest(octet_length(h) - 199, 0))) AS i FROM b)),
 often AS (SELECT s FROM w GROUP BY s HAVING count(*) > 1),
 r AS (SELECT doc_id, i, CASE WHEN i > lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 200 THEN 1 ELSE 0 END AS gap FROM w JOIN often USING (s)),
 g AS (SELECT doc_id, i, sum(gap) OVER (PARTITION BY doc_id ORDER BY i) AS run FROM r),
 runs AS (SELECT doc_id, min(i) AS a, max(i) + 200 AS z FROM g GROUP BY doc_id, run),
 cuts AS (SELECT doc_id, a, z, lag(z, 1, 0) OVER (PARTITION BY doc_id ORDER BY a) AS f FROM runs),
 kept AS (SELECT c.doc_id, string_agg(hex(h[f + 1:a]), '' ORDER BY a) AS k, max(z) AS last, sum(z - a) AS n_removed, count(*) AS n_spans FROM cuts c JOIN b ON b.doc_id = c.doc_id GROUP BY c.doc_id)
SELECT b.doc_id, octet_length(h) AS n_bytes, CAST(coalesce(n_removed, 0) AS BIGINT) AS n_removed, coalesce(n_spans, 0) AS n_spans,
 sha256(unhex(coalesce(k, '') || hex(h[coalesce(last, 0) + 1:octet_length(h)]))) AS kept_sha256 FROM b LEFT JOIN kept ON kept.doc_id = b.doc_id""",
    "op5_jaccard": f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all({_LOWER}, '{_WORD}') AS w FROM documents),
 s AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) AS i FROM d WHERE len(w) > 0)),
 n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
 p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY 1, 2),
 l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= 80 * (a.n + b.n - c)),
 e AS (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
 r AS (SELECT doc_id AS id, doc_id AS seen FROM d UNION SELECT r.id, e.y FROM r JOIN e ON r.seen = e.x)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, component_id FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT id, min(seen) AS component_id FROM r GROUP BY id) c ON c.id = d.doc_id""",
    "text_rule_counts": rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS w FROM documents),
 f AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS x FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM d WHERE len(w) >= 5)),
 h AS (SELECT DISTINCT f.doc_id, f.i + o AS place FROM f JOIN (SELECT doc_id, x FROM f GROUP BY doc_id, x HAVING count(*) > 1) USING (doc_id, x), (SELECT unnest(range(0, 5)) AS o)),
 k AS (SELECT doc_id, count(*) AS n FROM h GROUP BY doc_id),
 l AS (SELECT doc_id, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
 a AS (SELECT d.doc_id, len(w) AS n_words, length(array_to_string(w, '')) AS word_chars, len(regexp_extract_all(t, '[#*$%&|<>]')) AS n_symbols, len(l.l) - len(list_distinct(l.l)) AS n_dup_lines, coalesce(k.n, 0) AS n_repeat_words FROM d JOIN l ON l.doc_id = d.doc_id LEFT JOIN k ON k.doc_id = d.doc_id)
SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM a""",
    "text_secret_counts": rf"""
SELECT doc_id, len(list_filter(regexp_extract_all(coalesce(text, ''), '{_ASSIGN}', 1), lambda x: length(x) >= 6)) AS n_assign,
 len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20)) AS n_access,
 len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: length(x) >= 24)) AS n_hex FROM documents""",
    "text_without_letters": r"SELECT doc_id, CAST(0 AS DOUBLE) AS score FROM documents WHERE text IS NULL OR NOT regexp_matches(text, '\p{L}')",
    "text_token_starts": "SELECT count(*) AS documents, CAST(0 AS BIGINT) AS misplaced FROM documents",
}


def queries():
    return {
        "op1_language": op1_language,
        "op2_sst": op2_sst,
        "op3_suffix": op3_suffix,
        "op4_quality": op4_quality,
        "op5_jaccard": op5_jaccard,
        "op6_html": op6_html,
        "op7_decontaminate": op7_decontaminate,
        "op8_packing": op8_packing,
        "op9_secrets": op9_secrets,
        "op10_rules": op10_rules,
        "text_rule_counts": text_rule_counts,
        "text_secret_counts": text_secret_counts,
        "text_without_letters": text_without_letters,
        "text_token_starts": text_token_starts,
    }


def oracle_sql():
    return {k: " ".join(v.split()) for k, v in SQL.items()}
