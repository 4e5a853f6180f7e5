"""Registered queries of the corpus operators, and SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

import corpus_pipeline

from .decontaminate import op9_decontaminate
from .html_extract import op6_html_extract
from .jaccard_join import op10_jaccard_join
from .langid import op4_language_id
from .mixing import op5_mixing
from .quality_cnn import op8_quality
from .quality_rules import op2_quality_rules
from .token_counts import op7_token_counts
from .toxicity import op1_toxicity
from .warc import op3_warc

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_toxicity": op1_toxicity,
    "op2_quality_rules": op2_quality_rules,
    "op3_warc": op3_warc,
    "op4_language_id": op4_language_id,
    "op5_mixing": op5_mixing,
    "op6_html_extract": op6_html_extract,
    "op7_token_counts": op7_token_counts,
    "op8_quality": op8_quality,
    "op9_decontaminate": op9_decontaminate,
    "op10_jaccard_join": op10_jaccard_join,
    "pipeline": corpus_pipeline.run,
}
_WORDS = "list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '')"

#: Models, tilings, encodings and random permutations aren't SQL's; those operators are tested against brute force.
ORACLES: dict[str, str] = {
    "op3_warc": """WITH p AS (SELECT page_id, CAST(octet_length(encode(coalesce(html, ''))) AS BIGINT) AS n, sha256(coalesce(html, '')) AS d FROM pages),
h AS (SELECT d, min(page_id) AS head FROM p WHERE n >= 100 GROUP BY d)
SELECT page_id, n AS payload_bytes, p.d AS payload_digest, CASE WHEN page_id > head THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id > head THEN head END AS refers_to FROM p LEFT JOIN h ON h.d = p.d AND p.n >= 100""",
    "op10_jaccard_join": f"""WITH RECURSIVE t AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT r, doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) END AS x FROM t),
e AS (SELECT r, len(x) AS n, unnest(x) AS g FROM s),
p AS (SELECT a.r AS u, b.r AS v, a.n AS nu, b.n AS nv, count(*) AS k FROM e a JOIN e b ON a.g = b.g AND a.r <> b.r GROUP BY a.r, b.r, a.n, b.n),
l AS (SELECT u, v FROM p WHERE 100 * k >= 90 * (nu + nv - k)),
c AS (SELECT r, r AS m FROM s UNION SELECT c.r, l.v FROM c JOIN l ON c.m = l.u)
SELECT s.doc_id, CAST(len(s.x) AS BIGINT) AS n_shingles, min(o.doc_id) AS component_id FROM s JOIN c ON c.r = s.r JOIN s o ON o.r = c.m GROUP BY s.r, s.doc_id, len(s.x)""",
}
