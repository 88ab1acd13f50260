"""The queries of this subpackage and the SQL of those that SQL can express."""

from __future__ import annotations

from .decontaminate import op1_decontaminate
from .langid import op7_language_id
from .media import op8_media_columns
from .packing import op2_best_fit_packing
from .quality import op3_quality
from .simhash import op5_simhash
from .suffixdedup import op4_suffix_dedup
from .tokencount import op10_token_counts
from .urlfilter import OP9_SQL, op9_url_filter
from .warc import op6_warc

QUERIES = {
    f.__name__: f
    for f in (op1_decontaminate, op2_best_fit_packing, op3_quality, op4_suffix_dedup, op5_simhash, op6_warc, op7_language_id, op8_media_columns, op9_url_filter, op10_token_counts)
}

#: SHA-1 in base 32 from its hex digits: five bits at a time.
OP6_SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS body FROM pages),
d AS (SELECT page_id, octet_length(body) AS n, sha1(body) AS hex FROM p),
b AS (SELECT *, array_to_string(list_transform(range(1, 41), lambda i: lpad(bin(strpos('0123456789abcdef', substr(hex, i, 1)) - 1), 4, '0')), '') AS bits FROM d),
e AS (SELECT page_id, n, hex, array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
        1 + list_sum(list_transform(range(1, 6), lambda j: CAST(substr(bits, 5 * i + j, 1) AS INT) * CAST(pow(2, 5 - j) AS INT)))::INT, 1)), '') AS digest FROM b),
m AS (SELECT *, max(page_id) OVER (PARTITION BY hex) AS top FROM e)
SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, digest AS payload_digest, CASE WHEN page_id < top OR page_id IS NULL AND top IS NOT NULL THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN page_id < top OR page_id IS NULL AND top IS NOT NULL THEN top END AS refers_to FROM m
"""

ORACLE_SQL = {"op6_warc": OP6_SQL, "op9_url_filter": OP9_SQL}
