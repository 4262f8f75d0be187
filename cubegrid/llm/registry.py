"""Queries of this subpackage, by name; ``__spark_entry__`` adds them where it can be imported."""

from __future__ import annotations

from cubegrid.llm.decontaminate import op4_decontamination
from cubegrid.llm.gif import op6_gif_media
from cubegrid.llm.language_id import op10_language_id
from cubegrid.llm.line_dedup import op7_line_dedup
from cubegrid.llm.mixing import op1_mixing
from cubegrid.llm.near_dup import op2_near_duplicates
from cubegrid.llm.quality import op9_quality
from cubegrid.llm.substring_dedup import op8_substring_dedup
from cubegrid.llm.token_counts import op5_token_counts
from cubegrid.llm.warc import op3_warc

QUERIES = {
    "op1_mixing": op1_mixing,
    "op2_near_duplicates": op2_near_duplicates,
    "op3_warc": op3_warc,
    "op4_decontamination": op4_decontamination,
    "op5_token_counts": op5_token_counts,
    "op6_gif_media": op6_gif_media,
    "op7_line_dedup": op7_line_dedup,
    "op8_substring_dedup": op8_substring_dedup,
    "op9_quality": op9_quality,
    "op10_language_id": op10_language_id,
}

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _words(table: str) -> str:
    return f"regexp_extract_all(translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS w FROM {table}"


#: DuckDB SQL for those queries that SQL can express over whole tables.
ORACLE_SQL: dict[str, str] = {
    # base 32: five hex digits are four letters
    "op3_warc": f"""WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS n, sha1(coalesce(html, '')) AS h FROM pages),
 g AS (SELECT h, max(page_id) AS top FROM p GROUP BY h),
 v AS (SELECT h, top, list_transform(range(8), lambda k: CAST('0x' || substr(h, CAST(5 * k + 1 AS BIGINT), 5) AS INTEGER)) AS five FROM g),
 c AS (SELECT h, top, array_to_string(list_transform(five, lambda x: array_to_string(list_transform([15, 10, 5, 0], lambda s: substr('{_UPPER}234567', ((x >> s) & 31) + 1, 1)), '')), '') AS digest FROM v)
 SELECT page_id, CAST(n AS BIGINT) AS payload_bytes, digest AS payload_digest, CASE WHEN page_id = top THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> top THEN top END AS refers_to FROM p JOIN c ON p.h = c.h""",
    "op4_decontamination": f"""WITH d AS (SELECT doc_id, {_words("documents")}), b AS (SELECT item_id, {_words("benchmark")}),
 bp AS (SELECT item_id, w, least(13, len(w)) AS n, unnest(range(1, greatest(len(w) - 12, 1) + 1)) AS p FROM b WHERE len(w) > 0),
 bw AS (SELECT DISTINCT item_id, n, array_to_string(w[p : p + n - 1], ' ') AS g FROM bp),
 dp AS (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, (SELECT DISTINCT n FROM bw)),
 h AS (SELECT DISTINCT doc_id, item_id, p, dp.n AS n FROM dp JOIN bw ON dp.n = bw.n AND array_to_string(w[p : p + dp.n - 1], ' ') = g),
 c AS (SELECT doc_id, count(DISTINCT q) AS n_hit FROM (SELECT doc_id, unnest(range(p, p + n)) AS q FROM h) GROUP BY doc_id),
 i AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM h) GROUP BY doc_id)
 SELECT d.doc_id, len(w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated
 FROM d LEFT JOIN c ON d.doc_id = c.doc_id LEFT JOIN i ON d.doc_id = i.doc_id""",
    "op7_line_dedup": """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS raw, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
 f AS (SELECT doc_id, pos, trim(raw) AS s, row_number() OVER (PARTITION BY doc_id ORDER BY pos) AS i FROM l WHERE trim(raw) <> ''),
 w AS (SELECT *, lead(s) OVER (PARTITION BY doc_id ORDER BY i) AS nxt, len(regexp_split_to_array(s, '\\s+')) AS words FROM f),
 k AS (SELECT *, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS k1, CASE WHEN nxt IS NULL THEN 1 ELSE row_number() OVER (PARTITION BY s, nxt ORDER BY doc_id, i) END AS k2 FROM w),
 g AS (SELECT doc_id, pos, i, (k1 > 1 AND words >= 8) OR k2 > 1 OR coalesce(lag(k2) OVER (PARTITION BY doc_id ORDER BY i) > 1, false) AS gone FROM k),
 r AS (SELECT *, gone AND NOT coalesce(lag(gone) OVER (PARTITION BY doc_id ORDER BY i), false) AS begins FROM g),
 t AS (SELECT l.doc_id, count(r.i) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed, count(*) FILTER (WHERE begins) AS n_runs, coalesce(string_agg(raw, chr(10) ORDER BY l.pos) FILTER (WHERE NOT coalesce(gone, false)), '') AS kept
 FROM l LEFT JOIN r ON l.doc_id = r.doc_id AND l.pos = r.pos GROUP BY l.doc_id)
 SELECT documents.doc_id, coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed, coalesce(n_runs, 0) AS n_runs, length(coalesce(kept, '')) AS kept_chars, sha256(coalesce(kept, '')) AS kept_sha256 FROM documents LEFT JOIN t ON documents.doc_id = t.doc_id""",
}
