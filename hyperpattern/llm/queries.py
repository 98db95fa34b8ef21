"""The queries of this subpackage, by name, and their SQL."""

from __future__ import annotations

import corpus_pipeline

from .decontam import op7_winnowing_decontamination
from .html_text import op9_nearest_url_extraction
from .line_dedup import op2_fuzzy_line_dedup
from .media import op1_media_sniffing
from .near_dup import op8_probminhash_near_duplicates
from .packing import op5_best_fit_packing
from .repeats import op10_difference_cover_repeats
from .sharding import op6_kd_tree_sharding
from .toxicity import op4_toxicity_neighbours
from .warc import op3_warc_reassembly

QUERIES = {
    "pipeline": corpus_pipeline.run,
    "op10_difference_cover_repeats": op10_difference_cover_repeats,
    "op9_nearest_url_extraction": op9_nearest_url_extraction,
    "op2_fuzzy_line_dedup": op2_fuzzy_line_dedup,
    "op8_probminhash_near_duplicates": op8_probminhash_near_duplicates,
    "op4_toxicity_neighbours": op4_toxicity_neighbours,
    "op3_warc_reassembly": op3_warc_reassembly,
    "op1_media_sniffing": op1_media_sniffing,
    "op5_best_fit_packing": op5_best_fit_packing,
    "op7_winnowing_decontamination": op7_winnowing_decontamination,
    "op6_kd_tree_sharding": op6_kd_tree_sharding,
}
_WORDS = r"regexp_extract_all(translate(coalesce({0}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
_DIGEST = "array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + ((CAST(concat('0x', substr(h, 5 * (i // 4) + 1, 5)) AS INTEGER) >> (15 - 5 * (i % 4))) & 31), 1)), '')"

ORACLES: dict[str, str] = {
    "op3_warc_reassembly": f"""
        WITH p AS (SELECT page_id, coalesce(html, '') AS html, sha1(coalesce(html, '')) AS h FROM pages),
        f AS (SELECT *, min(page_id) OVER (PARTITION BY h) AS least FROM p)
        SELECT page_id, strlen(html) AS payload_bytes, {_DIGEST} AS payload_digest,
               CASE WHEN page_id IS NOT DISTINCT FROM least THEN 'response' ELSE 'revisit' END AS record_type,
               CASE WHEN page_id IS DISTINCT FROM least THEN least END AS refers_to
        FROM f""",
    "op7_winnowing_decontamination": f"""
        WITH d AS (SELECT doc_id, {_WORDS.format('text')} AS w FROM documents),
        b AS (SELECT CAST(item_id AS VARCHAR) AS item, {_WORDS.format('text')} AS w FROM benchmark),
        bw AS (SELECT item, least(len(w), 13) AS n, w, unnest(range(1, len(w) - least(len(w), 13) + 2)) AS s FROM b WHERE len(w) > 0),
        win AS (SELECT DISTINCT item, n, array_to_string(w[s:s + n - 1], ' ') AS t FROM bw),
        ns AS (SELECT DISTINCT n FROM win),
        dw AS (SELECT doc_id, n, w, unnest(range(1, len(w) - n + 2)) AS s FROM d, ns WHERE len(w) >= n),
        hit AS (SELECT dw.doc_id, dw.s, dw.n, win.item FROM dw JOIN win ON win.n = dw.n AND win.t = array_to_string(dw.w[dw.s:dw.s + dw.n - 1], ' ')),
        words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hit) GROUP BY doc_id),
        items AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(item, ',' ORDER BY item)) AS items_sha256 FROM (SELECT DISTINCT doc_id, item FROM hit) GROUP BY doc_id)
        SELECT d.doc_id, len(d.w) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items,
               coalesce(items_sha256, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(d.w) AS contaminated
        FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)""",
}
