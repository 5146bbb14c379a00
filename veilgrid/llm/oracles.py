"""DuckDB SQL for the queries of this subpackage that SQL can express.

The others are a trained model, a fingerprint, a tokenizer or a seeded shuffle; tests/llm holds them against brute force.
"""

from __future__ import annotations



#: Notices of one sentence, as they stand in the documents, with the licence, rule and identifier asked for.
NOTICES = (
    ("released under the mit license", "MIT", "mit-line", "mit-note"),
    ("licensed under the mit license", "MIT", "mit-line", "mit-note"),
    ("licensed under the apache license version 2 0", "Apache-2.0", "apache-line", "apache-note"),
    ("this work is licensed under the gnu general public license version 3", "GPL-3.0", "gpl3-line", "gpl3-note"),
    ("this work is licensed under the gnu general public license version 2", "GPL-2.0", "gpl2-line", "gpl2-note"),
    ("licensed under cc by 4 0", "CC-BY-4.0", "by-line", "by-note"),
    ("licensed under cc by nc 4 0", "CC-BY-NC-4.0", "by-nc-line", "by-nc-note"),
    ("licensed under cc by sa 4 0", "CC-BY-SA-4.0", "by-sa-line", "by-sa-note"),
    ("all rights reserved", "Proprietary", "reserved-line", "reserved"),
)


def license_sql() -> str:
    """One-sentence notices, written apart from the operator's tables: texts cut after marks before white space and at new lines, each sentence
    reduced to lower-case words. Longer notices don't occur in the given documents; tests/llm hold them."""
    cut = "string_split_regex(text, '[.!?]+(?:[ \\t\\x0b\\x0c\\r\\n]+|$)|\\n+')"
    known = ", ".join("(" + ", ".join(f"'{x}'" for x in row) + ")" for row in NOTICES)
    words = "trim(regexp_replace(translate(sentence, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^a-z0-9]+', ' ', 'g'))"
    return f"""WITH s AS (SELECT doc_id, unnest({cut}) AS sentence, unnest(range(len({cut}))) AS pos FROM documents WHERE text IS NOT NULL)
SELECT doc_id, v.license, v.rule, CAST(pos AS INTEGER) AS first_sentence, CAST(pos AS INTEGER) AS last_sentence, v.id AS sentence_ids, trim(sentence) AS matched FROM s JOIN (VALUES {known}) v(words, license, rule, id) ON {words} = v.words"""


def audit_sql() -> str:
    """Both replicas numbered within archives of 256 ids, record places by running sums of record lengths, and a full join by place on the bytes."""
    size = "(strlen('WARC/1.1..WARC-Type: resource..WARC-Target-URI: ') + strlen(url) + strlen('..Content-Length: ') + length(CAST(strlen(html) AS VARCHAR)) + 4 + strlen(html) + 4)"
    placed = lambda rows: f"SELECT CAST(floor(id / CAST(256 AS DOUBLE)) AS BIGINT) AS archive, row_number() OVER w - 1 AS place, id, CAST(sum({size}) OVER w - {size} AS BIGINT) AS start, {size} AS n, url, html FROM ({rows}) WINDOW w AS (PARTITION BY floor(id / CAST(256 AS DOUBLE)) ORDER BY id)"
    harmed = "SELECT page_id AS id, url, CASE WHEN page_id % 997 = 5 THEN '~' || substr(html, 2) WHEN page_id % 1499 = 7 THEN substr(html, 1, 100) ELSE html END AS html FROM pages WHERE page_id % 1601 <> 203 UNION ALL SELECT -1 - page_id, url, html FROM pages WHERE page_id % 2003 = 11"
    return f"""WITH a AS ({placed('SELECT page_id AS id, url, html FROM pages')}), b AS ({placed(harmed)})
SELECT archive, place AS "at", a.id AS record_id, a.start AS "offset", a.n AS length, b.id AS replica_record_id, b.start AS replica_offset, b.n AS replica_length,
CASE WHEN b.id IS NULL THEN 'missing' WHEN a.id IS NULL THEN 'extra' WHEN a.id = b.id THEN 'corrupt' ELSE 'moved' END AS state
FROM a FULL JOIN b USING (archive, place) WHERE a.id IS NULL OR b.id IS NULL OR a.html <> b.html OR a.url <> b.url"""


ORACLES: dict[str, str] = {"op5_license_scan": license_sql(), "op6_merkle_audit": audit_sql()}
