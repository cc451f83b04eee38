"""SQL for the operators on pairs, as DuckDB runs it on the small tables: all pairs that share a shingle or a label."""

from __future__ import annotations

_COMPONENTS = """
reach(a, b) AS (
  SELECT a, b FROM links
  UNION
  SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a
)"""

JACCARD = rf"""
WITH RECURSIVE texts AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), shingles AS (
  SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM texts WHERE len(w) >= 5) t
  UNION ALL
  SELECT doc_id, array_to_string(w, ' ') FROM texts WHERE len(w) BETWEEN 1 AND 4
), sizes AS (
  SELECT doc_id, count(*) AS n FROM shingles GROUP BY 1
), shared AS (
  SELECT p.doc_id AS a, q.doc_id AS b, count(*) AS c FROM shingles p JOIN shingles q ON p.g = q.g AND p.doc_id <> q.doc_id GROUP BY 1, 2
), links(a, b) AS (
  SELECT a, b FROM shared JOIN sizes x ON x.doc_id = a JOIN sizes y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)
), {_COMPONENTS}
SELECT d.doc_id, coalesce(n, 0) AS n_shingles, least(d.doc_id, coalesce(m, d.doc_id)) AS component_id
FROM documents d LEFT JOIN sizes s ON s.doc_id = d.doc_id LEFT JOIN (SELECT a, min(b) AS m FROM reach GROUP BY 1) r ON r.a = d.doc_id
"""

EMBEDDINGS = f"""
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE vec_id IS NOT NULL AND label IS NOT NULL AND embedding IS NOT NULL
), links(a, b) AS (
  SELECT p.vec_id, q.vec_id FROM v p JOIN v q ON p.label = q.label AND p.vec_id <> q.vec_id AND len(p.e) = len(q.e) WHERE list_cosine_similarity(p.e, q.e) >= 0.93
), {_COMPONENTS}
SELECT d.vec_id, coalesce(n, 0) AS n_links, least(d.vec_id, coalesce(m, d.vec_id)) AS component_id, d.vec_id = least(d.vec_id, coalesce(m, d.vec_id)) AS kept
FROM embeddings d LEFT JOIN (SELECT a, count(*) AS n FROM links GROUP BY 1) l ON l.a = d.vec_id LEFT JOIN (SELECT a, min(b) AS m FROM reach GROUP BY 1) r ON r.a = d.vec_id
"""


def licenses(phrases: dict[str, str], templates: dict[str, str]) -> str:
    """Phrases by word positions, templates as regular expressions over the words joined by spaces."""
    starts, labels, extra = [], [], []
    for phrase, label in phrases.items():
        p = phrase.split()
        match = " AND ".join(f"w[i + {k}] = '{x}'" for k, x in enumerate(p))
        starts.append(f"list_filter(range(1, greatest(len(w) - {len(p) - 2}, 1)), lambda i: {match})")
        labels.append(f"CASE WHEN contains(' ' || array_to_string(w, ' ') || ' ', ' {phrase} ') THEN '{label}' END")
    for label, markup in templates.items():
        out = " "
        for token in markup.replace("{=", " {=").replace("=}", "=} ").replace(" =}", "=}").replace("{= ", "{=").split():
            out += "(?:" if token == "{?" else ")?" if token == "?}" else "(?:[^ ]+ ){" + token[2:-2].replace("-", ",") + "}" if token.startswith("{=") else token + " "
        extra.append(f"CASE WHEN regexp_matches(' ' || array_to_string(w, ' ') || ' ', '{out}') THEN '{label}' END")
    joined = lambda items: f"array_to_string(list_sort(list_distinct(list_filter([{', '.join(items)}], lambda x: x IS NOT NULL))), ',')"
    return rf"""
WITH t AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents
), f AS (
  SELECT doc_id, len(w) AS n_words, {' || '.join(starts)} AS starts, {joined(labels)} AS base_labels, {joined([*labels, *extra])} AS labels, {joined(extra)} AS own FROM t
)
SELECT doc_id, n_words, len(starts) AS n_base, list_min(starts) - 1 AS first_word, list_max(starts) - 1 AS last_word, base_labels, labels,
       CASE WHEN own <> '' THEN 1.0::DOUBLE WHEN base_labels <> '' THEN 0.5::DOUBLE ELSE 0.0::DOUBLE END AS score FROM f
"""


#: For pages whose text is one article of headings and paragraphs, as in the given tables.
PAGES = r"""
WITH inner_html AS (
  SELECT page_id, url, regexp_replace(regexp_replace(regexp_extract(coalesce(html, ''), '(?s)<article>(.*?)</article>', 1), '<br>', ' ', 'g'), '</?(p|h1)>', chr(1), 'g') AS h FROM pages
), blocks AS (
  SELECT page_id, url, list_filter(list_transform(string_split(regexp_replace(h, '<[^>]*>', '', 'g'), chr(1)),
    lambda b: trim(regexp_replace(replace(replace(replace(replace(replace(b, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#x27;', ''''), '&amp;', '&'), '\s+', ' ', 'g'))), lambda b: b <> '') AS b
  FROM inner_html
)
SELECT page_id, url, array_to_string(b, chr(10)) AS text, CAST(length(array_to_string(b, chr(10))) AS BIGINT) AS n_chars FROM blocks
"""
