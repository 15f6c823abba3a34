"""The queries of these operators over the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from suffix_engine.llm import decontaminate, lines, media, mixing, ngram_join, quality, substring, tokens, urls, windows


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_ngram_join": lambda spark, d: ngram_join.components(_documents(spark, d)),
        "op2_domain_mixing": lambda spark, d: mixing.mixing_rates(_documents(spark, d), spark.read.parquet(f"{d}/labels.parquet")),
        "op3_substring_dedup": lambda spark, d: substring.substring_digests(_documents(spark, d)),
        "op4_quality_classifier": lambda spark, d: quality.quality_scores(_documents(spark, d), spark.read.parquet(f"{d}/labels.parquet")),
        "op5_media_columns": lambda spark, d: media.document_media(_documents(spark, d)),
        "op6_line_dedup": lambda spark, d: lines.line_digests(_documents(spark, d)),
        "op8_window_dedup": lambda spark, d: windows.window_digests(_documents(spark, d)),
        "op7_benchmark_decontamination": lambda spark, d: decontaminate.contamination(_documents(spark, d), spark.read.parquet(f"{d}/benchmark.parquet")),
        "op9_url_filter": lambda spark, d: urls.judge(spark.read.parquet(f"{d}/pages.parquet")),
        "op10_token_counts": lambda spark, d: tokens.token_report(_documents(spark, d), public_tokenizers.path("byte_bpe_50k.json")),
    }


LINE_SQL = r"""
WITH l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS i FROM documents),
k AS (SELECT *, translate(trim(line, chr(32) || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
h AS (SELECT key, max(doc_id) AS last FROM k WHERE length(key) >= 20 GROUP BY key HAVING count(DISTINCT doc_id) >= 3),
j AS (SELECT k.*, h.last IS NOT NULL AND h.last <> k.doc_id AS gone FROM k LEFT JOIN h USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM j GROUP BY doc_id
"""

WINDOW_SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
p AS (SELECT doc_id, unnest(range(1, len(w) - 11)) AS i, w FROM d WHERE len(w) >= 13),
s AS (SELECT doc_id, i, array_to_string(w[i:i + 12], ' ') AS win FROM p),
f AS (SELECT win, min(doc_id) AS first FROM s GROUP BY win),
g AS (SELECT DISTINCT s.doc_id, unnest(range(s.i, s.i + 13)) AS i FROM s JOIN f USING (win) WHERE f.first < s.doc_id),
w AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM d),
k AS (SELECT w.*, g.i IS NOT NULL AS gone FROM w LEFT JOIN g ON g.doc_id = w.doc_id AND g.i = w.i),
a AS (SELECT doc_id, count(*) AS n, count(*) FILTER (WHERE gone) AS r, string_agg(word, ' ' ORDER BY i) FILTER (WHERE NOT gone) AS kept FROM k GROUP BY doc_id)
SELECT d.doc_id, coalesce(a.n, 0) AS n_words, coalesce(a.r, 0) AS n_removed, sha256(coalesce(a.kept, '')) AS kept_sha256 FROM d LEFT JOIN a USING (doc_id)
"""


CONTAMINATION_SQL = r"""
WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
i AS (SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
v AS (SELECT item_id, unnest(range(1, greatest(2, len(w) - 11))) AS i, w FROM i WHERE len(w) > 0),
p AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 12], ' ') AS win, len(w[i:i + 12]) AS k FROM v),
n AS (SELECT DISTINCT k FROM p),
e AS (SELECT doc_id, k, unnest(range(1, len(w) - k + 2)) AS i, w FROM d, n WHERE len(w) >= k),
h AS (SELECT e.doc_id, p.item_id, e.k, e.i FROM e JOIN p ON p.k = e.k AND p.win = array_to_string(e.w[e.i:e.i + e.k - 1], ' ')),
x AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + k)) AS j FROM h) GROUP BY doc_id),
y AS (SELECT doc_id, count(DISTINCT item_id) AS n, string_agg(DISTINCT item_id::VARCHAR, ',' ORDER BY item_id::VARCHAR) AS s FROM h GROUP BY doc_id)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(x.n, 0) AS n_hit, coalesce(y.n, 0) AS n_items, sha256(coalesce(y.s, '')) AS items_sha256,
       coalesce(x.n, 0) > 0 AND 20 * coalesce(x.n, 0) >= len(w) AS contaminated
FROM d LEFT JOIN x USING (doc_id) LEFT JOIN y USING (doc_id)
"""


COMPONENT_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
t AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 3], ' ') AS shingle FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 3) + 1)) AS i FROM d WHERE len(w) > 0)),
s AS (SELECT doc_id, count(*) AS n, md5(string_agg(shingle, chr(10) ORDER BY shingle)) AS content FROM t GROUP BY doc_id),
q AS (SELECT content, min(doc_id) AS rep, min(n) AS n, count(*) AS n_equal FROM s GROUP BY content),
b AS (SELECT q.rep, q.n, t.shingle FROM q JOIN t ON t.doc_id = q.rep),
l AS (SELECT x.rep AS u, y.rep AS v FROM b x JOIN b y ON x.shingle = y.shingle AND x.rep < y.rep AND 100 * x.n >= 85 * y.n AND 100 * y.n >= 85 * x.n
      GROUP BY x.rep, y.rep, x.n, y.n HAVING 100 * count(*) >= 85 * (x.n + y.n - count(*))),
e AS (SELECT u, v FROM l UNION ALL SELECT v, u FROM l),
r AS (SELECT rep AS node, rep AS root FROM q UNION SELECT e.v, r.root FROM r JOIN e ON e.u = r.node),
c AS (SELECT node, min(root) AS root FROM r GROUP BY node)
SELECT d.doc_id, coalesce(s.n, 0) AS n_shingles, coalesce(c.root, d.doc_id) AS component_id, coalesce(q.n_equal, 1) AS n_equal
FROM d LEFT JOIN s USING (doc_id) LEFT JOIN q USING (content) LEFT JOIN c ON c.node = q.rep
"""

#: Texts as hexadecimal digits, so that a byte is two characters wherever characters are more than a byte; cut into pieces of 1,000
#: window starts, which only keeps the cutting of windows out of long strings cheap.
SUBSTRING_SQL = r"""
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
p AS (SELECT doc_id, 1000 * c AS base, substr(h, 2000 * c + 1, 2198) AS piece FROM (SELECT doc_id, h, unnest(range(0, length(h) // 2000 + 1)) AS c FROM d)),
x AS (SELECT doc_id, base + j AS i, md5(substr(piece, 2 * j + 1, 200)) AS win FROM (SELECT doc_id, base, piece, unnest(range(0, length(piece) // 2 - 99)) AS j FROM p)),
g AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY win ORDER BY doc_id, i) AS nth FROM x) WHERE nth > 1),
m AS (SELECT doc_id, i, CASE WHEN i - lag(i) OVER o <= 100 THEN 0 ELSE 1 END AS new FROM g WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
n AS (SELECT doc_id, i, sum(new) OVER (PARTITION BY doc_id ORDER BY i) AS span FROM m),
s AS (SELECT doc_id, min(i) AS a, max(i) + 100 AS z FROM n GROUP BY doc_id, span),
b AS (SELECT doc_id, a, z, coalesce(lag(z) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM s),
k AS (SELECT doc_id, sum(z - a) AS removed, count(*) AS spans, max(z) AS last, string_agg(substr(h, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) AS kept FROM b JOIN d USING (doc_id) GROUP BY doc_id)
SELECT doc_id, length(h) // 2 AS n_bytes, coalesce(removed, 0)::BIGINT AS n_removed, coalesce(spans, 0) AS n_spans,
       sha256(unhex(coalesce(kept, '') || substr(h, 2 * coalesce(last, 0) + 1))) AS kept_sha256
FROM d LEFT JOIN k USING (doc_id)
"""


def _url_sql(rules=urls.RULES, branches: int = urls.BRANCHES, depth: int = urls.DEPTH, weight: float = urls.WEIGHT, reject: float = urls.REJECT, different: float = urls.DIFFERENT, support: int = urls.SUPPORT) -> str:
    pick = lambda values: "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{v}'" for (h, p, _), v in values) + " END"
    ordered = sorted(rules, key=lambda r: -len(r[0] + r[1]))
    rule, verdict = pick([(r, r[0] + r[1]) for r in ordered]), pick([(r, r[2]) for r in ordered])
    levels = "".join(
        f"""
s{i} AS (SELECT host AS h, template AS t, s[{i + 1}] AS x, (count(*) FILTER (WHERE ruled = 'block'))::DOUBLE AS b, count(ruled)::DOUBLE AS l FROM l{i} WHERE len(s) > {i} GROUP BY ALL),
n{i} AS (SELECT *, count(*) OVER w AS n, sum(b) OVER w / sum(l) OVER w AS share FROM s{i} WINDOW w AS (PARTITION BY h, t)),
a{i} AS (SELECT *, l > 0 AND abs(b / l - share) <= {different} * sqrt(share * (1 - share) / l) AS alike FROM n{i}),
m{i} AS (SELECT h, t, x, count(*) FILTER (WHERE alike) OVER (PARTITION BY h, t) AS m, n > {branches} OR (alike AND m >= 2) OR (l = 0 AND m >= {support}) AS wild FROM a{i}),
l{i + 1} AS (SELECT l{i}.* EXCLUDE template, template || CASE WHEN len(s) <= {i} THEN '' WHEN wild THEN '/*' ELSE '/' || s[{i + 1}] END AS template FROM l{i} LEFT JOIN m{i} ON host = h AND template = t AND s[{i + 1}] = x),"""
        for i in range(depth)
    )
    return rf"""
WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
a AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
l0 AS (SELECT *, {rule} AS rule, {verdict} AS ruled, list_filter(string_split(path, '/'), lambda x: x <> '') AS s, '' AS template FROM a),{levels}
z AS (SELECT page_id, host, path, rule, ruled, template || CASE WHEN len(s) > {depth} THEN '/**' ELSE '' END AS template FROM l{depth}),
f AS (SELECT host AS h, template AS t, (count(*) FILTER (WHERE ruled = 'block'))::DOUBLE AS b, count(*)::DOUBLE AS n FROM z WHERE ruled IS NOT NULL GROUP BY host, template),
p AS (SELECT coalesce(sum(b) / sum(n), 0) AS prior FROM f),
bad AS (SELECT h, t FROM f, p WHERE (b + {weight} * prior) / (n + {weight}) >= {reject})
SELECT page_id, host, path, rule, coalesce(ruled, CASE WHEN h IS NOT NULL THEN 'block' ELSE 'allow' END) AS verdict, template FROM z LEFT JOIN bad ON host = h AND template = t
"""


def oracle_sql() -> dict[str, str]:
    return {
        "op1_ngram_join": COMPONENT_SQL,
        "op3_substring_dedup": SUBSTRING_SQL,
        "op6_line_dedup": LINE_SQL,
        "op7_benchmark_decontamination": CONTAMINATION_SQL,
        "op8_window_dedup": WINDOW_SQL,
        "op9_url_filter": _url_sql(),
    }
