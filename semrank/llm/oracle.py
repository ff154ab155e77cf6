"""DuckDB SQL that gives the same rows from the same tables, by plainer ways."""

from __future__ import annotations

from semrank.llm import license_scan, quality_rules

_WORDS = r"regexp_extract_all(coalesce({t}, ''), '[^\x20\x09-\x0D]+')"


def words(t: str = "text") -> str:
    return _WORDS.format(t=t)


OP1 = f"""
WITH d AS (SELECT source, lang, len({words()}) AS n, strlen(text) AS bytes FROM documents),
c AS (
  SELECT source, lang, 'words-1' AS version, n AS tokens FROM d WHERE n >= 10
  UNION ALL
  SELECT source, lang, 'bytes-4', CAST(ceil(bytes / 4.0) AS BIGINT) FROM d WHERE n >= 10)
SELECT source, lang, version, count(*) AS n_docs, CAST(sum(tokens) AS BIGINT) AS n_tokens FROM c GROUP BY ALL
"""

# every pair of neighbouring lines with words that came before, by id and place, goes with the blank lines between
OP3 = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM documents WHERE text IS NOT NULL),
filled AS (
  SELECT doc_id, i, line, row_number() OVER w AS k, lead(line) OVER w AS after, lead(i) OVER w AS j
  FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]') WINDOW w AS (PARTITION BY doc_id ORDER BY i)),
pairs AS (
  SELECT *, first_value(doc_id) OVER p AS first_doc, first_value(k) OVER p AS first_k FROM filled WHERE after IS NOT NULL
  WINDOW p AS (PARTITION BY line, after ORDER BY doc_id, k)),
gone AS (SELECT doc_id, i, j FROM pairs WHERE doc_id <> first_doc OR k - first_k > 1),
cut AS (SELECT DISTINCT l.doc_id, l.i FROM lines l JOIN gone g ON l.doc_id = g.doc_id AND l.i BETWEEN g.i AND g.j),
texts AS (
  SELECT l.doc_id, coalesce(string_agg(line, chr(10) ORDER BY l.i) FILTER (c.i IS NULL), '') AS text, count(c.i) AS n_lines
  FROM lines l LEFT JOIN cut c ON l.doc_id = c.doc_id AND l.i = c.i GROUP BY l.doc_id),
n AS (SELECT doc_id, count(*) AS n_chunks FROM gone GROUP BY doc_id)
SELECT d.doc_id, t.text, coalesce(n_chunks, 0) AS n_chunks_removed, coalesce(n_lines, 0) AS n_lines_removed
FROM documents d LEFT JOIN texts t USING (doc_id) LEFT JOIN n USING (doc_id)
"""

_STOPS = ", ".join(f"'{w}'" for w in sorted(set(quality_rules.STOP_WORDS)))
_VERDICT = " AND ".join(
    f"{r.measure} {op} {bound}" for r in quality_rules.RULES for op, bound in ((">=", r.low), ("<=", r.high)) if bound is not None
)
OP4 = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, {words()} AS w FROM documents),
pos AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS i FROM d),
win AS (
  SELECT doc_id, i, word, string_agg(word, ' ') OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING) AS five,
         count(*) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN CURRENT ROW AND 4 FOLLOWING) AS n,
         lag(word) OVER (PARTITION BY doc_id ORDER BY i) AS prior FROM pos),
rep AS (SELECT *, CASE WHEN n = 5 AND count(*) FILTER (n = 5) OVER (PARTITION BY doc_id, five) > 1 THEN 1 ELSE 0 END AS twice FROM win),
cov AS (SELECT *, max(twice) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS hit FROM rep),
per AS (
  SELECT doc_id, sum(hit) AS n_repeat, sum(length(word)) AS chars, count(*) FILTER (word = prior) AS echoes,
         count(*) FILTER (lower(trim(word, '.,;:!?')) IN ({_STOPS})) AS stops FROM cov GROUP BY doc_id),
lines AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d),
dup AS (SELECT doc_id, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup FROM lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
m AS (
  SELECT d.doc_id, len(w) AS n_words, CAST(coalesce(chars, 0) AS BIGINT) AS word_chars,
         CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols, CAST(coalesce(n_dup, 0) AS BIGINT) AS n_dup_lines,
         CAST(coalesce(n_repeat, 0) AS BIGINT) AS n_repeat_words, coalesce(n_lines, 0) AS n_lines,
         len(regexp_extract_all(t, '!!')) AS shouts, coalesce(stops, 0) AS stops, coalesce(echoes, 0) AS echoes
  FROM d LEFT JOIN per USING (doc_id) LEFT JOIN dup USING (doc_id)),
r AS (
  SELECT *, CASE WHEN n_words > 0 THEN word_chars / n_words ELSE 0.0 END AS mean_word, CASE WHEN n_words > 0 THEN n_symbols / n_words ELSE 0.0 END AS symbols_per_word,
         CASE WHEN n_words > 0 THEN shouts / n_words ELSE 0.0 END AS shouts_per_word, (stops + 1) / (n_words + 20) AS stop_share,
         CASE WHEN n_lines > 0 THEN n_dup_lines / n_lines ELSE 0.0 END AS dup_line_share, CASE WHEN n_words > 0 THEN n_repeat_words / n_words ELSE 0.0 END AS repeat_share,
         CASE WHEN n_words > 0 THEN echoes / n_words ELSE 0.0 END AS echo_share, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, (NOT base_failed AND {_VERDICT}) AS kept FROM r
"""

# every pair of documents that share a shingle, then reachability
OP5 = rf"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
         ELSE list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) END) AS g FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
both_ AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
link AS (SELECT a, b FROM both_ JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 75 * (x.n + y.n - c)),
edge AS (SELECT a, b FROM link UNION ALL SELECT b, a FROM link),
reach(a, b) AS (SELECT a, b FROM edge UNION SELECT r.a, e.b FROM reach r JOIN edge e ON r.b = e.a),
least_ AS (SELECT a, min(b) AS m FROM reach GROUP BY a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, least(d.doc_id, coalesce(m, d.doc_id)) AS component_id, least(d.doc_id, coalesce(m, d.doc_id)) = d.doc_id AS kept
FROM d LEFT JOIN n USING (doc_id) LEFT JOIN least_ ON a = d.doc_id
"""

# here documents are sorted and summed up to the need
OP6 = rf"""
WITH RECURSIVE d AS (
  SELECT doc_id, source, len({words()}) AS size, ('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15))::BIGINT AS pos FROM documents),
s AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, CAST((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1 AS BIGINT) AS weight, (SELECT sum(source_size) FROM s) AS total FROM s),
l AS (
  SELECT *, total - 3 * coalesce(sum(source_size) OVER u, 0) AS left_size, (SELECT sum(weight) FROM w) - coalesce(sum(weight) OVER u, 0) AS left_weight
  FROM w WINDOW u AS (ORDER BY source_size * 6 / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
v AS (SELECT *, CAST(left_size AS DOUBLE) / CAST(left_weight AS DOUBLE) AS level FROM l),
f AS (SELECT level FROM v WHERE CAST(3 * source_size AS DOUBLE) >= level * weight ORDER BY source_size * 6 / weight, source NULLS LAST LIMIT 1),
t AS (SELECT source, source_size, least(CAST(3 * source_size AS DOUBLE), (SELECT level FROM f) * weight) AS target FROM v),
b AS (SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target / source_size) AS BIGINT) ELSE 0 END AS base FROM t),
k AS (SELECT d.source, pos, sum(size) AS at_pos FROM d GROUP BY ALL),
run AS (SELECT source, pos, at_pos, sum(at_pos) OVER (PARTITION BY source ORDER BY pos) AS upto FROM k),
cut AS (
  SELECT r.source, max(pos) FILTER (CAST(upto AS DOUBLE) < target - base * source_size OR CAST(upto AS DOUBLE) - (target - base * source_size) <= (target - base * source_size) - CAST(upto - at_pos AS DOUBLE)) AS cut
  FROM run r JOIN b ON r.source IS NOT DISTINCT FROM b.source GROUP BY r.source)
SELECT doc_id, size, source_size, target, CAST(size * least(3, base + CASE WHEN pos <= coalesce(cut, -1) THEN 1 ELSE 0 END) AS BIGINT) AS taken
FROM d JOIN b ON d.source IS NOT DISTINCT FROM b.source JOIN cut ON d.source IS NOT DISTINCT FROM cut.source
"""

_KNOWN = ", ".join(f"('{license_scan.normal_text(s)}', '{k}')" for k, s in license_scan.SENTENCES.items())


def _licenses() -> str:
    """Rules over a text whose identifiers are each in it once or more: rule by rule, sentences used up in order."""
    steps, last = ["step0 AS (SELECT doc_id, sentence_ids, n_sentences, ',' || sentence_ids || ',' AS j, '' AS names FROM found)"], 0
    for k, (name, ids) in enumerate(license_scan.RULES, 1):
        steps.append(
            f"step{k} AS (SELECT doc_id, sentence_ids, n_sentences, "
            f"CASE WHEN hit THEN regexp_replace(j, '{','.join(ids) if len(ids) == 1 else '.*'.join(ids)}', '#', 'g') ELSE j END AS j, "
            f"CASE WHEN hit AND NOT list_contains(string_split(names, ','), '{name}') THEN CASE WHEN names = '' THEN '{name}' ELSE names || ',{name}' END ELSE names END AS names "
            f"FROM (SELECT *, regexp_matches(j, ',{',(?:.*,)?'.join(ids)},') AS hit FROM step{k - 1}))"
        )
        last = k
    return ", ".join(steps) + f" SELECT doc_id, n_sentences, sentence_ids, names AS licenses FROM step{last}"


OP8 = rf"""
WITH known(s, k) AS (VALUES {_KNOWN}),
cut AS (SELECT doc_id, string_split(regexp_replace(replace(coalesce(text, ''), chr(13), ' '), '\n|([.!?;]) ', '\1' || chr(1), 'g'), chr(1)) AS p FROM documents),
parts AS (SELECT doc_id, unnest(p) AS s, generate_subscripts(p, 1) AS i FROM cut),
hits AS (SELECT doc_id, i, k FROM parts p JOIN known ON trim(regexp_replace(lower(p.s), '[^a-z0-9]+', ' ', 'g')) = known.s),
found AS (
  SELECT d.doc_id, coalesce(string_agg(k, ',' ORDER BY i), '') AS sentence_ids, count(k) AS n_sentences
  FROM documents d LEFT JOIN hits h ON d.doc_id = h.doc_id GROUP BY d.doc_id),
{_licenses()}
"""

_TREE = r"""list_transform(string_split(regexp_replace({t}, '([!-/:-@\[-`{{-~]) ', '\1' || chr(1), 'g'), chr(10)), lambda p: list_transform(string_split(p, chr(1)), lambda x: substr(md5(x), 1, 12)))"""


def _side(name: str) -> str:
    return (
        f"list_transform({name}_l, lambda x: md5(array_to_string(x, ''))) AS {name}_n, list_sort(flatten({name}_l)) AS {name}_f"
    )


def _sections(name: str) -> str:
    ends = f"list_filter(range(1, len({name}_n) + 1), lambda i: i = len({name}_n) OR substr({name}_n[i], 1, 1) IN ('0', '1', '2', '3'))"
    return f"{ends} AS {name}_e"


def _nodes(name: str) -> str:
    return f"list_transform(range(1, len({name}_e) + 1), lambda k: md5(array_to_string({name}_n[(CASE WHEN k = 1 THEN 1 ELSE {name}_e[k - 1] + 1 END):{name}_e[k]], ''))) AS {name}_s"


def _print(name: str) -> str:
    return f"md5(array_to_string({name}_s, '')) || ':' || array_to_string(list_transform({name}_s, lambda x: substr(x, 1, 16)), '.') || ':' || array_to_string(list_transform({name}_l, lambda x: array_to_string(x, '.')), '/')"


def _each(name: str) -> str:
    """Leaves with the number of the repeat, which is the distance from the first of its kind in a sorted list."""
    return f"list_transform(range(1, len({name}_f) + 1), lambda i: {name}_f[i] || '.' || (i - list_position({name}_f, {name}_f[i]))) AS {name}_set"


def _near(other: str) -> str:
    return f"CASE WHEN own_s = {other}_s THEN 1.0 ELSE CAST(2.0 AS DOUBLE) * len(list_intersect(own_set, {other}_set)) / (len(own_set) + len({other}_set)) END AS near_{'edited' if other == 'edit' else 'next'}"


_NAMES = ("own", "edit", "next")
OP10 = f"""
WITH d AS (
  SELECT doc_id, coalesce(text, '') AS t, coalesce(lead(coalesce(text, '')) OVER (ORDER BY doc_id), first_value(coalesce(text, '')) OVER (ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)) AS nx FROM documents),
e AS (SELECT doc_id, length(t) AS n_chars, t, nx, substr(t, 1, length(t) - length(t) // 4) || substr(nx, 1, length(t) // 4) AS ed FROM d),
a AS (SELECT doc_id, n_chars, sha256(ed) AS edited_sha256, {", ".join(_TREE.format(t=t) + f" AS {n}_l" for t, n in zip(("t", "ed", "nx"), _NAMES, strict=True))} FROM e),
b AS (SELECT *, {", ".join(map(_side, _NAMES))} FROM a),
c AS (SELECT *, {", ".join(map(_sections, _NAMES))}, {", ".join(map(_each, _NAMES))} FROM b),
s AS (SELECT *, {", ".join(map(_nodes, _NAMES))} FROM c)
SELECT doc_id, n_chars, edited_sha256, {_print("own")} AS fingerprint, {_print("edit")} AS edited_fingerprint, {_near("edit")}, {_near("next")} FROM s
"""

ORACLES = {
    "op1_token_counts": OP1,
    "op3_line_dedup": OP3,
    "op4_quality_rules": OP4,
    "op5_near_duplicates": OP5,
    "op6_mixing": OP6,
    "op8_license_scan": OP8,
    "op10_fingerprints": OP10,
}
