"""DuckDB SQL for the operators that SQL can express."""

from __future__ import annotations

from derivatrace.llm import mixing, quality, url_filter

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
WORDS = r"[^\x20\x09-\x0D]+"
LETTERS = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def mix(seed: int = 7) -> str:
    cases = " ".join(f"WHEN {i} THEN {w}" for i, w in enumerate(mixing.WEIGHTS))
    return f"""WITH s AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '{WORDS}')) AS BIGINT) AS size FROM documents),
t AS (SELECT source, CAST(sum(size) AS BIGINT) AS total, CASE (row_number() OVER (ORDER BY source NULLS LAST) - 1) % {len(mixing.WEIGHTS)} {cases} END AS w FROM s GROUP BY source),
-- With the sources in order of cap by weight, all before a source being full, what is left by weight:
r AS (SELECT *, {mixing.MOST} * total / w AS ratio, ({mixing.SHARE} * sum(total) OVER () - coalesce(sum({mixing.MOST} * total) OVER (ORDER BY {mixing.MOST} * total / w, source ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / sum(w) OVER (ORDER BY {mixing.MOST} * total / w, source ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS each FROM t),
l AS (SELECT min_by(each, ratio) AS each FROM r WHERE each <= ratio),
p AS (SELECT t.*, least({mixing.MOST} * total, l.each * w) AS target, CAST(CAST('0x' || substr(md5('{seed}' || coalesce('=' || source, '')), 1, 12) AS BIGINT) AS DOUBLE) / 281474976710656.0 AS shift FROM t, l),
o AS (SELECT s.*, p.total AS source_size, p.target, p.shift, CASE WHEN p.total > 0 THEN p.target / p.total ELSE 0 END AS rate, row_number() OVER (PARTITION BY s.source ORDER BY s.size, s.doc_id) - 1 AS rank FROM s JOIN p ON s.source IS NOT DISTINCT FROM p.source),
c AS (SELECT *, CAST(least(floor(shift + (rank + 1) * rate) - floor(shift + rank * rate), ceil(rate)) AS BIGINT) AS copies FROM o)
SELECT doc_id, size, source_size, target, copies * size AS taken, copies FROM c"""


def contamination() -> str:
    words = lambda c: f"regexp_extract_all(translate(coalesce({c}, ''), '{UPPER}', '{LOWER}'), '{LETTERS}')"
    return f"""WITH dw AS (SELECT doc_id, {words('text')} AS w FROM documents), bw AS (SELECT item_id, {words('text')} AS w FROM benchmark),
win AS (SELECT DISTINCT item_id, array_to_string(w[i:i + 9], ' ') AS g, least(len(w), 10) AS n FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM bw WHERE len(w) > 0) t),
dg AS (SELECT doc_id, i, n, array_to_string(w[i:i + n - 1], ' ') AS g FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM dw, (SELECT DISTINCT n FROM win) sizes WHERE len(w) >= n) t),
hits AS (SELECT doc_id, i, dg.n, item_id FROM dg JOIN win ON dg.g = win.g AND dg.n = win.n),
covered AS (SELECT doc_id, count(DISTINCT pos) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS pos FROM (SELECT DISTINCT doc_id, i, n FROM hits) u) v GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS listed FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) u GROUP BY doc_id)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(listed, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM dw LEFT JOIN covered USING (doc_id) LEFT JOIN items USING (doc_id)"""


def quality_rules(alpha: float = 0.02, delta: float = 0.05) -> str:
    part = lambda a, b: f"CASE WHEN {b} > 0 THEN least(1.0, CAST({a} AS DOUBLE) / {b}) ELSE 0.0 END"
    formulas = {
        "symbols": part("n_symbols", "word_chars"), "dup_lines": part("n_dup_lines", "n_lines"), "repeats": part("n_repeat_words", "n_words"), "shouting": part("n_upper", "word_chars"),
        "short_lines": "CASE WHEN n_lines > 3 THEN greatest(0.0, 1.0 - CAST(n_words AS DOUBLE) / (n_lines * 8)) ELSE 0.0 END",
    }
    steps = len(quality.GRID)
    long = " UNION ALL ".join(f"SELECT doc_id, lang, {j} AS m, {f} AS v FROM d" for j, f in enumerate(formulas.values()))
    return f"""WITH t AS (SELECT doc_id, lang, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '{WORDS}') AS w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines FROM documents),
g AS (SELECT doc_id, i, w[i:i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM t) u),
again AS (SELECT doc_id, count(DISTINCT pos) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS pos FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, g) AS c FROM g) u WHERE c > 1) v GROUP BY doc_id),
c AS (SELECT t.doc_id, lang, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars, CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(length(regexp_replace(text, '[^A-Z]', '', 'g')) AS BIGINT) AS n_upper, CAST(len(lines) AS BIGINT) AS n_lines, CAST(len(lines) - len(list_distinct(lines)) AS BIGINT) AS n_dup_lines, coalesce(n, 0) AS n_repeat_words FROM t LEFT JOIN again USING (doc_id)),
d AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM c),
v AS ({long}),
marked AS (SELECT doc_id, min(quality) AS good FROM labels WHERE quality IS NOT NULL GROUP BY doc_id),
held AS (SELECT v.doc_id, v.lang, m, CAST(floor(v.v * {steps} + 1e-9) AS INT) AS b, good FROM v JOIN d USING (doc_id) LEFT JOIN marked USING (doc_id) WHERE NOT base_failed),
-- The list of rules, from bad and unlabelled texts: for each measure the least cutoff of the greatest gain, and before it the highest of half that gain or more.
shares AS (SELECT lang, m, s.b, count(*) FILTER (good <> 1 AND h.b >= s.b) / nullif(count(*) FILTER (good <> 1), 0) - coalesce(count(*) FILTER (good IS NULL AND h.b >= s.b) / nullif(count(*) FILTER (good IS NULL), 0), 0) AS gain FROM held h, range(1, {steps + 1}) s(b) WHERE good IS DISTINCT FROM 1 GROUP BY ALL),
tops AS (SELECT lang, m, max(gain) AS g FROM shares WHERE gain IS NOT NULL GROUP BY ALL HAVING max(gain) >= {quality.LEAST_GAIN}),
cuts AS (SELECT t.lang, t.m, t.g, max(b) FILTER (gain >= g * 0.5) AS hi, max(b) FILTER (gain >= g) AS lo FROM tops t JOIN shares s ON s.lang IS NOT DISTINCT FROM t.lang AND s.m = t.m GROUP BY ALL),
listed AS (SELECT lang, m, unnest(list_distinct([hi, lo])) AS b, g FROM cuts),
rules AS (SELECT lang, m, b, row_number() OVER (PARTITION BY lang ORDER BY g DESC, m, b DESC) AS i FROM listed),
-- Good texts test them in that order; a rule is held to all that it and those before it reject.
first AS (SELECT h.doc_id, h.lang, min(i) AS i FROM held h JOIN rules r ON r.lang IS NOT DISTINCT FROM h.lang AND r.m = h.m AND h.b >= r.b WHERE good = 1 GROUP BY h.doc_id, h.lang),
size AS (SELECT lang, count(DISTINCT doc_id) AS n, count(*) OVER () AS strata FROM held WHERE good = 1 GROUP BY lang),
tests AS (SELECT r.lang, r.m, r.b, r.i, n, strata, (SELECT count(*) FROM first f WHERE f.lang IS NOT DISTINCT FROM r.lang AND f.i <= r.i) AS k FROM rules r JOIN size ON size.lang IS NOT DISTINCT FROM r.lang),
passed AS (SELECT *, k <= n * {alpha!r} AND (SELECT sum(exp(lgamma(n + 1) - lgamma(j + 1) - lgamma(n - j + 1) + j * ln({alpha!r}) + (n - j) * ln(1 - {alpha!r}))) FROM range(0, k + 1) r(j)) <= {delta!r} / strata AS ok FROM tests),
sure AS (SELECT lang, m, min(b) / {float(steps)} AS cut FROM passed p WHERE NOT EXISTS (SELECT 1 FROM passed q WHERE q.lang IS NOT DISTINCT FROM p.lang AND q.i <= p.i AND NOT q.ok) GROUP BY lang, m),
bad AS (SELECT DISTINCT v.doc_id FROM v JOIN sure ON v.lang IS NOT DISTINCT FROM sure.lang AND v.m = sure.m AND v.v >= cut)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND bad.doc_id IS NULL AS kept FROM d LEFT JOIN bad USING (doc_id)"""


def urls(depth: int = 3, most_children: int = 50, rare: float = 0.2, z: float = 2.326, least_branch: int = 10, weight: float = 10.0, least_labels: int = 10, least_coverage: float = 0.25, reject_at: float = 0.9) -> str:
    fits = lambda r: f"(host = '{r.host}' OR ends_with(host, '.{r.host}')) AND starts_with(path, '{r.path}')"
    order = sorted(url_filter.RULES, key=lambda r: (len(r.text), len(r.host), r.verdict == "block"), reverse=True)
    case = lambda value: "CASE " + " ".join(f"WHEN {fits(r)} THEN '{value(r)}'" for r in order) + " END"
    end = "(\\.[A-Za-z][A-Za-z0-9]{0,4})$"

    def kind(s: str) -> str:
        stem = f"regexp_replace({s}, '{end}', '')"
        return f"""(CASE WHEN regexp_matches({stem}, '^\\d+$') THEN '{{n}}' WHEN regexp_matches({stem}, '^\\d{{4}}-\\d{{2}}(-\\d{{2}})?$') THEN '{{date}}' WHEN regexp_matches({stem}, '^[0-9A-Fa-f-]{{8,}}$') AND regexp_matches({stem}, '\\d') THEN '{{hex}}' WHEN regexp_matches({stem}, '\\d') AND length({stem}) >= 12 THEN '{{mixed}}' ELSE {stem} END) || regexp_extract({s}, '{end}', 1)"""

    def form(i: int) -> str:
        return f"CASE WHEN len(segs) < {i} THEN '' ELSE {kind(f'segs[{i}]')} END AS t{i}"

    rest = f"CASE WHEN len(segs) > {depth} THEN '/' || array_to_string(list_transform(segs[{depth + 1}:], lambda x: {kind('x')}), '/') ELSE '' END AS t{depth + 1}"
    part = "(2.0 / (9.0 * (forms - 1)))"
    limit = f"CASE WHEN forms > 1 THEN (forms - 1) * pow(1.0 - {part} + {z} * sqrt{part}, 3.0) ELSE 0 END + 1e-6"
    levels = [f"t{i}" for i in range(1, depth + 2)]
    ctes = [
        f"u AS (SELECT page_id, translate(regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 1), '{UPPER}', '{LOWER}') AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)([^?#]*)', 2) AS path FROM pages)",
        f"r AS (SELECT *, {case(lambda r: r.text)} AS rule, {case(lambda r: r.verdict)} AS label, string_split(regexp_replace(path, '^/', ''), '/') AS segs FROM u)",
        f"p AS (SELECT page_id, host, path, rule, label, {', '.join(form(i) for i in range(1, depth + 1))}, {rest} FROM r)",
        f"l0 AS (SELECT host, {', '.join(levels)}, count(*) AS n, count(label) AS labelled, count(*) FILTER (label = 'block') AS blocked FROM p GROUP BY ALL)",
    ]
    parents = ["host"]
    for i in range(1, depth + 1):
        up, seg, nxt, src = ", ".join(parents), f"t{i}", f"t{i + 1}", f"l{i - 1}"
        ctes += [
            f"k{i} AS (SELECT {up}, count(*) AS kids, sum(kn) AS total, max(kn) AS top FROM (SELECT {up}, {seg}, sum(n) AS kn FROM {src} GROUP BY ALL) a GROUP BY ALL HAVING count(*) > {most_children} AND max(kn) <= {rare} * sum(kn))",
            f"v{i} AS (SELECT a.*, CASE WHEN k.kids IS NOT NULL AND {seg} <> '' THEN '*' ELSE {seg} END AS n{i} FROM {src} a LEFT JOIN k{i} k USING ({up}))",
            f"c{i} AS (SELECT {up}, n{i}, {nxt}, sum(n) AS c FROM v{i} GROUP BY ALL)",
            f"q{i} AS (SELECT {up}, {nxt}, sum(c) AS pc FROM c{i} GROUP BY ALL)",
            f"s{i} AS (SELECT {up}, sum(pc) AS pn, count(*) AS forms FROM q{i} GROUP BY ALL)",
            f"x{i} AS (SELECT {up}, n{i}, sum(CAST(c AS DOUBLE) * c / pc) AS x, sum(c) AS bn FROM c{i} JOIN q{i} USING ({up}, {nxt}) GROUP BY ALL)",
            f"m{i} AS (SELECT {up}, n{i}, true AS alike FROM x{i} JOIN s{i} USING ({up}) WHERE n{i} <> '' AND bn >= {least_branch} AND x * pn / bn - bn <= {limit} QUALIFY count(*) OVER (PARTITION BY {up}) > 1)",
            f"l{i} AS (SELECT a.* EXCLUDE (n{i}), CASE WHEN m.alike THEN '~' ELSE a.n{i} END AS n{i} FROM v{i} a LEFT JOIN m{i} m USING ({up}, n{i}))",
        ]
        parents.append(f"n{i}")
    path = ", ".join([*[f"n{i}" for i in range(1, depth + 1)], f"t{depth + 1}"])
    ctes += [
        f"g AS (SELECT host, {path}, sum(n) AS n, sum(labelled) AS l, sum(blocked) AS b FROM l{depth} GROUP BY ALL)",
        "h AS (SELECT host, sum(labelled) AS hl, sum(blocked) AS hb FROM l0 GROUP BY host)",
        f"j AS (SELECT g.*, (b + {weight} * (hb + {0.5 * weight}) / (hl + {weight})) / (l + {weight}) >= {reject_at} AND l >= {least_labels} AND l >= {least_coverage} * n AS reject FROM g JOIN h USING (host))",
        f"f AS (SELECT host, {', '.join(levels)}, reject, concat_ws('/', host, {', '.join(f'CASE WHEN {c} <> {chr(39) * 2} THEN {c} END' for c in path.split(', '))}) AS template FROM l{depth} JOIN j USING (host, {path}))",
    ]
    return "WITH " + ",\n".join(ctes) + f"\nSELECT page_id, host, path, rule, coalesce(label, CASE WHEN reject THEN 'block' ELSE 'allow' END) AS verdict, template FROM p LEFT JOIN f USING (host, {', '.join(levels)})"
