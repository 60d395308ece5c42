"""DuckDB SQL with the rows of the queries that SQL can express, by brute force."""

from __future__ import annotations

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def words(text: str, pattern: str) -> str:
    return f"regexp_extract_all(translate(coalesce({text}, ''), '{UPPER}', '{LOWER}'), '{pattern}')"


#: Labels spread along edges (a, b) until each node has the smallest it can reach.
SPREAD = """r(node, reach) AS (SELECT a, a FROM edges UNION SELECT e.b, r.reach FROM r JOIN edges AS e ON e.a = r.node WHERE r.reach < e.b),
    comp AS (SELECT node, min(reach) AS comp FROM r GROUP BY node)"""

BASE32 = "array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', CAST(((CAST('0x' || substr(x, CAST((i // 4) * 5 + 1 AS BIGINT), 5) AS BIGINT) >> (15 - 5 * (i % 4))) & 31) + 1 AS BIGINT), 1)), '')"

WARC = f"""WITH d AS (SELECT page_id, coalesce(html, '') AS h, sha1(coalesce(html, '')) AS x, min(page_id) OVER (PARTITION BY coalesce(html, '')) AS first FROM pages)
    SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes, {BASE32} AS payload_digest, CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type, CASE WHEN page_id <> first THEN first END AS refers_to FROM d"""

BARE = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
DECONTAMINATE = f"""WITH bw AS (SELECT item_id, {words('text', BARE)} AS w FROM benchmark),
    win AS (SELECT DISTINCT item_id, n, w[i : i + n - 1] AS win FROM (SELECT item_id, w, least(13, len(w)) AS n, unnest(range(1, len(w) - least(13, len(w)) + 2)) AS i FROM bw WHERE len(w) > 0)),
    sizes AS (SELECT DISTINCT n FROM win),
    dw AS (SELECT doc_id, {words('text', BARE)} AS w FROM documents),
    hits AS (SELECT doc_id, i, n, item_id FROM (SELECT doc_id, i, n, w[i : i + n - 1] AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM dw, sizes WHERE len(w) >= n)) JOIN win USING (win, n)),
    places AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hits) GROUP BY doc_id),
    items AS (SELECT doc_id, count(*) AS n_items, sha256(string_agg(item, ',' ORDER BY item)) AS digest FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hits) GROUP BY doc_id)
    SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, coalesce(digest, sha256('')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w) AS contaminated FROM dw LEFT JOIN places USING (doc_id) LEFT JOIN items USING (doc_id)"""

SPACED = r"[^\x20\x09-\x0D]+"
MINHASH = f"""WITH RECURSIVE dw AS (SELECT doc_id, {words('text', SPACED)} AS w FROM documents),
    s AS (SELECT DISTINCT doc_id, w[i : i + least(5, len(w)) - 1] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - least(5, len(w)) + 2)) AS i FROM dw WHERE len(w) > 0)),
    n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
    shared AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS k FROM s AS x JOIN s AS y ON x.g = y.g AND x.doc_id < y.doc_id GROUP BY 1, 2),
    links AS (SELECT a, b FROM shared JOIN n AS p ON p.doc_id = a JOIN n AS q ON q.doc_id = b WHERE 100 * k >= 85 * (p.n + q.n - k)),
    edges AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
    {SPREAD}
    SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_shingles, coalesce(comp, doc_id) AS component_id, coalesce(comp, doc_id) = doc_id AS kept FROM dw LEFT JOIN n USING (doc_id) LEFT JOIN comp ON node = doc_id"""

VECTORS = f"""WITH RECURSIVE v AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
    links AS (SELECT x.vec_id AS a, y.vec_id AS b FROM v AS x JOIN v AS y ON x.label = y.label AND x.vec_id < y.vec_id WHERE list_inner_product(x.e, y.e) / sqrt(list_inner_product(x.e, x.e)) / sqrt(list_inner_product(y.e, y.e)) >= 0.93::DOUBLE),
    edges AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
    {SPREAD}
    SELECT vec_id, CAST(coalesce(k, 0) AS BIGINT) AS n_links, coalesce(comp, vec_id) AS component_id, coalesce(comp, vec_id) = vec_id AS kept FROM embeddings LEFT JOIN (SELECT a, count(*) AS k FROM edges GROUP BY a) ON a = vec_id LEFT JOIN comp ON node = vec_id"""


def url_sql() -> str:
    """The rules, and the template tree level by level."""
    from .url_templates import BAD_WORDS, KINDS_DIFFER, LABELS_DIFFER, PRIOR_WEIGHT, RULES, THRESHOLD
    from .url_templates import SQL_LEVELS as LEVELS

    ranked = sorted(RULES, key=lambda r: (-len(r[1] + r[2]), r[1] + r[2]))
    fits = lambda h, p: f"(host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}')"
    rule = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{h}{p}'" for _, h, p in ranked) + " END"
    said = "CASE " + " ".join(f"WHEN {fits(h, p)} THEN '{k}'" for k, h, p in ranked) + " END"

    def chi(own, rest):
        a, b = f"({' + '.join(own)})", f"({' + '.join(rest)})"
        cells = " + ".join(f"CASE WHEN {x} + {y} = 0 THEN 0 ELSE pow({x} * {b} - {y} * {a}, 2) / ({x} + {y}) END" for x, y in zip(own, rest))
        return f"CASE WHEN {a} = 0 OR {b} = 0 THEN 0 ELSE ({cells}) / ({a} * {b}) END"

    sums = ("n", "labelled", "bad", "ends", "numbers", "words")
    listed = f"list_has_any(string_split_regex(host, '[.-]'), [{', '.join(repr(w) for w in BAD_WORDS)}])"
    steps = [f"""m AS (SELECT page_id, host, path, {rule} AS rule, {said} AS said, CASE WHEN {said} IS NOT NULL THEN {said} WHEN {listed} THEN 'block' END AS taught, regexp_replace(path, '[0-9]+', '#', 'g') AS shape FROM (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*'), '{UPPER}', '{LOWER}') AS host, regexp_extract(substr(rest, length(regexp_extract(rest, '^[^/?#]*')) + 1), '^[^?#]*') AS path FROM (SELECT page_id, coalesce(CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END, '') AS rest FROM pages)))""",
        "n1 AS (SELECT host, shape, CAST(count(*) AS DOUBLE) AS n, CAST(count(taught) AS DOUBLE) AS labelled, CAST(count(*) FILTER (taught = 'block') AS DOUBLE) AS bad, string_split(shape, '/') AS segs, '' AS template FROM m GROUP BY host, shape)"]
    for d in range(2, LEVELS + 2):
        labels = chi(("bad", "(labelled - bad)"), ("(all_bad - bad)", "(all_labelled - labelled - all_bad + bad)"))
        kinds = chi(("ends", "numbers", "words"), ("(all_ends - ends)", "(all_numbers - numbers)", "(all_words - words)"))
        steps += [f"h{d} AS (SELECT *, coalesce(segs[{d}], '') AS seg, CASE WHEN segs[{d + 1}] IS NULL THEN n ELSE 0 END AS ends, CASE WHEN contains(coalesce(segs[{d + 1}], ''), '#') THEN n ELSE 0 END AS numbers, n - CASE WHEN segs[{d + 1}] IS NULL THEN n ELSE 0 END - CASE WHEN contains(coalesce(segs[{d + 1}], ''), '#') THEN n ELSE 0 END AS words FROM n{d - 1})",
            f"b{d} AS (SELECT host, template, seg, {', '.join(f'sum({c}) AS {c}' for c in sums)} FROM h{d} GROUP BY host, template, seg)",
            f"p{d} AS (SELECT host, template, count(*) AS width, {', '.join(f'sum({c}) AS all_{c}' for c in sums)} FROM b{d} GROUP BY host, template)",
            f"c{d} AS (SELECT host, template, seg, CASE WHEN seg = '' OR contains(seg, '#') OR width = 1 OR {labels} >= {LABELS_DIFFER} OR {kinds} >= {KINDS_DIFFER} THEN seg ELSE '*' END AS out FROM b{d} JOIN p{d} USING (host, template))",
            f"n{d} AS (SELECT host, shape, n, labelled, bad, segs, CASE WHEN len(segs) >= {d} THEN template || '/' || out ELSE template END AS template FROM h{d} JOIN c{d} USING (host, template, seg))"]
    last = f"n{LEVELS + 1}"
    steps += [f"f AS (SELECT host, shape, n, labelled, bad, template FROM {last})",
        "g AS (SELECT CASE WHEN coalesce(sum(labelled), 0) > 0 THEN sum(bad) / sum(labelled) ELSE 0 END AS share FROM f)",
        f"j AS (SELECT host, template, sum(labelled) > 0 AND (sum(bad) + {PRIOR_WEIGHT} * any_value(share)) / (sum(labelled) + {PRIOR_WEIGHT}) >= {THRESHOLD} AS rejected FROM f, g GROUP BY host, template)"]
    return f"WITH {', '.join(steps)} SELECT page_id, m.host, path, rule, coalesce(said, CASE WHEN rejected THEN 'block' ELSE 'allow' END) AS verdict FROM m LEFT JOIN f ON f.host = m.host AND f.shape = m.shape LEFT JOIN j ON j.host = f.host AND j.template = f.template"


ORACLE_SQL = {"op2_warc": WARC, "op3_minhash": MINHASH, "op5_url_templates": url_sql(), "op7_vector_graph": VECTORS, "op8_decontaminate": DECONTAMINATE}
