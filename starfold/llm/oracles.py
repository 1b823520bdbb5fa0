"""SQL of the operators that it can express, for DuckDB over the same tables."""

from __future__ import annotations

_LOW = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
_WORDS = "regexp_extract_all(" + _LOW + r", '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"


def decontamination(window: int = 10) -> str:
    """Windows of items joined with those of documents; words under a hit are counted once."""
    return f"""
    WITH d AS (SELECT doc_id, coalesce({_WORDS.format('text')}, []) AS ws FROM documents),
    b AS (SELECT DISTINCT CAST(item_id AS VARCHAR) AS item, {_WORDS.format('text')} AS ws FROM benchmark WHERE item_id IS NOT NULL AND text IS NOT NULL),
    bn AS (SELECT item, ws, least({window}, len(ws)) AS n FROM b WHERE len(ws) > 0),
    bk AS (SELECT item, ws, n, unnest(range(1, len(ws) - n + 2)) AS k FROM bn),
    bw AS (SELECT DISTINCT item, n, array_to_string(ws[k:k + n - 1], ' ') AS w FROM bk),
    dk AS (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS k FROM d, (SELECT DISTINCT n FROM bw) m WHERE len(ws) >= n),
    hit AS (SELECT q.doc_id, q.k, q.n, bw.item FROM (SELECT doc_id, k, n, array_to_string(ws[k:k + n - 1], ' ') AS w FROM dk) q JOIN bw ON q.n = bw.n AND q.w = bw.w),
    covered AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(k, k + n)) AS p FROM hit) c GROUP BY doc_id),
    items AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT doc_id, item FROM hit) i GROUP BY doc_id)
    SELECT d.doc_id, CAST(len(d.ws) AS BIGINT) AS n_words, coalesce(c.n_hit, 0) AS n_hit, coalesce(i.n_items, 0) AS n_items,
           sha256(coalesce(i.names, '')) AS items_sha256, coalesce(c.n_hit, 0) > 0 AS contaminated
    FROM d LEFT JOIN covered c ON d.doc_id = c.doc_id LEFT JOIN items i ON d.doc_id = i.doc_id"""


def substring_dedup(length: int = 50) -> str:
    """Every string of ``length`` bytes as hexadecimal digits, cut from short blocks, its least document, and the runs of bytes that are covered."""
    return f"""
    WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
    c AS (SELECT doc_id, place, substr(h, 2 * place + 1, {2 * (500 + length - 1)}) AS h FROM (SELECT doc_id, h, unnest(range(0, greatest(length(h) // 2 - {length - 1}, 0), 500)) AS place FROM d) q),
    s AS (SELECT doc_id, place + k AS k, substr(h, 2 * k + 1, {2 * length}) AS x FROM (SELECT doc_id, place, h, unnest(range(0, length(h) // 2 - {length - 1})) AS k FROM c) q),
    f AS (SELECT x, min(doc_id) AS low FROM s GROUP BY x HAVING count(*) > 1),
    late AS (SELECT s.doc_id, s.k, lag(s.k) OVER (PARTITION BY s.doc_id ORDER BY s.k) AS was FROM s JOIN f ON s.x = f.x WHERE s.doc_id > f.low),
    runs AS (SELECT doc_id, k, sum(CASE WHEN was IS NULL OR k > was + {length} THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY k ROWS UNBOUNDED PRECEDING) AS r FROM late),
    spans AS (SELECT doc_id, r, min(k) AS a, max(k) + {length} AS b FROM runs GROUP BY doc_id, r),
    gaps AS (SELECT doc_id, a, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS from_, a AS to_, b - a AS gone, 1 AS span FROM spans
             UNION ALL SELECT d.doc_id, 1099511627776, coalesce(e.b, 0), length(d.h) // 2, 0, 0 FROM d LEFT JOIN (SELECT doc_id, max(b) AS b FROM spans GROUP BY doc_id) e ON d.doc_id = e.doc_id)
    SELECT d.doc_id, CAST(max(length(d.h)) // 2 AS BIGINT) AS n_bytes, CAST(sum(g.gone) AS BIGINT) AS n_removed, CAST(sum(g.span) AS BIGINT) AS n_spans,
           sha256(unhex(string_agg(substr(d.h, 2 * g.from_ + 1, 2 * (g.to_ - g.from_)), '' ORDER BY g.a))) AS kept_sha256
    FROM d JOIN gaps g ON d.doc_id = g.doc_id GROUP BY d.doc_id"""


def near_duplicates(words: int = 5, threshold: float = 0.8, levels: int = 12) -> str:
    """All pairs with enough common weight, their probability Jaccard term by term, and components by rounds of minima."""
    rounds = ", ".join(
        f"l{k + 1} AS (SELECT e.x AS v, min(l.m) AS m FROM e JOIN l{k} l ON e.y = l.v GROUP BY e.x)" for k in range(levels)
    )
    return f"""
    WITH d AS (SELECT doc_id, text, min(doc_id) OVER (PARTITION BY text) AS first_ FROM documents),
    t AS (SELECT doc_id AS v, {_WORDS.format('text')} AS ws FROM d WHERE doc_id = first_ AND text IS NOT NULL),
    g AS (SELECT v, array_to_string(ws[k:k + least({words}, len(ws)) - 1], ' ') AS s FROM (SELECT v, ws, unnest(range(1, greatest(len(ws) - {words - 1}, 1) + 1)) AS k FROM t WHERE len(ws) > 0) q),
    w AS (SELECT v, s, count(*) AS n FROM g GROUP BY v, s),
    total AS (SELECT v, sum(n) AS n FROM w GROUP BY v),
    c AS (SELECT a.v AS x, b.v AS y, sum(a.n) AS na, sum(b.n) AS nb FROM w a JOIN w b ON a.s = b.s AND a.v < b.v GROUP BY a.v, b.v),
    p AS (SELECT c.x, c.y FROM c JOIN total i ON c.x = i.v JOIN total j ON c.y = j.v WHERE c.na >= {threshold} * i.n - 1e-9 AND c.nb >= {threshold} * j.n - 1e-9),
    u AS (SELECT p.x, p.y, s, max(CASE WHEN w.v = p.x THEN w.n ELSE 0 END) AS a, max(CASE WHEN w.v = p.y THEN w.n ELSE 0 END) AS b FROM p JOIN w ON w.v IN (p.x, p.y) GROUP BY p.x, p.y, s),
    terms AS (SELECT k.x, k.y, k.s, sum(greatest(o.a / k.a, o.b / k.b)) AS z FROM u k JOIN u o ON k.x = o.x AND k.y = o.y WHERE k.a > 0 AND k.b > 0 GROUP BY k.x, k.y, k.s),
    links AS (SELECT x, y FROM terms GROUP BY x, y HAVING sum(1 / z) >= {threshold} - 1e-12),
    e AS (SELECT x, y FROM links UNION SELECT y, x FROM links UNION SELECT v, v FROM t),
    l0 AS (SELECT v, v AS m FROM t), {rounds}
    SELECT d.doc_id, coalesce(l.m, d.doc_id) AS class_id FROM d LEFT JOIN l{levels} l ON d.first_ = l.v AND d.text IS NOT NULL"""


def _least_draw(options: list[tuple[str, float]]) -> str:
    """Name of the earliest of the draws of ``options``."""
    if len(options) == 1:
        return f"'{options[0][0]}'"
    draw = lambda n, w: f"{{'d': -ln((CAST(('0x' || substr(md5(k || '|{n}'), 1, 13)) AS BIGINT) + 0.5) / {1 << 52}.0) / {float(w)}, 'n': '{n}'}}"
    return f"least({', '.join(draw(n, w) for n, w in options)})['n']"


def _descent(tree: list[tuple[str, str, int, float]]) -> tuple[str, str, str]:
    """Expressions of the region, the rack (from ``region``) and the shard (from ``rack``)."""
    from starfold.llm.sharding import _weights

    def under(level: int, parent: str) -> str:
        cases = []
        for name in dict.fromkeys(r[level - 1] for r in tree):
            rows = [r for r in tree if r[level - 1] == name]
            cases.append(f"WHEN '{name}' THEN {_least_draw([(str(n), w) for n, w in _weights(rows, level)])}")
        return f"CASE {parent} {' '.join(cases)} END"

    return _least_draw(_weights(tree, 0)), under(1, "region"), under(2, "rack")


def sharding(shards: int = 24) -> str:
    """Every draw of every level; the checksum of the bytes by the usual table, made here by its rule."""
    from starfold.llm.sharding import grown, layout

    tree = layout(shards)
    a, b, c = _descent(tree)
    x, y, z = _descent(grown(tree))
    step = lambda v: f"CASE WHEN {v} & 1 = 1 THEN xor(3988292384::BIGINT, {v} >> 1) ELSE {v} >> 1 END"
    rounds = ", ".join(f"t{i + 1} AS (SELECT k, {step('v')} AS v FROM t{i})" for i in range(8))
    return f"""
    WITH t0 AS (SELECT range AS k, CAST(range AS BIGINT) AS v FROM range(256)), {rounds},
    crc AS (SELECT list(v ORDER BY k) AS v FROM t8),
    d AS (SELECT doc_id, coalesce(CAST(doc_id AS VARCHAR), 'null') AS k, hex(encode(coalesce(text, ''))) AS h FROM documents),
    q AS (SELECT *, list_transform(regexp_extract_all(h, '..'), lambda x: CAST('0x' || x AS BIGINT)) AS bytes FROM d),
    s AS (SELECT doc_id, k, CAST(length(h) // 2 + 8 AS BIGINT) AS size,
                 xor(4294967295::BIGINT, list_reduce(list_prepend(4294967295::BIGINT, bytes), lambda r, o: xor(r >> 8, crc.v[(xor(r, o) & 255) + 1]))) AS text_crc32 FROM q, crc),
    r0 AS (SELECT *, {a} AS region FROM s), r1 AS (SELECT *, {b} AS rack FROM r0), r2 AS (SELECT * EXCLUDE (region, rack), CAST({c} AS INTEGER) AS shard FROM r1),
    g0 AS (SELECT *, {x} AS region FROM r2), g1 AS (SELECT *, {y} AS rack FROM g0), g2 AS (SELECT * EXCLUDE (region, rack), CAST({z} AS INTEGER) AS grown_shard FROM g1)
    SELECT doc_id, size, text_crc32, 'key' AS law, shard, row_number() OVER (PARTITION BY shard ORDER BY md5(k), doc_id, size, text_crc32) - 1 AS slot, grown_shard FROM g2"""


ORACLES = {
    "op3_decontamination": decontamination(),
    "op5_substring_dedup": substring_dedup(),
    "op7_near_duplicates": near_duplicates(),
    "op9_sharding": sharding(),
}
