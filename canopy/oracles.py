"""DuckDB SQL of the forests, and of small patterns in them."""

from __future__ import annotations

KEYS = {"region": ["r"], "nation": ["r", "n"], "customer": ["r", "n", "c"], "order": ["r", "n", "c", "o"], "line": ["r", "n", "c", "o", "l"]}


def star(tenths: int = 10) -> str:
    """CTEs up to ``nodes(tree_id, begin, end, level, parent, label, keys)`` of the star hierarchy."""
    parts = [
        "SELECT r_regionkey::BIGINT r, -1 n, -1 c, -1 o, -1 l, -1 a, 0 lv, 'region' label FROM region",
        "SELECT n_regionkey, n_nationkey, -1, -1, -1, -1, 1, 'nation' FROM nation",
        "SELECT r, n, c, -1, -1, -1, 2, 'customer' FROM cust",
        "SELECT r, n, c, -1, -1, 0, 3, 'seg=' || seg FROM cust",
        "SELECT r, n, c, o, -1, -1, 3, 'order' FROM ord",
        "SELECT r, n, c, o, -1, 0, 4, 'status=' || status FROM ord",
        "SELECT r, n, c, o, -1, 1, 4, 'prio=' || prio FROM ord",
        "SELECT r, n, c, o, l, -1, 4, 'line' FROM line",
        "SELECT r, n, c, o, l, 0, 5, 'flag=' || flag FROM line",
        "SELECT r, n, c, o, l, 1, 5, 'ls=' || ls FROM line",
    ]
    over = {k: f"(PARTITION BY {', '.join(v)})" for k, v in KEYS.items()}
    size = " ".join(f"WHEN label = '{k}' THEN count(*) OVER {w}" for k, w in over.items())
    # the holder of a row is the first row that shares the holder's keys
    up = {"nation": "region", "customer": "nation", "order": "customer", "line": "order"}
    parent = " ".join(f"WHEN label = '{k}' THEN min(b) OVER {over[h]}" for k, h in up.items())
    leaf = " ".join(f"WHEN a >= 0 AND lv = {lv} THEN min(b) OVER {over[h]}" for lv, h in ((3, "customer"), (4, "order"), (5, "line")))
    return f"""
    cust AS (SELECT n_regionkey r, n_nationkey n, c_custkey c, c_mktsegment seg FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE c_custkey % 10 < {tenths}),
    ord AS (SELECT r, n, c, o_orderkey o, o_orderstatus status, o_orderpriority prio FROM orders JOIN cust ON o_custkey = c),
    line AS (SELECT r, n, c, o, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_returnflag, l_linestatus, l_quantity, l_extendedprice) l,
                    l_returnflag flag, l_linestatus ls FROM lineitem JOIN ord ON l_orderkey = o),
    raw AS ({' UNION ALL '.join(parts)}),
    placed AS (SELECT *, 2 * (row_number() OVER (PARTITION BY r ORDER BY n, c, o, l, a) - 1) - lv AS b FROM raw),
    nodes AS (SELECT r AS tree_id, b AS "begin", b + 2 * (CASE {size} ELSE 1 END) - 1 AS "end", lv AS level,
                     CASE {parent} {leaf} END AS parent, label, r, n, c, o, l, a FROM placed)"""


def star_pairs(uppers: tuple[str, ...] = tuple(KEYS)) -> str:
    """CTE ``pairs(t, a, ae, al, d, de, dl)`` of ancestor-descendant pairs below the given labels."""
    on = lambda k: " AND ".join(f"u.{c} = v.{c}" for c in KEYS[k])
    parts = [f"SELECT u.tree_id t, u.\"begin\" a, u.\"end\" ae, u.label al, v.\"begin\" d, v.\"end\" de, v.label dl FROM nodes u JOIN nodes v ON {on(k)} AND v.\"begin\" > u.\"begin\" WHERE u.label = '{k}'" for k in uppers]
    return f"pairs AS ({' UNION ALL '.join(parts)})"


def dialogue() -> str:
    """CTEs up to ``nodes`` of conversations: every turn below the one before, each with a length leaf first."""
    return """
    turns AS (SELECT conv_id t, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, coalesce(text, '')) k, count(*) OVER (PARTITION BY conv_id) n,
                     coalesce(role, 'none') role, coalesce(length(text), 0) size FROM conversations WHERE conv_id IS NOT NULL AND turn IS NOT NULL),
    nodes AS (
      SELECT DISTINCT t AS tree_id, 0 AS "begin", 2 * (2 * n + 1) - 1 AS "end", 0 AS level, NULL::BIGINT AS parent, 'conv' AS label FROM turns
      UNION ALL SELECT t, 2 * (2 * k - 1) - k, 2 * (2 * k - 1) - k + 2 * (2 * (n - k) + 2) - 1, k, CASE WHEN k = 1 THEN 0 ELSE 2 * (2 * k - 3) - (k - 1) END, role FROM turns
      UNION ALL SELECT t, 2 * (2 * k) - (k + 1), 2 * (2 * k) - (k + 1) + 1, k + 1, 2 * (2 * k - 1) - k, 'len=' || CASE WHEN size > 0 THEN length(size::VARCHAR) ELSE 0 END FROM turns)"""


def dialogue_pairs() -> str:
    """CTE ``pairs`` of conversations after ``turns``, by equal keys: the turns above are 1 to k - 1."""
    return """
    tops AS (SELECT t, k, role, 2 * (2 * k - 1) - k AS b, 2 * (2 * k - 1) - k + 2 * (2 * (n - k) + 2) - 1 AS e, 2 * (2 * n + 1) - 1 AS whole, 'len=' || CASE WHEN size > 0 THEN length(size::VARCHAR) ELSE 0 END AS leaf FROM turns),
    lower AS (SELECT t, k, whole, b AS d, e AS de, role AS dl, k - 1 AS above FROM tops UNION ALL SELECT t, k, whole, 4 * k - (k + 1), 4 * k - k, leaf, k FROM tops),
    each_above AS (SELECT t, d, de, dl, unnest(range(1, above + 1)) AS k FROM lower),
    pairs AS (SELECT t, 0 AS a, whole AS ae, 'conv' AS al, d, de, dl FROM lower UNION ALL SELECT t, b, e, role, d, de, dl FROM each_above JOIN tops USING (t, k))"""


def encoded() -> str:
    """CTEs up to ``nodes`` and ``pairs`` from ``edges(tree, id, parent, label, o)``; needs WITH RECURSIVE."""
    return """
    walk AS (SELECT tree, id, label, [{'o': o, 'id': id}] AS path, [id] AS line FROM edges WHERE parent IS NULL
      UNION ALL SELECT e.tree, e.id, e.label, list_append(w.path, {'o': e.o, 'id': e.id}), list_append(w.line, e.id) FROM walk w JOIN edges e ON e.tree = w.tree AND e.parent = w.id),
    sizes AS (SELECT tree, a AS id, count(*) AS n FROM (SELECT tree, unnest(line) AS a FROM walk) GROUP BY tree, a),
    ranked AS (SELECT tree, id, label, line, (len(line) - 1)::INT AS lv, (2 * (row_number() OVER (PARTITION BY tree ORDER BY path) - 1) - (len(line) - 1))::BIGINT AS b FROM walk),
    coded AS (SELECT r.tree, r.id, r.label, r.line, r.lv, r.b, (r.b + 2 * n - 1)::BIGINT AS e FROM ranked r JOIN sizes s ON r.tree = s.tree AND r.id = s.id),
    nodes AS (SELECT x.tree AS tree_id, x.b AS "begin", x.e AS "end", x.lv AS level, up.b AS parent, x.label FROM coded x LEFT JOIN coded up ON up.tree = x.tree AND up.id = x.line[len(x.line) - 1] AND x.lv > 0),
    links AS (SELECT tree, b AS d, e AS de, label AS dl, unnest(line[1:len(line) - 1]) AS id FROM coded),
    pairs AS (SELECT l.tree AS t, u.b AS a, u.e AS ae, u.label AS al, l.d, l.de, l.dl FROM links l JOIN coded u ON u.tree = l.tree AND u.id = l.id)"""


def navigation_edges(stages: list[str], week: int, epoch: int, gap_s: int | None = None, keep: int = 100) -> str:
    """CTE ``edges`` of visits: a user's events of one week or, with ``gap_s``, up to a longer pause."""
    rank = f"CASE event_type {' '.join(f"WHEN '{x}' THEN {k}" for k, x in enumerate(stages))} ELSE {len(stages)} END"
    stamped = f"SELECT user_id, event_id AS id, event_type AS label, epoch_us(ts::TIMESTAMP) AS o, {rank} AS s FROM events"
    if gap_s is None:
        visits = f"e0 AS (SELECT user_id * 100000 + floor((o / 1000000 - {epoch}) / {week})::BIGINT AS tree, id, label, o, s FROM ({stamped}))"
    else:
        visits = f"""e1 AS (SELECT *, CASE WHEN o - lag(o) OVER (PARTITION BY user_id ORDER BY o, id) > {gap_s * 1_000_000} THEN 1 ELSE 0 END AS cut FROM ({stamped})),
    e0 AS (SELECT (user_id * 100000 + sum(cut) OVER (PARTITION BY user_id ORDER BY o, id))::BIGINT AS tree, id, label, o, s FROM e1)"""
    chosen = "" if keep == 100 else f" WHERE ('0x' || substr(md5(tree::VARCHAR), 1, 8))::BIGINT % 100 < {keep}"
    return f"""
    {visits}, e AS (SELECT * FROM e0{chosen}),
    up AS (SELECT tree, id, arg_max(pid, (po, pid)) AS parent FROM (
             SELECT x.tree, x.id, y.id AS pid, y.o AS po FROM e x JOIN e y ON x.tree = y.tree AND y.s < x.s AND (y.o, y.id) < (x.o, x.id)) GROUP BY tree, id),
    edges AS (SELECT e.tree, e.id, coalesce(up.parent, -1) AS parent, label, o FROM e LEFT JOIN up ON e.tree = up.tree AND e.id = up.id
              UNION ALL SELECT DISTINCT tree, -1, NULL, 'visit', 0 FROM e)"""


def session_edges(stages: list[str], gap_s: int) -> str:
    """CTE ``edges`` of session trees: events under the gap from the one before are one session."""
    rank = f"CASE event_type {' '.join(f"WHEN '{x}' THEN {k}" for k, x in enumerate(stages))} ELSE {len(stages)} END"
    return f"""
    e1 AS (SELECT user_id, event_id AS id, event_type AS label, epoch_us(ts::TIMESTAMP) AS o, {rank} AS s FROM events),
    e2 AS (SELECT *, CASE WHEN o - lag(o) OVER (PARTITION BY user_id ORDER BY o, id) < {gap_s * 1_000_000} THEN 0 ELSE 1 END AS cut FROM e1),
    e3 AS (SELECT user_id, id, label, o, s, sum(cut) OVER (PARTITION BY user_id ORDER BY o, id) AS k FROM e2),
    e AS (SELECT dense_rank() OVER (ORDER BY user_id, k) AS tree, id, label, o, s FROM e3),
    up AS (SELECT tree, id, arg_max(pid, (po, pid)) AS parent FROM (
             SELECT x.tree, x.id, y.id AS pid, y.o AS po FROM e x JOIN e y ON x.tree = y.tree AND y.s < x.s AND (y.o, y.id) < (x.o, x.id)) GROUP BY tree, id),
    edges AS (SELECT e.tree, e.id, coalesce(up.parent, -1) AS parent, label, o FROM e LEFT JOIN up ON e.tree = up.tree AND e.id = up.id
              UNION ALL SELECT DISTINCT tree, -1, NULL, 'visit', 0 FROM e)"""


def text_edges() -> str:
    """CTE ``edges`` of documents: lines, sentences by the digits of their length, and tags."""
    digits = lambda x: f"CASE WHEN length({x}) > 0 THEN length(length({x})::VARCHAR) ELSE 0 END"
    return f"""
    docs AS (SELECT doc_id AS tree, coalesce(text, '') AS text, lang FROM documents WHERE doc_id IS NOT NULL),
    cut AS (SELECT tree, string_split(text, chr(10)) AS parts FROM docs),
    lines AS (SELECT tree, unnest(range(len(parts))) AS k, unnest(parts) AS line FROM cut),
    said AS (SELECT tree, k, list_filter(string_split(regexp_replace(line, '[.][[:space:]]+', '.' || chr(1), 'g'), chr(1)), lambda x: length(x) > 0) AS parts FROM lines),
    sentences AS (SELECT tree, k, unnest(range(len(parts))) AS j, unnest(parts) AS s FROM said),
    tagged AS (SELECT doc_id, max(quality) AS quality, max(toxic) AS toxic FROM labels GROUP BY doc_id),
    tags AS (SELECT tree, unnest(['lang=' || lang, 'quality=' || quality, 'toxic=' || toxic]) AS label FROM docs LEFT JOIN tagged ON doc_id = tree),
    raw AS (SELECT DISTINCT tree, 0 AS id, NULL::BIGINT AS parent, 'doc' AS label FROM docs
      UNION ALL SELECT tree, k * 10000 + 100, 0, 'line' FROM lines
      UNION ALL SELECT tree, k * 10000 + 101 + j, k * 10000 + 100, 's:len=' || {digits('s')} FROM sentences
      UNION ALL SELECT tree, dense_rank() OVER (PARTITION BY tree ORDER BY label), 0, label FROM tags WHERE label IS NOT NULL),
    edges AS (SELECT *, id AS o FROM raw)"""


def dom_edges(void: list[str]) -> str:
    """CTE ``edges`` of pages, a tag a step; an end tag closes back to its match, one without a match is ignored."""
    return f"""
    found AS (SELECT page_id AS tree, regexp_extract_all(coalesce(html, ''), '</?[a-zA-Z][a-zA-Z0-9]*[^>]*>') AS tags FROM pages WHERE page_id IS NOT NULL),
    every AS (SELECT tree, unnest(range(1, len(tags) + 1)) AS i, unnest(tags) AS tag FROM found),
    tag AS (SELECT tree, i, tag[2] = '/' AS closes, lower(regexp_extract(tag, '^</?([a-zA-Z][a-zA-Z0-9]*)', 1)) AS name, tag LIKE '%/>' AND tag[2] != '/' AS empty FROM every),
    fold AS (SELECT tree, 0::BIGINT AS i, 0::BIGINT AS next_id, []::BIGINT[] AS ids, []::VARCHAR[] AS names, NULL::BIGINT AS id, NULL::BIGINT AS parent, NULL::VARCHAR AS label FROM found
      UNION ALL
      SELECT f.tree, t.i, f.next_id + (NOT t.closes)::BIGINT,
        CASE WHEN t.closes THEN CASE WHEN list_contains(f.names, t.name) THEN f.ids[1:len(f.names) - list_position(list_reverse(f.names), t.name)] ELSE f.ids END
             WHEN t.empty OR t.name IN ({', '.join(repr(v) for v in void)}) THEN f.ids ELSE list_append(f.ids, f.next_id) END,
        CASE WHEN t.closes THEN CASE WHEN list_contains(f.names, t.name) THEN f.names[1:len(f.names) - list_position(list_reverse(f.names), t.name)] ELSE f.names END
             WHEN t.empty OR t.name IN ({', '.join(repr(v) for v in void)}) THEN f.names ELSE list_append(f.names, t.name) END,
        CASE WHEN NOT t.closes THEN f.next_id END, CASE WHEN NOT t.closes THEN f.ids[len(f.ids)] END, CASE WHEN NOT t.closes THEN t.name END
      FROM fold f JOIN tag t ON t.tree = f.tree AND t.i = f.i + 1),
    edges AS (SELECT tree, id, parent, label, id AS o FROM fold WHERE id IS NOT NULL)"""


def supply() -> str:
    """CTEs up to ``nodes`` of nation > supplier > part with three leaves each, and ``goods``, a row for each part."""
    size = "CASE WHEN p_size < 1 THEN 0 WHEN p_size >= 51 THEN 6 ELSE (p_size - 1) // 10 + 1 END"
    over = {"nation": "(PARTITION BY n)", "supplier": "(PARTITION BY n, s)", "part": "(PARTITION BY n, s, p)"}
    return f"""
    goods AS (SELECT s_nationkey::BIGINT AS n, s_suppkey::BIGINT AS s, p_partkey::BIGINT AS p, 'brand=' || p_brand AS brand, 'type=' || p_type AS kind, 'size=' || ({size})::BIGINT AS size
      FROM (SELECT DISTINCT l_suppkey, l_partkey FROM lineitem) JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey),
    raw AS (SELECT n_nationkey::BIGINT AS n, -1 AS s, -1 AS p, -1 AS a, 0 AS lv, 'nation' AS label FROM nation
      UNION ALL SELECT s_nationkey, s_suppkey, -1, -1, 1, 'supplier' FROM supplier
      UNION ALL SELECT n, s, p, -1, 2, 'part' FROM goods
      UNION ALL SELECT n, s, p, unnest([0, 1, 2]), 3, unnest([brand, kind, size]) FROM goods),
    placed AS (SELECT *, (2 * (row_number() OVER (PARTITION BY n ORDER BY s, p, a) - 1) - lv)::BIGINT AS b FROM raw),
    nodes AS (SELECT n AS tree_id, b AS "begin", (b + 2 * CASE lv WHEN 0 THEN count(*) OVER {over['nation']} WHEN 1 THEN count(*) OVER {over['supplier']} WHEN 2 THEN count(*) OVER {over['part']} ELSE 1 END - 1)::BIGINT AS "end", lv AS level,
      CASE lv WHEN 1 THEN min(b) OVER {over['nation']} WHEN 2 THEN min(b) OVER {over['supplier']} WHEN 3 THEN min(b) OVER {over['part']} END AS parent, label FROM placed)"""


PAIRS = """pairs AS (SELECT u.tree_id t, u."begin" a, u."end" ae, u.label al, v."begin" d, v."end" de, v.label dl
    FROM nodes u JOIN nodes v ON u.tree_id = v.tree_id AND v."begin" > u."begin" AND v."end" < u."end")"""


def small_patterns(minsup: int, roots: tuple[str, ...] | None = None) -> str:
    """CTEs up to ``frequent(code, k, support)`` of 2 and 3 nodes, and ``cover`` of inner roots, from ``pairs``.

    ``cover(p, n, q)``: images of p's root at an inner node of the frequent q.
    """
    inside = f" IN ({', '.join(repr(r) for r in roots)})" if roots else " IS NOT NULL"
    return f"""
    two AS (SELECT al || '(' || dl || ')' AS code, 2 AS k, count(DISTINCT (t, a)) AS support FROM pairs WHERE al{inside} GROUP BY al, dl HAVING count(DISTINCT (t, a)) >= {minsup}),
    chain AS (SELECT p.al x, p.dl y, q.dl z, p.t, p.a, p.d FROM pairs p JOIN pairs q ON p.t = q.t AND p.d = q.a WHERE p.al{inside}),
    fork AS (SELECT p.al x, p.dl y, q.dl z, p.t, p.a FROM pairs p JOIN pairs q ON p.t = q.t AND p.a = q.a AND p.dl <= q.dl AND (p.de < q.d OR q.de < p.d) WHERE p.al{inside}),
    three AS (
      SELECT x || '(' || y || '(' || z || '))' AS code, 3 AS k, count(DISTINCT (t, a)) AS support, x, y, z, 'chain' AS shape, count(DISTINCT (t, d)) AS inner_roots FROM chain GROUP BY x, y, z HAVING count(DISTINCT (t, a)) >= {minsup}
      UNION ALL
      SELECT x || '(' || y || ',' || z || ')', 3, count(DISTINCT (t, a)), x, y, z, 'fork', 0 FROM fork GROUP BY x, y, z HAVING count(DISTINCT (t, a)) >= {minsup}),
    frequent AS (SELECT code, k, support FROM two UNION ALL SELECT code, k, support FROM three),
    -- the subpatterns of two nodes of each frequent one of three, and how many root images they have there
    inside AS (
      SELECT x || '(' || y || ')' AS p, support AS n, code AS q FROM three
      UNION ALL SELECT x || '(' || z || ')', support, code FROM three
      UNION ALL SELECT y || '(' || z || ')', inner_roots, code FROM three WHERE shape = 'chain'),
    flagged AS (
      SELECT code, k, support,
        NOT EXISTS (SELECT 1 FROM inside WHERE p = code AND n = f.support) AS is_closed,
        NOT EXISTS (SELECT 1 FROM inside WHERE p = code) AS is_maximal
      FROM frequent f)"""
