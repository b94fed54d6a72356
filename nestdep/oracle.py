"""SQL building blocks on the flat base tables: what stands at each path of each derived collection.

Written on the base tables, not by nesting again, so that it is independent of
the engine.  Values are text with a domain letter; numbers go through DOUBLE.
"""

from __future__ import annotations


def n(expr: str) -> str:
    return f"'n' || CAST(CAST({expr} AS DOUBLE) AS VARCHAR)"


def s(expr: str) -> str:
    return f"'s' || {expr}"


def t(expr: str) -> str:
    return f"'t' || CAST(epoch_us(CAST({expr} AS TIMESTAMP)) AS VARCHAR)"


_ITEMS = "lineitem JOIN orders ON l_orderkey = o_orderkey"
_CUST = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_CORD = "customer JOIN orders ON o_custkey = c_custkey"
_CITEM = "customer JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey"
_UDAY = "concat_ws('@', CAST(user_id AS VARCHAR), CAST(CAST(ts AS DATE) AS VARCHAR))"
_WITH = "SELECT a.l_partkey AS d, b.l_partkey AS o FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey WHERE a.l_partkey <> b.l_partkey"

#: collection -> path -> SELECT of (d, v): one row per value of the document.
VALUES: dict[str, dict[str, str]] = {
    "order_docs": {
        "$.orderkey": f"SELECT o_orderkey d, {n('o_orderkey')} v FROM orders",
        "$.custkey": f"SELECT o_orderkey d, {n('o_custkey')} v FROM orders",
        "$.status": f"SELECT o_orderkey d, {s('o_orderstatus')} v FROM orders",
        "$.priority": f"SELECT o_orderkey d, {s('o_orderpriority')} v FROM orders",
        "$.totalprice": f"SELECT o_orderkey d, {n('o_totalprice')} v FROM orders",
        "$.orderdate": f"SELECT o_orderkey d, {t('o_orderdate')} v FROM orders",
        "$.items[*].linenumber": f"SELECT o_orderkey d, {n('l_linenumber')} v FROM {_ITEMS}",
        "$.items[*].partkey": f"SELECT o_orderkey d, {n('l_partkey')} v FROM {_ITEMS}",
        "$.items[*].suppkey": f"SELECT o_orderkey d, {n('l_suppkey')} v FROM {_ITEMS}",
        "$.items[*].quantity": f"SELECT o_orderkey d, {n('l_quantity')} v FROM {_ITEMS}",
        "$.items[*].returnflag": f"SELECT o_orderkey d, {s('l_returnflag')} v FROM {_ITEMS}",
        "$.items[*].linestatus": f"SELECT o_orderkey d, {s('l_linestatus')} v FROM {_ITEMS}",
        "$.flags[*]": f"SELECT DISTINCT o_orderkey d, {s('l_returnflag')} v FROM {_ITEMS}",
        "$.flag_or_status[*]": f"SELECT DISTINCT o_orderkey d, {s('l_returnflag')} v FROM {_ITEMS} UNION SELECT o_orderkey, {s('o_orderstatus')} FROM orders",
    },
    "customer_docs": {
        "$.custkey": f"SELECT c_custkey d, {n('c_custkey')} v FROM customer",
        "$.segment": f"SELECT c_custkey d, {s('c_mktsegment')} v FROM customer",
        "$.nation.nationkey": f"SELECT c_custkey d, {n('n_nationkey')} v FROM {_CUST}",
        "$.nation.name": f"SELECT c_custkey d, {s('n_name')} v FROM {_CUST}",
        "$.nation.region.regionkey": f"SELECT c_custkey d, {n('r_regionkey')} v FROM {_CUST}",
        "$.nation.region.name": f"SELECT c_custkey d, {s('r_name')} v FROM {_CUST}",
        "$.orders[*].orderkey": f"SELECT c_custkey d, {n('o_orderkey')} v FROM {_CORD}",
        "$.orders[*].custkey": f"SELECT c_custkey d, {n('o_custkey')} v FROM {_CORD}",
        "$.orders[*].status": f"SELECT c_custkey d, {s('o_orderstatus')} v FROM {_CORD}",
        "$.orders[*].items[*].partkey": f"SELECT c_custkey d, {n('l_partkey')} v FROM {_CITEM}",
        "$.orders[*].items[*].suppkey": f"SELECT c_custkey d, {n('l_suppkey')} v FROM {_CITEM}",
        "$.orders[*].items[*].returnflag": f"SELECT c_custkey d, {s('l_returnflag')} v FROM {_CITEM}",
    },
    "product_docs": {
        "$.partkey": f"SELECT p_partkey d, {n('p_partkey')} v FROM part",
        "$.brand": f"SELECT p_partkey d, {s('p_brand')} v FROM part",
        "$.related.ordered_with[*]": f"SELECT DISTINCT d, {n('o')} v FROM ({_WITH}) JOIN part ON p_partkey = d",
        "$.related.returned_with[*]": f"SELECT DISTINCT d, {n('o')} v FROM ({_WITH} AND a.l_returnflag = 'R' AND b.l_returnflag = 'R') JOIN part ON p_partkey = d",
        "$.suppliers[*]": f"SELECT DISTINCT p_partkey d, {n('l_suppkey')} v FROM lineitem JOIN part ON p_partkey = l_partkey",
        "$.categories[*][*]": f"SELECT p_partkey d, {s('p_type')} v FROM part UNION ALL SELECT p_partkey, {s('p_type')} || '/' || split_part(p_name, ' ', 1) FROM part",
        "$.size_rank{key}": f"SELECT p_partkey d, {s(chr(39) + 'size' + chr(39) + ' || CAST(p_size % 5 AS VARCHAR)')} v FROM part",
        "$.size_rank{value}": f"SELECT p_partkey d, {n('p_size')} v FROM part",
    },
    "event_docs": {
        "$.event_id": f"SELECT event_id d, {n('event_id')} v FROM events",
        "$.ts": f"SELECT event_id d, {t('ts')} v FROM events",
        "$.user_id": f"SELECT event_id d, {n('user_id')} v FROM events",
        "$.event_type": f"SELECT event_id d, {s('event_type')} v FROM events",
        "$.value": f"SELECT event_id d, {n('value')} v FROM events",
        "$.props.k": f"SELECT event_id d, {n(chr(40) + 'props->>' + chr(39) + '$.k' + chr(39) + chr(41))} v FROM events WHERE props->>'$.k' IS NOT NULL",
    },
    "user_day_docs": {
        "$.user_id": f"SELECT DISTINCT {_UDAY} d, {n('user_id')} v FROM events",
        "$.day": f"SELECT DISTINCT {_UDAY} d, {t('CAST(ts AS DATE)')} v FROM events",
        "$.events[*].event_type": f"SELECT {_UDAY} d, {s('event_type')} v FROM events",
        "$.events[*].k": f"SELECT {_UDAY} d, {n(chr(40) + 'props->>' + chr(39) + '$.k' + chr(39) + chr(41))} v FROM events WHERE props->>'$.k' IS NOT NULL",
        "$.events[*].value": f"SELECT {_UDAY} d, {n('value')} v FROM events",
    },
    "conversation_docs": {
        "$.conv_id": f"SELECT DISTINCT conv_id d, {n('conv_id')} v FROM conversations",
        "$.turns[*].turn": f"SELECT conv_id d, {n('turn')} v FROM conversations WHERE turn IS NOT NULL",
        "$.turns[*].role": f"SELECT conv_id d, {s('role')} v FROM conversations WHERE role IS NOT NULL",
        "$.turns[*].text": f"SELECT conv_id d, {s('text')} v FROM conversations WHERE text IS NOT NULL",
        "$.roles[*]": f"SELECT DISTINCT conv_id d, {s('role')} v FROM conversations WHERE role IS NOT NULL",
    },
    "geo_docs": {
        "$.regionkey": f"SELECT r_regionkey d, {n('r_regionkey')} v FROM region",
        "$.name": f"SELECT r_regionkey d, {s('r_name')} v FROM region",
        "$.nations[*].nationkey": f"SELECT n_regionkey d, {n('n_nationkey')} v FROM nation",
        "$.nations[*].name": f"SELECT n_regionkey d, {s('n_name')} v FROM nation",
        "$.nations[*].suppliers[*].suppkey": f"SELECT n_regionkey d, {n('s_suppkey')} v FROM supplier JOIN nation ON s_nationkey = n_nationkey",
        "$.nations[*].suppliers[*].nationkey": f"SELECT n_regionkey d, {n('s_nationkey')} v FROM supplier JOIN nation ON s_nationkey = n_nationkey",
        "$.nations[*].customers[*].custkey": f"SELECT n_regionkey d, {n('c_custkey')} v FROM customer JOIN nation ON c_nationkey = n_nationkey",
        "$.nations[*].customers[*].orderkeys[*]": f"SELECT DISTINCT n_regionkey d, {n('o_orderkey')} v FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey",
    },
}


#: The same of a flat table, which is no nested collection of its own.
FLAT: dict[str, dict[str, str]] = {
    "nation": {
        "$.n_nationkey": f"SELECT n_nationkey d, {n('n_nationkey')} v FROM nation",
        "$.n_name": f"SELECT n_nationkey d, {s('n_name')} v FROM nation",
        "$.n_regionkey": f"SELECT n_nationkey d, {n('n_regionkey')} v FROM nation",
    }
}

#: Flat rows of each document by static unrolling: SELECT of (d, r).
EXPANSION: dict[str, str] = {
    "order_docs": """SELECT o_orderkey d, greatest(count(l_orderkey), 1) * greatest(count(DISTINCT l_returnflag), 1)
        * (count(DISTINCT l_returnflag) + CASE WHEN bool_or(coalesce(l_returnflag = o_orderstatus, FALSE)) THEN 0 ELSE 1 END) AS r
        FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey""",
    "customer_docs": """SELECT c_custkey d, greatest(coalesce(sum(k), 0), 1) AS r FROM customer
        LEFT JOIN (SELECT o_custkey, greatest(count(l_orderkey), 1) AS k FROM orders LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_custkey, o_orderkey) ON o_custkey = c_custkey GROUP BY c_custkey""",
    "product_docs": f"""SELECT p_partkey d, 2 * greatest(coalesce(a, 0), 1) * greatest(coalesce(b, 0), 1) * greatest(coalesce(k, 0), 1) AS r FROM part
        LEFT JOIN (SELECT d, count(DISTINCT o) AS a FROM ({_WITH}) GROUP BY d) x ON x.d = p_partkey
        LEFT JOIN (SELECT d, count(DISTINCT o) AS b FROM ({_WITH} AND a.l_returnflag = 'R' AND b.l_returnflag = 'R') GROUP BY d) y ON y.d = p_partkey
        LEFT JOIN (SELECT l_partkey, count(DISTINCT l_suppkey) AS k FROM lineitem GROUP BY l_partkey) z ON l_partkey = p_partkey""",
    "event_docs": "SELECT event_id d, 1 AS r FROM events",
    "user_day_docs": f"SELECT {_UDAY} d, count(*) AS r FROM events GROUP BY ALL",
    "conversation_docs": "SELECT conv_id d, count(*) * greatest(count(DISTINCT role), 1) AS r FROM conversations GROUP BY conv_id",
    "geo_docs": """SELECT r_regionkey d, greatest(coalesce(sum(greatest(coalesce(s, 0), 1) * greatest(coalesce(c, 0), 1)), 0), 1) AS r FROM region LEFT JOIN nation ON n_regionkey = r_regionkey
        LEFT JOIN (SELECT s_nationkey, count(*) AS s FROM supplier GROUP BY ALL) ON s_nationkey = n_nationkey
        LEFT JOIN (SELECT c_nationkey, sum(greatest(coalesce(k, 0), 1)) AS c FROM customer LEFT JOIN (SELECT o_custkey, count(DISTINCT o_orderkey) AS k FROM orders GROUP BY ALL) ON o_custkey = c_custkey GROUP BY c_nationkey)
        ON c_nationkey = n_nationkey GROUP BY r_regionkey""",
}


def cells(collection: str, paths: list[str] | None = None) -> str:
    """SELECT of (path, d, v) of a collection."""
    found = VALUES[collection] if collection in VALUES else FLAT[collection]
    return " UNION ALL ".join(f"SELECT '{p}' AS path, CAST(d AS VARCHAR) AS d, v FROM ({found[p]})" for p in (paths or found))


def cells_per_path(collection: str) -> str:
    return f"SELECT path, CAST(count(*) AS BIGINT) AS n_cells, CAST(count(DISTINCT v) AS BIGINT) AS n_values FROM ({cells(collection)}) GROUP BY path"


def ninds(collection: str, paths: list[str] | None = None, theta: float = 1.0, valid_only: bool = False, of: str | None = None, kind: str = "nind") -> str:
    only = f"WHERE coalesce(included, 0) >= {theta} * support" if valid_only else ""
    return f"""
        WITH c AS ({of or cells(collection, paths)}), u AS (SELECT DISTINCT path, v FROM c), sup AS (SELECT path, count(*) AS support FROM u GROUP BY path),
        inc AS (SELECT a.path AS lhs, b.path AS rhs, count(*) AS included FROM u a JOIN u b ON a.v = b.v GROUP BY ALL),
        p AS (SELECT x.path AS lhs, y.path AS rhs, x.support FROM sup x JOIN sup y ON x.path <> y.path)
        SELECT '{kind}' AS kind, lhs, rhs, CAST(support AS BIGINT) AS support, CAST(coalesce(included, 0) AS BIGINT) AS included,
               round(coalesce(included, 0) / support, 6) AS strength, coalesce(included, 0) >= {theta} * support AS valid
        FROM p LEFT JOIN inc USING (lhs, rhs) {only}"""


def mask_pairs(collection: str, paths: list[str], only: str = "TRUE") -> str:
    """SELECT of (d1, d2, mask) of pairs that share a value; bit i is paths[i]."""
    bit = " ".join(f"WHEN path = '{p}' THEN {1 << i}" for i, p in enumerate(paths))
    return f"""
        SELECT a.d AS d1, b.d AS d2, bit_or(a.b) AS mask
        FROM (SELECT DISTINCT path, d, v, CAST(CASE {bit} END AS BIGINT) AS b FROM ({cells(collection, paths)}) WHERE {only}) a
        JOIN (SELECT DISTINCT path, d, v FROM ({cells(collection, paths)}) WHERE {only}) b ON a.path = b.path AND a.v = b.v AND a.d < b.d GROUP BY a.d, b.d"""


def mask_histogram(collection: str, paths: list[str], documents: str) -> str:
    return f"""
        WITH m AS ({mask_pairs(collection, paths)}), h AS (SELECT mask, count(*) AS pairs FROM m GROUP BY mask),
        z AS (SELECT 0 AS mask, n * (n - 1) // 2 - (SELECT coalesce(sum(pairs), 0) FROM h) AS pairs FROM (SELECT count(*) AS n FROM ({documents})))
        SELECT CAST(mask AS BIGINT) AS mask, CAST(pairs AS BIGINT) AS pairs FROM h UNION ALL SELECT CAST(mask AS BIGINT), CAST(pairs AS BIGINT) FROM z WHERE pairs > 0"""


def _side(x: str, paths: list[str]) -> str:
    return "concat_ws(',', " + ", ".join(f"CASE WHEN {x} & {1 << i} > 0 THEN '{p}' END" for i, p in enumerate(paths)) + ")"


def _one(a: str, paths: list[str]) -> str:
    return f"CASE {a} " + " ".join(f"WHEN {i} THEN '{p}'" for i, p in enumerate(paths)) + " END"


def nfds(collection: str, paths: list[str], documents: str, max_lhs: int = 3, hist: str | None = None, kind: str = "nfd") -> str:
    """Minimal dependencies by enumerating all left sides against the histogram."""
    k = len(paths)
    return f"""
        WITH h AS ({hist or mask_histogram(collection, paths, documents)}),
        c AS (SELECT x, a FROM range({1 << k}) r(x), range({k}) q(a) WHERE x & (1 << a) = 0 AND bit_count(x) <= {max_lhs}),
        ok AS (SELECT x, a FROM c WHERE NOT EXISTS (SELECT 1 FROM h WHERE h.mask & x = x AND h.mask & (1 << a) = 0)),
        m AS (SELECT x, a FROM ok o WHERE NOT EXISTS (SELECT 1 FROM ok i WHERE i.a = o.a AND i.x <> o.x AND i.x & o.x = i.x))
        SELECT '{kind}' AS kind, {_side("x", paths)} AS lhs, {_one("a", paths)} AS rhs, CAST(1.0 AS DOUBLE) AS strength, TRUE AS valid FROM m"""


def flat_fds(flat: str, columns: dict[str, str], max_lhs: int = 2) -> str:
    """Minimal classical dependencies of flat rows: as many left values as values of both sides. columns: name -> column of flat."""
    names = list(columns)
    k = len(names)
    row = lambda x: "row(" + ", ".join([*(columns[n] for i, n in enumerate(names) if x >> i & 1), "0"]) + ")"
    masks = [x for x in range(1 << k) if x.bit_count() <= max_lhs + 1]
    counts = " UNION ALL ".join(f"SELECT {x} AS x, count(DISTINCT {row(x)}) AS n FROM f" for x in masks)
    return f"""
        WITH f AS ({flat}), n AS ({counts}),
        ok AS (SELECT l.x, a FROM n l, range({k}) q(a), n b WHERE bit_count(l.x) <= {max_lhs} AND l.x & (1 << a) = 0 AND b.x = l.x | (1 << a) AND b.n = l.n)
        SELECT 'fd' AS kind, {_side("x", names)} AS lhs, {_one("a", names)} AS rhs, CAST(1.0 AS DOUBLE) AS strength, TRUE AS valid
        FROM ok o WHERE NOT EXISTS (SELECT 1 FROM ok i WHERE i.a = o.a AND i.x <> o.x AND i.x & o.x = i.x)"""


def keys(collection: str, paths: list[str], documents: str, max_size: int = 3) -> str:
    """Minimal sets of paths that no pair of documents overlaps on."""
    return f"""
        WITH h AS ({mask_histogram(collection, paths, documents)}),
        ok AS (SELECT x FROM range(1, {1 << len(paths)}) r(x) WHERE bit_count(x) <= {max_size} AND NOT EXISTS (SELECT 1 FROM h WHERE h.mask & x = x))
        SELECT {_side("x", paths)} AS paths, CAST(bit_count(x) AS INTEGER) AS size FROM ok o WHERE NOT EXISTS (SELECT 1 FROM ok i WHERE i.x <> o.x AND i.x & o.x = i.x)"""


def cover_strengths(collection: str, paths: list[str], documents: str, max_lhs: int) -> str:
    """SELECT of (x, a, strength) by the greedy scan itself, in the affine order of integer ids; one row per left side of at least one path."""
    k = len(paths)
    return f"""
        SELECT c.x, c.a, 1 - coalesce(len(list_reduce(list([d1, d2] ORDER BY (d1 * 7919 + d2 * 104729 + 7) % 1009, d1, d2) FILTER (d1 IS NOT NULL),
                 lambda taken, e: CASE WHEN list_has_any(taken, e) THEN taken ELSE taken || e END, []::BIGINT[])), 0) / (SELECT count(*) FROM ({documents})) AS strength
        FROM (SELECT x, a FROM range({1 << k}) r(x), range({k}) q(a) WHERE x & (1 << a) = 0 AND bit_count(x) BETWEEN 1 AND {max_lhs}) c
        LEFT JOIN (SELECT least(CAST(d1 AS BIGINT), CAST(d2 AS BIGINT)) AS d1, greatest(CAST(d1 AS BIGINT), CAST(d2 AS BIGINT)) AS d2, mask FROM ({mask_pairs(collection, paths)})) m
        ON m.mask & c.x = c.x AND m.mask & (1 << c.a) = 0 GROUP BY c.x, c.a"""


def approximate_nfds(collection: str, paths: list[str], documents: str, theta: float, max_lhs: int = 3) -> str:
    """Minimal dependencies of at least a strength.

    An empty left side is judged by the documents without the most frequent value
    of the right one, which is exact where documents have one value at most; others
    are taken here only if that alone decides.
    """
    k = len(paths)
    number = "CASE path " + " ".join(f"WHEN '{p}' THEN {i}" for i, p in enumerate(paths)) + " END"
    return f"""
        WITH n AS (SELECT count(*) AS n FROM ({documents})), one AS (SELECT DISTINCT path, d, v FROM ({cells(collection, paths)})),
        p AS (SELECT mask FROM ({mask_pairs(collection, paths)})),
        most AS (SELECT a, max(f) AS f FROM (SELECT {number} AS a, v, count(*) AS f FROM one GROUP BY ALL) GROUP BY a),
        bad AS (SELECT a, (SELECT n * (n - 1) // 2 FROM n) - (SELECT count(*) FROM p WHERE mask & (1 << a) > 0) AS bad FROM range({k}) q(a)),
        e AS (SELECT 0 AS x, a, CASE WHEN bad = 0 THEN 1.0 ELSE 1 - (n - greatest(1, coalesce(f, 0))) / n END AS strength FROM bad LEFT JOIN most USING (a), n),
        c AS (SELECT CAST(x AS BIGINT) AS x, CAST(a AS BIGINT) AS a, strength FROM e UNION ALL SELECT x, a, strength FROM ({cover_strengths(collection, paths, documents, max_lhs)})),
        ok AS (SELECT * FROM c WHERE strength >= {theta})
        SELECT 'nfd' AS kind, {_side("x", paths)} AS lhs, {_one("a", paths)} AS rhs, round(CAST(strength AS DOUBLE), 6) AS strength, TRUE AS valid
        FROM ok o WHERE NOT EXISTS (SELECT 1 FROM ok i WHERE i.a = o.a AND i.x <> o.x AND i.x & o.x = i.x)"""


def whole_numbers(sql: str) -> str:
    """The same with numbers printed as integers, as the engine's keys are."""
    return sql.replace(" AS DOUBLE) AS VARCHAR)", " AS BIGINT) AS VARCHAR)")
