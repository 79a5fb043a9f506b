"""SQL for the same answers by other means: recursive queries, path lists and interval splitting rather than rounds and bit arithmetic."""

from __future__ import annotations

_S = 10**12

#: t(v, parent, level) of the geographic tree.
GEO = f"""geo_t AS (
  SELECT CAST(0 AS BIGINT) v, CAST(NULL AS BIGINT) parent, CAST(0 AS BIGINT) level
  UNION ALL SELECT {_S} + r_regionkey, 0, 1 FROM region
  UNION ALL SELECT 2 * {_S} + n_nationkey, {_S} + n_regionkey, 2 FROM nation
  UNION ALL SELECT 3 * {_S} + c_custkey, 2 * {_S} + c_nationkey, 3 FROM customer
  UNION ALL SELECT 4 * {_S} + s_suppkey, 2 * {_S} + s_nationkey, 3 FROM supplier
  UNION ALL SELECT 5 * {_S} + o_orderkey, 3 * {_S} + o_custkey, 4 FROM orders),
geo_e AS (SELECT v src, parent dst FROM geo_t WHERE parent IS NOT NULL UNION SELECT parent, v FROM geo_t WHERE parent IS NOT NULL)"""

_MESH_PAIRS = f"""SELECT 3 * {_S} + o_custkey a, 5 * {_S} + o_orderkey b FROM orders UNION SELECT 5 * {_S} + l_orderkey, 6 * {_S} + l_partkey FROM lineitem"""
_TRADE_PAIRS = f"""SELECT DISTINCT 3 * {_S} + o_custkey a, 4 * {_S} + l_suppkey b FROM lineitem JOIN orders ON l_orderkey = o_orderkey"""


def edges(name: str, pairs: str) -> str:
    return f"{name}_p AS ({pairs}), {name}_e AS (SELECT a src, b dst FROM {name}_p UNION SELECT b, a FROM {name}_p)"


def breadth_first(name: str, deepest: int = 16, choice: str = "min(u.v)") -> str:
    """{name}_t(v, parent, level) over {name}_e from the greatest id."""
    return f"""{name}_walk(v, level) AS (
  SELECT max(src), CAST(0 AS BIGINT) FROM {name}_e
  UNION SELECT e.dst, w.level + 1 FROM {name}_walk w JOIN {name}_e e ON e.src = w.v WHERE w.level < {deepest}),
{name}_l AS (SELECT v, min(level) level FROM {name}_walk GROUP BY v),
{name}_t AS (
  SELECT c.v, {choice} parent, any_value(c.level) level
  FROM {name}_l c JOIN {name}_e e ON e.src = c.v JOIN {name}_l u ON u.v = e.dst AND u.level = c.level - 1 GROUP BY c.v
  UNION ALL SELECT v, NULL, level FROM {name}_l WHERE level = 0)"""


MESH_E, TRADE_E = edges("mesh", _MESH_PAIRS), edges("trade", _TRADE_PAIRS)
MESH = f"{MESH_E}, {breadth_first('mesh')}"


def ports(name: str) -> str:
    """{name}_ports(src, dst, port, rev_port): both numbers from one list of links, without a join."""
    return f"""{name}_ports AS (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY dst) - 1 port, row_number() OVER (PARTITION BY dst ORDER BY src) - 1 rev_port FROM {name}_e)"""


def heights(name: str) -> str:
    """{name}_b(v, parent, height, up, port) and {name}_last(parent, last): heights, and the last port of a tallest child."""
    return f"""{name}_ht AS (SELECT a v, max(t.level) - any_value(s.level) height FROM {name}_up x JOIN {name}_t t ON t.v = x.v JOIN {name}_t s ON s.v = x.a GROUP BY a),
{name}_b AS (SELECT t.v, t.parent, h.height, p.height up, q.port FROM {name}_t t JOIN {name}_ht h ON h.v = t.v JOIN {name}_ht p ON p.v = t.parent JOIN {name}_ports q ON q.src = t.parent AND q.dst = t.v),
{name}_last AS (SELECT parent, max(port) last FROM {name}_b WHERE height = up - 1 GROUP BY parent)"""


def answers(name: str) -> str:
    """Asks, answers and totals of both ways of answering (needs heights)."""
    ask = "greatest(3, up - height + 1) + CASE WHEN height <= up - 2 AND port < last THEN 1 ELSE 0 END"
    return f"""SELECT CAST(sum({ask}) AS BIGINT) asks, 3 * count(*) answers, count(*) weights, CAST(sum({ask}) + 4 * count(*) AS BIGINT) ask_total,
  count(*) + (SELECT count(*) FROM {name}_e WHERE src IN (SELECT parent FROM {name}_t)) broadcast_total FROM {name}_b JOIN {name}_last USING (parent)"""


def flooding(name: str, rounds: int) -> str:
    """{name}_sent(round, messages): what each round of flooding the greatest id sends, from the greatest id within so many hops."""
    return f"""{name}_far(v, hop, best) AS (
  SELECT src, 0, src FROM (SELECT DISTINCT src FROM {name}_e)
  UNION ALL SELECT e.src, any_value(f.hop) + 1, greatest(e.src, max(f.best)) FROM {name}_far f JOIN {name}_e e ON e.dst = f.v WHERE f.hop < {rounds} GROUP BY e.src),
{name}_best AS (SELECT v, hop, max(best) OVER (PARTITION BY v ORDER BY hop) best FROM {name}_far),
{name}_deg AS (SELECT src v, count(*) degree FROM {name}_e GROUP BY src),
{name}_moved AS (SELECT v, hop, hop = 0 OR best > lag(best) OVER (PARTITION BY v ORDER BY hop) sends FROM {name}_best),
{name}_sent AS (SELECT CAST(hop AS BIGINT) round, CAST(sum(degree) AS BIGINT) messages FROM {name}_moved JOIN {name}_deg USING (v) WHERE sends GROUP BY hop)"""


def healed(name: str, dead: str) -> str:
    """{name}_links(u, v): links between the live vertices of the healed tree; needs numbers and weights.

    A plan keeps one helper between each two neighbouring slots with live vertices; over a helper is the lower of the nearest
    higher ones on both sides, over a slot the lower of the two beside it.
    """
    return f"""{name}_dead AS (SELECT v FROM {name}_t WHERE {dead}),
{name}_full AS (SELECT DISTINCT a v FROM {name}_up WHERE v NOT IN (SELECT v FROM {name}_dead)),
{name}_s AS (SELECT r.parent x, r.rank r, r.v c, row_number() OVER (PARTITION BY r.parent ORDER BY r.rank) i, count(*) OVER (PARTITION BY r.parent) n,
    lead(r.rank) OVER (PARTITION BY r.parent ORDER BY r.rank) r2 FROM {name}_r r JOIN {name}_full f ON f.v = r.v WHERE r.parent IN (SELECT v FROM {name}_dead)),
{name}_hx AS (SELECT x, i, c, (r2 >> (length(bin(xor(r, r2))) - 1)) << (length(bin(xor(r, r2))) - 1) p FROM {name}_s WHERE r2 IS NOT NULL),
{name}_hz AS (SELECT x, i, c, length(bin(p & -p)) z FROM {name}_hx),
{name}_hi AS (SELECT h.x, h.i, max(CASE WHEN g.i < h.i THEN g.i END) l, min(CASE WHEN g.i > h.i THEN g.i END) r FROM {name}_hz h LEFT JOIN {name}_hz g ON g.x = h.x AND g.z > h.z GROUP BY h.x, h.i),
{name}_hp AS (SELECT hi.x, hi.i, CASE WHEN l IS NULL THEN r WHEN r IS NULL THEN l WHEN a.z < b.z THEN l ELSE r END up FROM {name}_hi hi LEFT JOIN {name}_hz a ON a.x = hi.x AND a.i = hi.l LEFT JOIN {name}_hz b ON b.x = hi.x AND b.i = hi.r),
{name}_sp AS (SELECT s.x, s.c, CASE WHEN a.z IS NULL THEN b.i WHEN b.z IS NULL THEN a.i WHEN a.z < b.z THEN a.i ELSE b.i END up, s.n FROM {name}_s s LEFT JOIN {name}_hz a ON a.x = s.x AND a.i = s.i - 1 LEFT JOIN {name}_hz b ON b.x = s.x AND b.i = s.i),
{name}_lastof(v, cur) AS (SELECT v, v FROM {name}_full UNION ALL SELECT l.v, s.c FROM {name}_lastof l JOIN {name}_s s ON s.x = l.cur AND s.i = s.n),
{name}_end AS (SELECT v, cur owner FROM {name}_lastof WHERE cur NOT IN (SELECT v FROM {name}_dead)),
{name}_climb(v, cur) AS (SELECT v, v FROM {name}_full UNION ALL SELECT k.v, s.x FROM {name}_climb k JOIN {name}_s s ON s.c = k.cur AND s.n = 1),
{name}_above AS (SELECT k.v, t.parent q, sp.up i FROM {name}_climb k JOIN {name}_t t ON t.v = k.cur LEFT JOIN {name}_sp sp ON sp.c = k.cur WHERE sp.n IS NULL OR sp.n > 1),
{name}_own AS (SELECT h.x, h.i, e.owner FROM {name}_hz h JOIN {name}_end e ON e.v = h.c),
{name}_up1 AS (SELECT f.v owner, a.q, a.i FROM {name}_full f JOIN {name}_above a ON a.v = f.v WHERE f.v NOT IN (SELECT v FROM {name}_dead)
  UNION ALL SELECT w.owner, CASE WHEN p.up IS NULL THEN a.q ELSE w.x END, CASE WHEN p.up IS NULL THEN a.i ELSE p.up END FROM {name}_own w JOIN {name}_hp p ON p.x = w.x AND p.i = w.i LEFT JOIN {name}_above a ON a.v = w.x),
{name}_links AS (SELECT DISTINCT least(u.owner, coalesce(w.owner, u.q)) u, greatest(u.owner, coalesce(w.owner, u.q)) v FROM {name}_up1 u LEFT JOIN {name}_own w ON w.x = u.q AND w.i = u.i
  WHERE u.q IS NOT NULL AND u.owner <> coalesce(w.owner, u.q)),
{name}_after AS (SELECT v, count(*) n FROM (SELECT u v FROM {name}_links UNION ALL SELECT v FROM {name}_links) GROUP BY v),
{name}_kids AS (SELECT parent v, count(*) n FROM {name}_t WHERE parent IS NOT NULL GROUP BY parent)"""


def degree_growth(name: str) -> str:
    return f"""SELECT CAST(coalesce(a.n, 0) - coalesce(k.n, 0) - CASE WHEN t.parent IS NULL THEN 0 ELSE 1 END AS BIGINT) increase, count(*) vertices
  FROM {name}_t t LEFT JOIN {name}_after a ON a.v = t.v LEFT JOIN {name}_kids k ON k.v = t.v WHERE t.v NOT IN (SELECT v FROM {name}_dead) GROUP BY 1"""


def packets(name: str) -> str:
    """{name}_pk(src, dst): every vertex sends to the one that an arithmetic rule over the new numbers gives; needs numbers."""
    return f"""{name}_pk AS (SELECT a.v src, b.v dst FROM {name}_i a JOIN {name}_i b ON b.new_id = (a.new_id * 48271 + 7) % (SELECT count(*) FROM {name}_i) + 1)"""


def route_lengths(name: str) -> str:
    """{name}_len(src, dst, hops): up to the lowest common ancestor and down; needs weights and {name}_pk."""
    return f"""{name}_px AS MATERIALIZED (SELECT src, dst, x.a FROM {name}_pk JOIN {name}_up x ON x.v = src),
{name}_pa AS MATERIALIZED (SELECT p.src, p.dst, p.a FROM {name}_px p JOIN {name}_up y ON y.v = p.dst AND y.a = p.a),
{name}_pc AS MATERIALIZED (SELECT src, dst, max(c.level) top FROM {name}_pa JOIN {name}_t c ON c.v = a GROUP BY src, dst),
{name}_len AS (SELECT src, dst, CAST(s.level + e.level - 2 * top AS BIGINT) hops FROM {name}_pc JOIN {name}_t s ON s.v = src JOIN {name}_t e ON e.v = dst)"""

def weights(name: str, kind: str = "leaves") -> str:
    """{name}_w(v, weight, size) from the closure of ancestors."""
    leaf = f"v NOT IN (SELECT parent FROM {name}_t WHERE parent IS NOT NULL)" if kind == "leaves" else "true"
    return f"""{name}_up(v, a) AS (SELECT v, v FROM {name}_t UNION ALL SELECT x.v, t.parent FROM {name}_up x JOIN {name}_t t ON t.v = x.a WHERE t.parent IS NOT NULL),
{name}_leaf AS (SELECT v FROM {name}_t WHERE {leaf}),
{name}_w AS (SELECT a v, CAST(count(l.v) AS BIGINT) weight, count(*) size FROM {name}_up x LEFT JOIN {name}_leaf l ON l.v = x.v GROUP BY a)"""


def heavy(name: str, b: int = 2) -> str:
    """{name}_h(v, parent, level, weight, size, heavy)."""
    return f"""{name}_h AS (SELECT t.v, t.parent, t.level, w.weight, w.size, w.weight * {b} >= p.weight heavy
  FROM {name}_t t JOIN {name}_w w ON w.v = t.v LEFT JOIN {name}_w p ON p.v = t.parent)"""


def numbers(name: str, post: bool = True) -> str:
    """{name}_n(v, rank, lo, new_id): ranks of path lists; {name}_r has the ranks among siblings."""
    key = "list_append(path, 999999999999)" if post else "path"
    lo = "new_id - size + 1" if post else "new_id"
    return f"""{name}_r AS (SELECT *, CASE WHEN parent IS NULL THEN 0 ELSE row_number() OVER (PARTITION BY parent ORDER BY NOT heavy, v) - 1 END rank FROM {name}_h),
{name}_path(v, path) AS (SELECT v, CAST([] AS BIGINT[]) FROM {name}_r WHERE parent IS NULL
  UNION ALL SELECT r.v, list_append(p.path, r.rank) FROM {name}_path p JOIN {name}_r r ON r.parent = p.v),
{name}_i AS (SELECT v, row_number() OVER (ORDER BY {key}) new_id FROM {name}_path),
{name}_n AS (SELECT r.*, new_id, {lo} lo FROM {name}_r r JOIN {name}_i i ON i.v = r.v)"""


def light_paths(name: str) -> str:
    """{name}_lp(v, light_path, light_level): ports of light links joined by dots."""
    return f"""{name}_lp(v, light_path, light_level) AS (SELECT v, '', CAST(0 AS BIGINT) FROM {name}_h WHERE parent IS NULL
  UNION ALL SELECT h.v, CASE WHEN heavy THEN light_path WHEN light_path = '' THEN CAST(q.port AS VARCHAR) ELSE light_path || '.' || q.port END, light_level + CASE WHEN heavy THEN 0 ELSE 1 END
  FROM {name}_lp p JOIN {name}_h h ON h.parent = p.v JOIN {name}_ports q ON q.src = h.parent AND q.dst = h.v)"""


def half_full(sizes: str) -> str:
    """hf(size, kind, label, pk) by splitting intervals: kind 'N' or 'L', pk the label of the inner node above; sizes: a query of size."""
    p = "CAST(1 AS BIGINT) << (length(bin(hi - lo - 1)) - 1)"
    return f"""hf_sizes AS ({sizes}),
hf_split(size, lo, hi, up) AS (
  SELECT size, CAST(0 AS BIGINT), size, CAST(NULL AS BIGINT) FROM hf_sizes WHERE size > 0
  UNION ALL SELECT size, CASE side WHEN 0 THEN lo ELSE lo + p END, CASE side WHEN 0 THEN lo + p ELSE hi END, lo + p - 1
  FROM (SELECT *, {p} p FROM hf_split WHERE hi - lo > 1) CROSS JOIN (SELECT unnest([0, 1]) side)),
hf AS (SELECT size, CASE WHEN hi - lo = 1 THEN 'L' ELSE 'N' END kind, CASE WHEN hi - lo = 1 THEN lo ELSE lo + ({p.replace('hi - lo - 1', 'greatest(hi - lo - 1, 1)')}) - 1 END label, up FROM hf_split),
hf_links AS (
  SELECT l.size, l.label y, l.up leaf_parent, n.up node_parent, n.label IS NOT NULL inner_node,
    c.left_label, c.left_leaf, c.right_label, c.right_leaf
  FROM (SELECT * FROM hf WHERE kind = 'L') l
  LEFT JOIN (SELECT * FROM hf WHERE kind = 'N') n ON n.size = l.size AND n.label = l.label
  LEFT JOIN (SELECT size, up, min(CASE WHEN is_left THEN label END) left_label, bool_or(is_left AND kind = 'L') left_leaf,
      min(CASE WHEN NOT is_left THEN label END) right_label, bool_or(NOT is_left AND kind = 'L') right_leaf
    FROM (SELECT size, kind, label, up, CASE WHEN kind = 'L' THEN label <= up ELSE label < up END is_left FROM hf WHERE up IS NOT NULL) GROUP BY size, up) c
    ON c.size = l.size AND c.up = l.label AND n.label IS NOT NULL),
hf_root AS (SELECT size, label root FROM hf WHERE up IS NULL AND kind = 'N')"""


def portions(name: str) -> str:
    """{name}_po: recovery portions with ids, from {name}_r (rank) and the splits."""
    return f"""{name}_c AS (SELECT parent v, count(*) size FROM {name}_r WHERE parent IS NOT NULL GROUP BY parent),
{half_full(f'SELECT DISTINCT size FROM {name}_c')},
{name}_k AS (SELECT r.v, r.parent, r.rank, c.size FROM {name}_r r JOIN {name}_c c ON c.v = r.parent),
{name}_po AS (SELECT k.parent, k.rank, k.v,
    lp.v leaf_parent,
    CASE WHEN k.rank = k.size - 1 THEN g.parent WHEN k.rank = rt.root THEN sc.v ELSE np.v END helper_parent,
    CASE WHEN k.rank = k.size - 1 THEN coalesce(ro.v, k.v) ELSE lc.v END "left", rc.v "right",
    CASE WHEN k.rank = k.size - 1 THEN k.size = 1 ELSE x.left_leaf END left_is_leaf, x.right_leaf right_is_leaf, k.rank = k.size - 1 is_successor
  FROM {name}_k k JOIN hf_links x ON x.size = k.size AND x.y = k.rank JOIN {name}_r g ON g.v = k.parent
  LEFT JOIN hf_root rt ON rt.size = k.size
  LEFT JOIN {name}_k lp ON lp.parent = k.parent AND lp.rank = x.leaf_parent
  LEFT JOIN {name}_k np ON np.parent = k.parent AND np.rank = x.node_parent
  LEFT JOIN {name}_k lc ON lc.parent = k.parent AND lc.rank = x.left_label
  LEFT JOIN {name}_k rc ON rc.parent = k.parent AND rc.rank = x.right_label
  LEFT JOIN {name}_k ro ON ro.parent = k.parent AND ro.rank = rt.root
  LEFT JOIN {name}_k sc ON sc.parent = k.parent AND sc.rank = k.size - 1)"""


def sql(*ctes: str, select: str) -> str:
    return f"WITH RECURSIVE {', '.join(ctes)} {select}"


_SOURCES = "(SELECT source, row_number() OVER (ORDER BY source) sk FROM (SELECT DISTINCT source FROM documents))"
DOCS_E = edges("dc", f"""SELECT 11 * {_S} + doc_id a, 12 * {_S} + sk b FROM documents JOIN {_SOURCES} USING (source)
  UNION SELECT 12 * {_S} + sk, 13 * {_S} + lk FROM documents JOIN {_SOURCES} USING (source) JOIN (SELECT lang, row_number() OVER (ORDER BY lang) lk FROM (SELECT DISTINCT lang FROM documents)) USING (lang)""")
SUPPLY_E = edges("supply", f"SELECT DISTINCT 6 * {_S} + l_partkey a, 4 * {_S} + l_suppkey b FROM lineitem")
SPIDER_E = edges("spider", f"""SELECT 10 * {_S} + conv_id * 1000 + turn a, coalesce(10 * {_S} + conv_id * 1000 + lag(turn) OVER (PARTITION BY conv_id ORDER BY turn), 9 * {_S}) b FROM (SELECT DISTINCT conv_id, turn FROM conversations)""")
#: t(v, parent, level) of users in a path with their events in chains below.
CHAIN = f"""ev AS (SELECT 8 * {_S} + event_id v, coalesce(8 * {_S} + lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id), 7 * {_S} + user_id) parent, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) nth, user_id FROM events),
us AS (SELECT user_id, row_number() OVER (ORDER BY user_id) - 1 level, lag(user_id) OVER (ORDER BY user_id) prev FROM (SELECT DISTINCT user_id FROM events)),
chain_t AS (SELECT v, parent, us.level + nth AS level FROM ev JOIN us USING (user_id) UNION ALL SELECT 7 * {_S} + user_id, 7 * {_S} + prev, level FROM us),
chain_e AS (SELECT v src, parent dst FROM chain_t WHERE parent IS NOT NULL UNION SELECT parent, v FROM chain_t WHERE parent IS NOT NULL)"""
