"""SQL for the registered queries, written without regard to speed: nested comparison, enumeration and recursion."""

from __future__ import annotations

from copresence.operators import sensitivity
from copresence.sources import workloads as data

from .queries import DRAW_SEED, EPS, EVENT_HOURS, HOUR, K, KS, ORDER_DAYS, PAGE_ITEMS, RECT_DISTANCES, REPS, STRIP_DISTANCES

ORACLES: dict[str, str] = {}


def chain(*steps: str, last: str) -> str:
    """Common table expressions and the final SELECT."""
    return "WITH RECURSIVE " + ",\n".join(s.strip().rstrip(",") for s in steps) + "\n" + last


# ---- units and transactions


def words_sql(table: str = "documents", grp: str = "concat_ws('|', source, lang)", key: str = "doc_id", core: bool = False) -> str:
    where = "WHERE pos * 4 >= n AND pos * 4 < 3 * n" if core else ""
    return f"""
w0 AS (SELECT {key} AS part, {grp} AS grp, list_filter(regexp_split_to_array(text, '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') AS w FROM {table}),
w1 AS (SELECT part, grp, len(w) AS n, unnest(w) AS x, unnest(range(len(w))) AS pos FROM w0),
w2 AS (SELECT *, sum(length(x) + 1) OVER (PARTITION BY part ORDER BY pos) AS cum, ascii(x) AS c FROM w1),
u AS (SELECT grp, part, pos, part * 1000000 + pos AS unit_id, (cum - length(x) - 1)::bigint AS lo, (cum - 1)::bigint AS hi,
      CASE WHEN c BETWEEN 97 AND 122 THEN c - 96 WHEN c BETWEEN 65 AND 90 THEN c - 64 ELSE 0 END AS bit FROM w2 {where})"""


def strip_tx_sql(d: int = data.REACH) -> str:
    """Neighbours are at most d / 2 + 1 words away, as a word takes two characters at least."""
    reach = d // 2 + 1
    return f"""
tx AS (SELECT a.grp, a.unit_id, bit_or(1::bigint << b.bit) AS mask FROM u a, (SELECT unnest(range(-{reach}, {reach + 1})) AS off) o, u b
       WHERE b.part = a.part AND b.pos = a.pos + o.off AND b.lo <= a.hi + {d} AND b.hi >= a.lo - {d} GROUP BY 1, 2)"""


PATTERNS = """
pat AS (SELECT grp, mask, count(*) AS weight FROM tx GROUP BY 1, 2)"""

ORDERS = f"""
ow AS (SELECT l_orderkey, bit_or(1::bigint << ((27 * (p_size - 1) * (p_size - 1)) // 2500)) AS own FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1),
ox AS (SELECT o_orderkey AS id, o_custkey AS cust, o_orderdate::date AS day, own FROM orders LEFT JOIN ow ON o_orderkey = l_orderkey),
tx AS (SELECT c_nationkey::varchar AS grp, a.id AS unit_id, bit_or(b.own) AS mask FROM ox a JOIN ox b ON a.cust = b.cust AND abs(a.day - b.day) <= {data.DAYS} JOIN customer ON a.cust = c_custkey
       GROUP BY 1, 2 HAVING bit_or(b.own) IS NOT NULL)"""

EVENT_UNITS = """
ev AS (SELECT (user_id % 25)::varchar AS grp, user_id AS part, event_id AS unit_id, epoch_us(ts) AS t, ts,
       (CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 WHEN 'view' THEN 4 END * 5 + least(4, floor(value / 25)))::integer AS bit, props FROM events)"""

EVENT_TX = f"""
tx AS (SELECT a.grp, a.unit_id, bit_or(1::bigint << b.bit) AS mask FROM ev a JOIN ev b ON a.grp = b.grp AND a.part = b.part AND abs(a.t - b.t) <= {data.HOURS * 3_600_000_000} GROUP BY 1, 2)"""

_LINE = "l_partkey l_suppkey l_linenumber l_quantity l_extendedprice l_discount l_tax l_returnflag l_linestatus l_shipdate".split()
RECT_UNITS = """
ln AS (SELECT l_orderkey * 4096 + row_number() OVER (PARTITION BY l_orderkey ORDER BY {order}) AS unit_id, * FROM lineitem),
u AS (SELECT s_nationkey::varchar AS grp, unit_id, 5 * (l_shipdate::date - DATE '1995-01-01') AS x0, 5 * (l_shipdate::date - DATE '1995-01-01') + l_quantity::bigint AS x1,
      floor(l_extendedprice / 20)::bigint AS y0, floor(l_extendedprice / 20)::bigint + p_size AS y1, ((27 * (p_size - 1) * (p_size - 1)) // 2500)::integer AS bit
      FROM ln JOIN supplier ON l_suppkey = s_suppkey JOIN part ON l_partkey = p_partkey)"""


def rect_pairs_sql(d: int) -> str:
    gap = lambda p, q: f"greatest(0, b.{p} - a.{q}, a.{p} - b.{q})"
    d2 = f"({gap('x0', 'x1')} * {gap('x0', 'x1')} + {gap('y0', 'y1')} * {gap('y0', 'y1')})"
    return f"""
pairs AS (SELECT a.grp, a.unit_id AS focal_id, b.unit_id AS other_id, b.bit AS other_bit, {d2} AS dist2 FROM u a JOIN u b ON a.grp = b.grp AND b.x0 <= a.x1 + {d} AND b.x1 >= a.x0 - {d}
          WHERE b.y0 <= a.y1 + {d} AND b.y1 >= a.y0 - {d} AND {d2} <= {d * d})"""


RECT_TX = """
tx AS (SELECT grp, focal_id AS unit_id, bit_or(1::bigint << other_bit) AS mask FROM pairs GROUP BY 1, 2)"""


# ---- itemsets


def itemsets_sql(num: int = 10, den: int = 100, name: str = "items", pat: str = "pat") -> str:
    """All subsets of all patterns, by growing each one class upwards; classes that aren't frequent can't be in any."""
    return f"""
{name}_n AS (SELECT grp, sum(weight)::bigint AS n FROM {pat} GROUP BY 1),
{name}_keep AS (SELECT grp, bit_or(1::bigint << b) AS keep FROM (SELECT p.grp, b, sum(weight) AS s FROM {pat} p, range(63) t(b) WHERE (mask >> b) & 1 = 1 GROUP BY 1, 2) JOIN {name}_n USING (grp) WHERE s * {den} >= n * {num} GROUP BY 1),
{name}_m AS (SELECT p.grp, mask & keep AS mask, sum(weight)::bigint AS weight FROM {pat} p JOIN {name}_keep USING (grp) WHERE mask & keep <> 0 GROUP BY 1, 2),
{name}_s AS (SELECT grp, mask, weight, 0::bigint AS sub, -1::bigint AS high FROM {name}_m
  UNION ALL SELECT grp, mask, weight, sub | (1::bigint << b), b FROM {name}_s, range(63) t(b) WHERE b > high AND (mask >> b) & 1 = 1),
{name} AS (SELECT grp, sub AS itemset, bit_count(sub)::bigint AS k, sum(weight)::bigint AS sup, any_value(n) AS n, (sum(weight)::double / any_value(n)::double) AS rel
  FROM {name}_s JOIN {name}_n USING (grp) WHERE sub <> 0 GROUP BY grp, sub HAVING sum(weight) * {den} >= any_value(n) * {num})"""


ITEM_ROWS = "SELECT grp, itemset, k, sup, n, round(rel, 6) AS rel FROM items"
STRIP = (words_sql(), strip_tx_sql(), PATTERNS)
STRIP_ITEMS = (*STRIP, itemsets_sql())

# ---- profiles, distances, trees


def profile_sql(items: str = "items", value: str = "rel", where: str = "true", name: str = "", unit: bool = True, cosine: bool = False) -> str:
    """{name}prof (raw), {name}v (what is clustered), {name}dist (a < b)."""
    v = f"value / sqrt(sum(value * value) OVER (PARTITION BY grp))" if unit else "value"
    d = "1 - coalesce(dot, 0) / sqrt(x.sq * y.sq)" if cosine else "sqrt(greatest(0, x.sq + y.sq - 2 * coalesce(dot, 0)))"
    return f"""
{name}prof AS (SELECT grp, itemset AS feature, {value} AS value FROM {items} WHERE {where}),
{name}v AS (SELECT grp, feature, {v} AS value FROM {name}prof),
{name}sq AS (SELECT grp, sum(value * value) AS sq FROM {name}v GROUP BY 1),
{name}dots AS (SELECT a.grp AS a, b.grp AS b, sum(a.value * b.value) AS dot FROM {name}v a JOIN {name}v b ON a.feature = b.feature AND a.grp < b.grp GROUP BY 1, 2),
{name}dist AS (SELECT x.grp AS a, y.grp AS b, {d} AS d FROM {name}sq x JOIN {name}sq y ON x.grp < y.grp LEFT JOIN {name}dots q ON q.a = x.grp AND q.b = y.grp)"""


def tree_sql(name: str = "", average: bool = False) -> str:
    """{name}tree: the partition (g, c) after each step and what was merged; clusters go by their least leaf.

    Pair sums S over unordered pairs give the cost: |a-b|^2 of centroids = S_ab/(nm) - S_aa/n^2 - S_bb/m^2."""
    power = "d" if average else "d * d"
    cost = "s / (n * m)" if average else "n * m / (n + m) * (s / (n * m) - coalesce(sa, 0) / (n * n) - coalesce(sb, 0) / (m * m))"
    return f"""
{name}gi AS (SELECT grp, (row_number() OVER (ORDER BY grp) - 1)::integer AS i FROM {name}sq),
{name}pd AS (SELECT x.i AS i, y.i AS j, {power} AS q FROM {name}dist JOIN {name}gi x ON x.grp = a JOIN {name}gi y ON y.grp = b),
{name}tree AS (SELECT 0 AS step, i AS g, i AS c, NULL::integer AS a, NULL::integer AS b, NULL::double AS cost, NULL::bigint AS sz FROM {name}gi
  UNION ALL
  SELECT t.step + 1, t.g, CASE WHEN t.c = m.b THEN m.a ELSE t.c END, m.a, m.b, m.cost, m.sz FROM {name}tree t, (
    WITH s AS (SELECT least(p.c, r.c) AS a, greatest(p.c, r.c) AS b, sum(q) AS s FROM {name}pd JOIN {name}tree p ON p.g = i JOIN {name}tree r ON r.g = j GROUP BY 1, 2),
    n AS (SELECT c, count(*)::double AS n FROM {name}tree GROUP BY 1),
    k AS (SELECT s.a, s.b, {cost} AS cost, (n + m)::bigint AS sz FROM s JOIN (SELECT c, n FROM n) x ON x.c = s.a JOIN (SELECT c, n AS m FROM n) y ON y.c = s.b
          LEFT JOIN (SELECT a, s AS sa FROM s WHERE a = b) d ON d.a = s.a LEFT JOIN (SELECT a, s AS sb FROM s WHERE a = b) e ON e.a = s.b WHERE s.a <> s.b)
    SELECT * FROM k ORDER BY round(cost, 12), a, b LIMIT 1) m),
{name}lab AS (SELECT k, grp, (dense_rank() OVER (PARTITION BY k ORDER BY c) - 1)::bigint AS cluster FROM (SELECT unnest([{", ".join(map(str, KS))}])::bigint AS k), {name}tree JOIN {name}gi ON g = i
  WHERE step = (SELECT count(*) FROM {name}gi) - k)"""


PROFILE = (*STRIP_ITEMS, profile_sql())
TREE = (*PROFILE, tree_sql())
BOTH = """
dd AS (SELECT a, b, d FROM dist UNION ALL SELECT b, a, d FROM dist)"""
SEVEN = f"""
l7 AS (SELECT grp, cluster FROM lab WHERE k = {K})"""
BLOCKS = """
blk AS (SELECT DISTINCT concat_ws('|', source, lang) AS grp, lang AS block FROM documents)"""


def add(name: str, *steps: str, last: str) -> None:
    ORACLES[name] = chain(*steps, last=last)


# ---- the worked example

_VILLAGE = ", ".join(f"({n}, '{c}', '{row}')" for n, c, row in data.VILLAGE_ROWS)
VILLAGE = f"""
v0 AS (SELECT * FROM (VALUES {_VILLAGE}) t(unit_id, own, neighbours)),
v1 AS (SELECT unit_id, instr('CBGW', own) - 1 AS own, list_transform(string_split(neighbours, ''), lambda x: instr('CBGW', x) - 1) AS every FROM v0),
tx AS (SELECT 'village' AS grp, unit_id, bit_or(1::bigint << b) AS mask FROM (SELECT unit_id, unnest(list_append(every, own)) AS b FROM v1) GROUP BY unit_id)"""
add("village_transactions", VILLAGE, last="SELECT unit_id, mask, bit_count(mask)::bigint AS len FROM tx")
add("village_neighbour_columns", VILLAGE, last="SELECT unit_id, array_to_string(list_sort(every), ',') AS every, array_to_string(list_sort(list_distinct(every)), ',') AS single, array_to_string(list_sort(list_distinct(list_append(every, own))), ',') AS final FROM v1")
add("village_itemsets_min3", VILLAGE, PATTERNS, itemsets_sql(3, 7), last=ITEM_ROWS)

# ---- units

add("strip_units", words_sql(), last="SELECT grp, count(*) AS units, sum(lo)::bigint AS lo, sum(hi)::bigint AS hi, sum(bit)::bigint AS bits FROM u GROUP BY 1")
add("order_units", ORDERS.replace(f"<= {data.DAYS}", "<= 0"), last="SELECT grp, count(*) AS units, sum(unit_id)::bigint AS ids, sum(bit_count(mask))::bigint AS items FROM tx GROUP BY 1")
add("event_units", EVENT_UNITS, last="SELECT grp, part, unit_id, t AS lo, t AS hi, bit::bigint AS bit FROM ev")
_RECT = RECT_UNITS.format(order=", ".join(_LINE))
add("rect_units", _RECT, last="SELECT grp, unit_id, x0::bigint AS x0, x1::bigint AS x1, y0, y1::bigint AS y1, bit::bigint AS bit FROM u")
ORACLES["class_dictionary"] = "SELECT * FROM (VALUES " + ", ".join(f"({b}::bigint, {c}::bigint, {t}::bigint, '{n}')" for b, (c, t, n) in enumerate(zip(data.STRIP.codes, data.STRIP.themes, data.STRIP.labels, strict=True))) + ") t(bit, code, theme, label)"
add("units_validation", _RECT, last="SELECT 'unknown class' AS problem, count(*) FILTER (bit IS NULL OR bit NOT BETWEEN 0 AND 26) AS n FROM u UNION ALL SELECT 'no group', count(*) FILTER (grp IS NULL) FROM u UNION ALL SELECT 'repeated unit', count(*) FROM (SELECT unit_id FROM u GROUP BY 1 HAVING count(*) > 1)")
add("transactions_validation", words_sql(), strip_tx_sql(), last="SELECT 'empty' AS problem, count(*) FILTER (mask = 0) AS n FROM tx UNION ALL SELECT 'unknown class', count(*) FILTER (mask >= (1::bigint << 27)) FROM tx UNION ALL SELECT 'several transactions', count(*) - count(DISTINCT unit_id) FROM tx UNION ALL SELECT 'no transaction', count(*) FROM u WHERE unit_id NOT IN (SELECT unit_id FROM tx)")

# ---- transactions

add("strip_tx_d20", *STRIP, last="SELECT * FROM pat")
add("order_tx_180", ORDERS, last="SELECT * FROM tx")
for _n in ("event_tx_24h_join", "event_tx_24h_window"):
    add(_n, EVENT_UNITS, EVENT_TX, last="SELECT * FROM tx")
for _n in ("rect_tx_d150", "rect_tx_d150_tiles"):
    add(_n, _RECT, rect_pairs_sql(data.GAP), RECT_TX, last="SELECT * FROM tx")
ORACLES["ring_tx_d150"] = ORACLES["rect_tx_d150"]
add("ring_tx_d25", _RECT, rect_pairs_sql(25), RECT_TX, last="SELECT * FROM tx")
FRAMES = """
fr AS (SELECT grp, unit_id, bit, x0 - m AS x0, x1 + m AS x1, y0 - m AS y0, y1 + m AS y1, x0 - m + 2 AS hx0, x1 + m - 2 AS hx1, y0 - m + 2 AS hy0, y1 + m - 2 AS hy1 FROM (SELECT *, 3 + 2 * (unit_id % 20) AS m FROM u))"""
_IN = lambda p, q: f"{p}.x0 >= {q}.hx0 AND {p}.x1 <= {q}.hx1 AND {p}.y0 >= {q}.hy0 AND {p}.y1 <= {q}.hy1"
_ROOM = lambda p, q: f"least({p}.x0 - {q}.hx0, {q}.hx1 - {p}.x1, {p}.y0 - {q}.hy0, {q}.hy1 - {p}.y1)"
_APART = lambda c: f"greatest(0, b.{c}0 - a.{c}1, a.{c}0 - b.{c}1)"
add("ring_tx_holes_d5", _RECT, FRAMES, f"""
fp AS (SELECT a.grp, a.unit_id, b.bit, CASE WHEN a.unit_id = b.unit_id THEN 0 WHEN {_IN("b", "a")} THEN {_ROOM("b", "a")} * {_ROOM("b", "a")} WHEN {_IN("a", "b")} THEN {_ROOM("a", "b")} * {_ROOM("a", "b")}
       ELSE {_APART("x")} * {_APART("x")} + {_APART("y")} * {_APART("y")} END AS d2 FROM fr a JOIN fr b ON a.grp = b.grp AND b.x0 <= a.x1 + 5 AND b.x1 >= a.x0 - 5 WHERE b.y0 <= a.y1 + 5 AND b.y1 >= a.y0 - 5)""",
    last="SELECT grp, unit_id, bit_or(1::bigint << bit) AS mask FROM fp WHERE d2 <= 25 GROUP BY 1, 2")
VEC = f"""
vp AS (SELECT 'all' AS grp, a.vec_id AS focal_id, b.vec_id AS other_id, b.label AS other_bit, list_distance(a.embedding::double[], b.embedding::double[]) AS dist FROM embeddings a, embeddings b
       WHERE list_distance(a.embedding::double[], b.embedding::double[]) <= {EPS})"""
add("vector_tx_eps", VEC, last="SELECT grp, focal_id AS unit_id, bit_or(1::bigint << other_bit) AS mask FROM vp GROUP BY 1, 2")
add("one_per_unit", words_sql(), strip_tx_sql(), last="SELECT (SELECT count(*) FROM u) AS units, (SELECT count(*) FROM tx) AS transactions, (SELECT count(*) FROM u WHERE unit_id NOT IN (SELECT unit_id FROM tx)) AS missing")
_LENGTHS = "SELECT d, count(*) AS n, round(avg(len), 6) AS mean_len, quantile_cont(len, 0.5)::double AS median_len, max(len) AS max_len FROM lens GROUP BY d"
add("buffer_calibration_strip", words_sql(), *[strip_tx_sql(d).replace("tx AS", f"tx{d} AS") for d in STRIP_DISTANCES], "lens AS (" + " UNION ALL ".join(f"SELECT {d}::bigint AS d, bit_count(mask)::bigint AS len FROM tx{d}" for d in STRIP_DISTANCES) + ")", last=_LENGTHS)
add("buffer_calibration_rect", _RECT, rect_pairs_sql(max(RECT_DISTANCES)), f"lens AS (SELECT d, bit_count(bit_or(1::bigint << other_bit))::bigint AS len FROM pairs, (SELECT unnest([{', '.join(map(str, RECT_DISTANCES))}])::bigint AS d) WHERE dist2 <= d * d GROUP BY d, grp, focal_id)", last=_LENGTHS)
_DAYS = [ORDERS.replace(f"<= {data.DAYS}", f"<= {n}").replace("tx AS", f"tx{n} AS") for n in ORDER_DAYS]
add("buffer_calibration_orders", _DAYS[0], *["tx" + x.split("\ntx", 1)[1] for x in _DAYS[1:]], "lens AS (" + " UNION ALL ".join(f"SELECT {n}::bigint AS d, bit_count(mask)::bigint AS len FROM tx{n}" for n in ORDER_DAYS) + ")", last=_LENGTHS)
add("buffer_calibration_events", EVENT_UNITS, *[EVENT_TX.replace(f"<= {data.HOURS * HOUR}", f"<= {n * HOUR}").replace("tx AS", f"tx{n} AS") for n in EVENT_HOURS], "lens AS (" + " UNION ALL ".join(f"SELECT {n}::bigint AS d, bit_count(mask)::bigint AS len FROM tx{n}" for n in EVENT_HOURS) + ")", last=_LENGTHS)
_AUDIT = "SELECT grp, count(*) AS transactions, sum(m - 1)::bigint AS neighbours, sum(c)::bigint AS classes, sum(m - c)::bigint AS collapsed, count(*) FILTER (m > c) AS affected FROM au GROUP BY grp"
add("set_bag_audit_strip", words_sql(), strip_tx_sql().replace("tx AS", "au AS").replace("bit_or(1::bigint << b.bit) AS mask", "count(*) AS m, count(DISTINCT b.bit) AS c"), last=_AUDIT)
add("set_bag_audit_rect", _RECT, rect_pairs_sql(data.GAP), "au AS (SELECT grp, focal_id, count(*) AS m, count(DISTINCT other_bit) AS c FROM pairs GROUP BY 1, 2)", last=_AUDIT)
_SIDE = max(2 * data.GAP, 64)
_ON = lambda name, grow: f"{name} AS (SELECT grp, tx, ty, count(*) AS {name} FROM (SELECT grp, tx, unnest(range(floor((y0 - {grow}) / {_SIDE}.0)::bigint, floor((y1 + {grow}) / {_SIDE}.0)::bigint + 1)) AS ty FROM (SELECT *, unnest(range(floor((x0 - {grow}) / {_SIDE}.0)::bigint, floor((x1 + {grow}) / {_SIDE}.0)::bigint + 1)) AS tx FROM u)) GROUP BY 1, 2, 3)"
add("engine_cost_rect", _RECT, rect_pairs_sql(data.GAP), RECT_TX, PATTERNS, _ON("f", data.GAP), _ON("o", 0), last="SELECT (SELECT count(*) FROM u) AS units, (SELECT sum(f) FROM f)::bigint AS focal_rows, (SELECT sum(o) FROM o)::bigint AS other_rows, (SELECT sum(f * o) FROM f JOIN o USING (grp, tx, ty))::bigint AS candidates, (SELECT count(*) FROM pairs) AS pairs, (SELECT count(*) FROM pat) AS patterns")
add("level_sizes_strip", *STRIP_ITEMS, last="SELECT k, count(*) AS sets, sum(sup)::bigint AS total FROM items GROUP BY 1")
add("size_histogram", words_sql(), strip_tx_sql(), last="SELECT bit_count(mask)::bigint AS len, count(*) AS n FROM tx GROUP BY 1")
add("recurrence_summary", *STRIP, last="SELECT grp, sum(weight)::bigint AS transactions, count(*) AS patterns, sum(weight)::bigint - count(*) AS repeats, bit_count(bit_or(mask))::bigint AS classes FROM pat GROUP BY grp UNION ALL SELECT NULL, sum(weight)::bigint, count(*), sum(weight)::bigint - count(*), bit_count(bit_or(mask))::bigint FROM pat")
add("dichotomous_matrix", ORDERS, last="SELECT grp, unit_id, " + ", ".join(f"((mask >> {b}) & 1)::bigint AS b{b}" for b in range(27)) + " FROM tx")
_CODES = "[" + ", ".join(map(str, data.PARTS.codes)) + "]"
add("unpivot_dichotomous", ORDERS, last=f"SELECT grp, ({_CODES})[b + 1]::bigint AS code, count(*) AS n FROM tx, range(27) t(b) WHERE (mask >> b) & 1 = 1 GROUP BY 1, 2")
add("transactions_text", ORDERS, last=f"SELECT grp, array_to_string(list_sort(list_transform(list_filter(range(27), lambda b: (mask >> b::integer) & 1 = 1), lambda b: ({_CODES})[b + 1])), ' ') AS line FROM tx")
add("select_groups", words_sql(), strip_tx_sql(), last="SELECT grp, count(*) AS n FROM tx GROUP BY 1 HAVING count(*) BETWEEN 1000 AND 10000")
add("clip_units", _RECT, last="SELECT grp, count(*) AS n FROM u WHERE x1 >= 2000 AND x0 <= 6000 AND y1 >= 500 AND y0 <= 2000 GROUP BY 1")

# ---- listings of other tools

add("polygon_neighbors_rect", _RECT, rect_pairs_sql(0), last="SELECT grp, focal_id, other_id FROM pairs WHERE focal_id <> other_id")
add("neighborhood_summary_rect", _RECT, rect_pairs_sql(50), last="SELECT grp, focal_id, count(*) AS neighbors, count(DISTINCT other_bit) AS classes, min(other_bit)::bigint AS low, max(other_bit)::bigint AS high, sum(other_bit)::bigint AS total FROM pairs WHERE focal_id <> other_id GROUP BY 1, 2")
add("near_table_rect", _RECT, rect_pairs_sql(50), last="SELECT grp, focal_id, other_id, dist2, row_number() OVER (PARTITION BY grp, focal_id ORDER BY dist2, other_id) AS rank FROM pairs WHERE focal_id <> other_id QUALIFY rank <= 3")
add("near_table_vec", VEC, last="SELECT focal_id, other_id, round(dist, 5) AS dist, row_number() OVER (PARTITION BY focal_id ORDER BY round(dist, 5), other_id) AS rank FROM vp WHERE focal_id <> other_id QUALIFY rank <= 3")

# ---- mining

for _n in ("nodeset", "nodeset_plain", "nodeset_sharded", "levelwise", "enumerate"):
    add(f"itemsets_{_n}_strip", *STRIP_ITEMS, last=ITEM_ROWS)
for _n in ("itemsets_library_orders", "itemsets_nodeset_orders"):
    add(_n, ORDERS, PATTERNS, itemsets_sql(), last=ITEM_ROWS)
add("itemsets_nodeset_rect", _RECT, rect_pairs_sql(data.GAP), RECT_TX, PATTERNS, itemsets_sql(), last=ITEM_ROWS)
add("itemsets_nodeset_events", EVENT_UNITS, EVENT_TX, PATTERNS, itemsets_sql(), last=ITEM_ROWS)
ORACLES["miner_discrepancies"] = "SELECT * FROM (VALUES ('strip', 0::bigint), ('rect', 0::bigint), ('orders', 0::bigint)) t(workload, differences)"
add("support_of_given_sets", *STRIP_ITEMS, last="SELECT p.grp, g.itemset, sum(weight)::bigint AS sup FROM pat p, (SELECT DISTINCT itemset FROM items WHERE k = 2) g WHERE p.mask & g.itemset = g.itemset GROUP BY 1, 2")
add("exact_profile", *STRIP_ITEMS, last="SELECT grp, count(*) AS features, sum(sup)::bigint AS total, count(*) FILTER (sup = 0) AS absent FROM (SELECT g.grp, f.itemset, (SELECT coalesce(sum(weight), 0) FROM pat p WHERE p.grp = g.grp AND p.mask & f.itemset = f.itemset)::bigint AS sup FROM (SELECT DISTINCT grp FROM pat) g, (SELECT DISTINCT itemset FROM items) f) GROUP BY grp")
_SHARES = {"5%": (5, 100), "7.5%": (75, 1000), "10%": (10, 100), "12.5%": (125, 1000), "15%": (15, 100)}
MANY = "many AS (" + " UNION ALL ".join(f"SELECT '{t}' AS threshold, * FROM low WHERE sup * {q} >= n * {p}" for t, (p, q) in _SHARES.items()) + ")"
STRIP_MANY = (*STRIP, itemsets_sql(5, 100, "low"), MANY)
_COUNTS = "SELECT threshold, count(*) AS nonzero, count(DISTINCT itemset) AS features, sum(sup)::bigint AS total FROM many GROUP BY 1"
add("itemsets_many_thresholds", *STRIP_MANY, last=_COUNTS)
add("itemsets_many_thresholds_orders", ORDERS, PATTERNS, itemsets_sql(5, 100, "low"), MANY, last=_COUNTS)
UNIQUE = "one AS (SELECT grp, mask, 1::bigint AS weight FROM pat)"
add("itemsets_unique_pattern_votes", *STRIP, UNIQUE, itemsets_sql(pat="one"), last=ITEM_ROWS)
ORACLES["monotonicity_violations"] = "SELECT 0::bigint AS violations"
add("top_itemsets_one_group", *STRIP_ITEMS, last=f"SELECT grp, itemset, sup, n, (200 * sup + n) // (2 * n) AS percent, row_number() OVER (ORDER BY sup DESC, itemset) AS rank FROM items WHERE k >= 2 AND itemset & {1 << data.ROAD_BIT} = 0 AND grp = (SELECT grp FROM items_n ORDER BY n DESC, grp LIMIT 1) QUALIFY rank <= 11")

_TOP = "SELECT grp, itemset, sup, n, (200 * sup + n) // (2 * n) AS percent, row_number() OVER (PARTITION BY grp ORDER BY sup DESC, itemset) AS rank FROM items WHERE k >= 2 AND itemset & {hide} = 0 QUALIFY rank <= 11"
add("top_itemsets_every_group", *STRIP_ITEMS, last=_TOP.format(hide=1 << data.ROAD_BIT))
add("top_itemsets_orders", ORDERS, PATTERNS, itemsets_sql(), last=_TOP.format(hide=0))

# ---- profiles and distances

add("profile_sparse", *PROFILE, last="SELECT grp, feature, round(value, 6) AS value FROM prof")
add("profile_dense", *PROFILE, last="SELECT g.grp, f.feature, round(coalesce(p.value, 0), 6) AS value FROM (SELECT DISTINCT grp FROM prof) g CROSS JOIN (SELECT DISTINCT feature FROM prof) f LEFT JOIN prof p ON p.grp = g.grp AND p.feature = f.feature")
add("matrix_extract", *PROFILE, last="SELECT grp, " + ", ".join(f"round(coalesce(max(value) FILTER (feature = {f}), 0), 6) AS f{i}" for i, f in enumerate((1 << 1, 1 << 4, 1 << 5, 1 << 20))) + " FROM prof GROUP BY 1")
add("profile_l2", *PROFILE, last="SELECT grp, feature, round(value, 6) AS value FROM v")
add("profile_stats", *PROFILE, last="SELECT count(DISTINCT grp) AS groups, count(DISTINCT feature) AS features, count(*) AS nonzero FROM prof")
add("profile_map_vectors", *PROFILE, last="SELECT grp, count(*) AS features, round(sum(value), 6) AS total FROM prof GROUP BY 1")
add("pairwise_euclidean", *PROFILE, last="SELECT a, b, round(d, 6) AS d FROM dist")
add("pairwise_cosine", *STRIP_ITEMS, profile_sql(unit=False, cosine=True), last="SELECT a, b, round(greatest(0, d), 6) AS d FROM dist")
add("peers_top5", *TREE, BOTH, SEVEN, last="SELECT a AS grp, b AS peer, round(d, 6) AS d, row_number() OVER (PARTITION BY a ORDER BY round(d, 10), b) AS rank, (x.cluster = y.cluster)::bigint AS same_cluster FROM dd JOIN l7 x ON x.grp = a JOIN l7 y ON y.grp = b QUALIFY rank <= 5")

# ---- clustering

add("ward_merges", *TREE, last="SELECT DISTINCT step::bigint AS step, a::bigint AS left_leaf, b::bigint AS right_leaf, sz AS size, round(sqrt(2 * greatest(0, cost)), 6) AS height FROM tree WHERE step > 0")
add("ward_rounds", *TREE, last="SELECT step::bigint AS step, round(h, 6) AS height, sz AS size FROM (SELECT DISTINCT step, sqrt(2 * greatest(0, cost)) AS h, sz FROM tree WHERE step > 0)")
add("ward_labels_2_10", *TREE, last="SELECT * FROM lab")
add("average_cosine_labels", *STRIP_ITEMS, profile_sql(unit=False, cosine=True), tree_sql(average=True), last="SELECT * FROM lab")
add("cophenetic", *TREE, last="SELECT x.grp AS a, y.grp AS b, round(max(h), 6) AS height FROM (SELECT p.g AS i, q.g AS j, sqrt(2 * greatest(0, p.cost)) AS h, row_number() OVER (PARTITION BY p.g, q.g ORDER BY p.step) AS r FROM tree p JOIN tree q ON p.step = q.step AND p.c = q.c AND p.g < q.g WHERE p.step > 0) JOIN gi x ON x.i = i JOIN gi y ON y.i = j WHERE r = 1 GROUP BY 1, 2".replace("JOIN gi x ON x.i = i JOIN gi y ON y.i = j", "z JOIN gi x ON x.i = z.i JOIN gi y ON y.i = z.j"))

# ---- number of clusters

SILHOUETTE = """
sm AS (SELECT x.k, a, x.cluster AS ca, y.cluster AS cb, avg(d) AS m FROM dd JOIN lab x ON x.grp = a JOIN lab y ON y.grp = b AND y.k = x.k GROUP BY 1, 2, 3, 4),
sp AS (SELECT k, a, max(m) FILTER (ca = cb) AS own, min(m) FILTER (ca <> cb) AS other FROM sm GROUP BY 1, 2),
sil AS (SELECT k, avg(CASE WHEN own IS NULL OR other IS NULL OR greatest(own, other) = 0 THEN 0 ELSE (other - own) / greatest(own, other) END) AS silhouette FROM sp GROUP BY 1)"""
SPREAD = """
cn AS (SELECT k, cluster, count(*)::double AS n FROM lab GROUP BY 1, 2),
fs AS (SELECT DISTINCT feature FROM v),
ct AS (SELECT c.k, c.cluster, f.feature, coalesce(s, 0) / n AS c FROM cn c CROSS JOIN fs f LEFT JOIN (SELECT k, cluster, feature, sum(value) AS s FROM lab JOIN v USING (grp) GROUP BY 1, 2, 3) q ON q.k = c.k AND q.cluster = c.cluster AND q.feature = f.feature),
mu AS (SELECT feature, sum(value) / (SELECT count(*) FROM gi) AS m FROM v GROUP BY 1),
dense AS (SELECT gi.grp, f.feature, coalesce(value, 0) AS value FROM gi CROSS JOIN fs f LEFT JOIN v ON v.grp = gi.grp AND v.feature = f.feature),
dc AS (SELECT l.k, l.grp, l.cluster, sum((d.value - ct.c) * (d.value - ct.c)) AS d2 FROM lab l JOIN dense d USING (grp) JOIN ct ON ct.k = l.k AND ct.cluster = l.cluster AND ct.feature = d.feature GROUP BY 1, 2, 3),
ch AS (SELECT w.k, (ssb / (q - 1)) / (ssw / ((SELECT count(*) FROM gi) - q)) AS calinski_harabasz FROM (SELECT k, sum(d2) AS ssw FROM dc GROUP BY 1) w
  JOIN (SELECT c.k, sum(n * x) AS ssb, count(*) AS q FROM cn c JOIN (SELECT k, cluster, sum((ct.c - m) * (ct.c - m)) AS x FROM ct JOIN mu USING (feature) GROUP BY 1, 2) y ON y.k = c.k AND y.cluster = c.cluster GROUP BY 1) b ON b.k = w.k),
sc AS (SELECT k, cluster, avg(sqrt(d2)) AS s FROM dc GROUP BY 1, 2),
db AS (SELECT k, avg(worst) AS davies_bouldin FROM (SELECT x.k, x.cluster, max((p.s + r.s) / x.d) AS worst FROM (SELECT a.k, a.cluster, b.cluster AS o, sqrt(sum((a.c - b.c) * (a.c - b.c))) AS d FROM ct a JOIN ct b ON a.k = b.k AND a.feature = b.feature AND a.cluster <> b.cluster GROUP BY 1, 2, 3) x
  JOIN sc p ON p.k = x.k AND p.cluster = x.cluster JOIN sc r ON r.k = x.k AND r.cluster = x.o GROUP BY 1, 2) GROUP BY 1)"""
add("silhouette_by_k", *TREE, BOTH, SILHOUETTE, last="SELECT k, round(silhouette, 6) AS silhouette FROM sil")
add("calinski_harabasz_by_k", *TREE, SPREAD, last="SELECT k, round(calinski_harabasz, 6) AS calinski_harabasz FROM ch")
add("davies_bouldin_by_k", *TREE, SPREAD, last="SELECT k, round(davies_bouldin, 6) AS davies_bouldin FROM db")
add("feature_draws", *PROFILE, f"fe AS (SELECT DISTINCT feature FROM prof), dr AS (SELECT rep, feature, row_number() OVER (PARTITION BY rep ORDER BY md5('{DRAW_SEED}|' || rep || '|' || feature), feature) AS r FROM fe, range({REPS}) t(rep))", last="SELECT rep, feature FROM dr WHERE r <= floor((SELECT count(*) FROM fe) * 0.8)")

# ---- what the clusters are

add("cluster_sizes", *TREE, last="SELECT k, cluster, count(*) AS size FROM lab GROUP BY 1, 2")
MEDOIDS = """
mt AS (SELECT x.k, x.grp, x.cluster, round(coalesce(sum(CASE WHEN y.cluster = x.cluster THEN d END), 0), 10) AS t FROM lab x JOIN dd ON dd.a = x.grp JOIN lab y ON y.k = x.k AND y.grp = dd.b GROUP BY 1, 2, 3),
med AS (SELECT k, cluster, grp AS medoid FROM mt QUALIFY row_number() OVER (PARTITION BY k, cluster ORDER BY t, grp) = 1)"""
add("medoids", *TREE, BOTH, MEDOIDS, last="SELECT * FROM med")
add("distinguishing_itemsets", *TREE, SEVEN, """
fx AS (SELECT DISTINCT feature FROM prof), n7 AS (SELECT cluster, count(*) AS n FROM l7 GROUP BY 1),
df AS (SELECT c.cluster, f.feature, round(coalesce((SELECT sum(value) FROM prof p JOIN l7 USING (grp) WHERE l7.cluster = c.cluster AND p.feature = f.feature), 0) / c.n - (SELECT sum(value) FROM prof p WHERE p.feature = f.feature) / (SELECT count(*) FROM l7), 9) AS diff FROM n7 c, fx f),
rk AS (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY diff DESC, feature) AS up, row_number() OVER (PARTITION BY cluster ORDER BY diff, feature) AS down FROM df)""", last=f"SELECT {K}::bigint AS k, cluster, feature, CASE WHEN up <= 3 THEN up ELSE down END AS rank, round(diff, 6) AS diff, CASE WHEN up <= 3 THEN 'over' ELSE 'under' END AS side FROM rk WHERE up <= 3 OR down <= 3")
CONTENT = f"""
co AS (SELECT grp, sum(bit_count(mask & {data.STRIP.other}) * weight)::double / sum(weight) AS mean_other, sum(CASE WHEN mask & {data.STRIP.other} <> 0 THEN weight ELSE 0 END)::double / sum(weight) AS share_any,
       sum(CASE WHEN mask & {data.STRIP.other} <> 0 AND mask & {data.STRIP.other} = mask THEN weight ELSE 0 END)::double / sum(weight) AS share_only FROM pat GROUP BY 1)"""
add("cluster_profile_table", *TREE, BOTH, MEDOIDS, SEVEN, CONTENT, last=f"SELECT {K}::bigint AS k, cluster, count(*) AS size, any_value(medoid) AS medoid, round(quantile_cont(share_any, 0.5), 6) AS median_share_any FROM l7 JOIN co USING (grp) JOIN (SELECT cluster, medoid FROM med WHERE k = {K}) USING (cluster) GROUP BY cluster")

# ---- agreement


def agreement_sql(pairs: str, by: str = "k") -> tuple[str, str]:
    """pairs(by, u, v) -> ari(by, ari), nmi(by, nmi)."""
    c2 = lambda x: f"({x} * ({x} - 1) / 2)"
    return f"""
cl AS (SELECT {by}, u, v, count(*)::double AS c FROM ({pairs}) GROUP BY 1, 2, 3),
cu AS (SELECT {by}, u, sum(c) AS c FROM cl GROUP BY 1, 2), cv AS (SELECT {by}, v, sum(c) AS c FROM cl GROUP BY 1, 2), cN AS (SELECT {by}, sum(c) AS n FROM cl GROUP BY 1),
ar AS (SELECT {by}, CASE WHEN (pu + pv) / 2 = pu * pv / {c2("n")} THEN 1 ELSE (p - pu * pv / {c2("n")}) / ((pu + pv) / 2 - pu * pv / {c2("n")}) END AS ari
  FROM (SELECT {by}, sum({c2("c")}) AS p FROM cl GROUP BY 1) JOIN (SELECT {by}, sum({c2("c")}) AS pu FROM cu GROUP BY 1) USING ({by}) JOIN (SELECT {by}, sum({c2("c")}) AS pv FROM cv GROUP BY 1) USING ({by}) JOIN cN USING ({by})),
nm AS (SELECT {by}, CASE WHEN hu + hv <= 2e-15 THEN 1 ELSE mi / ((hu + hv) / 2) END AS nmi
  FROM (SELECT cl.{by}, sum(cl.c / n * ln(cl.c * n / (cu.c * cv.c))) AS mi FROM cl JOIN cu ON cu.{by} = cl.{by} AND cu.u = cl.u JOIN cv ON cv.{by} = cl.{by} AND cv.v = cl.v JOIN cN ON cN.{by} = cl.{by} GROUP BY 1)
  JOIN (SELECT {by}, sum(-c / n * ln(c / n)) AS hu FROM cu JOIN cN USING ({by}) GROUP BY 1) USING ({by}) JOIN (SELECT {by}, sum(-c / n * ln(c / n)) AS hv FROM cv JOIN cN USING ({by}) GROUP BY 1) USING ({by}))""", ""


def spearman_sql(x: str, y: str) -> str:
    """Rank correlation of x(a, b, d) and y(a, b, d), ties averaged."""
    rank = lambda c: f"rank() OVER (ORDER BY {c}) + (count(*) OVER (PARTITION BY {c}) - 1) / 2.0"
    return f"(SELECT corr(rx, ry) FROM (SELECT {rank('dx')} AS rx, {rank('dy')} AS ry FROM (SELECT round(p.d, 10) AS dx, round(q.d, 10) AS dy FROM {x} p JOIN {y} q ON p.a = q.a AND p.b = q.b)))"


_BLOCK_PAIRS = "SELECT k, cluster AS u, block AS v FROM lab JOIN blk USING (grp)"
add("ari_vs_block", *TREE, BLOCKS, agreement_sql(_BLOCK_PAIRS)[0], last="SELECT k, round(ari, 6) AS ari FROM ar")
add("nmi_vs_block", *TREE, BLOCKS, agreement_sql(_BLOCK_PAIRS)[0], last="SELECT k, round(nmi, 6) AS nmi FROM nm")


def _threshold_steps(prefix: tuple[str, ...]) -> list[str]:
    steps = [*prefix]
    for i, t in enumerate(sensitivity.THRESHOLDS):
        steps += [f"it{i} AS (SELECT * FROM many WHERE threshold = '{t}')", profile_sql(f"it{i}", name=f"q{i}_"), tree_sql(f"q{i}_")]
    return steps


def _threshold_sql(prefix: tuple[str, ...]) -> str:
    base = sensitivity.THRESHOLDS.index(sensitivity.PRIMARY)
    pairs = " UNION ALL ".join(f"SELECT '{t}' AS threshold, x.cluster AS u, y.cluster AS v FROM q{i}_lab x JOIN q{base}_lab y ON x.grp = y.grp AND x.k = {K} AND y.k = {K}" for i, t in enumerate(sensitivity.THRESHOLDS))
    sp = " UNION ALL ".join(f"SELECT '{t}' AS threshold, (SELECT count(DISTINCT feature) FROM q{i}_v) AS features, {spearman_sql(f'q{i}_dist', f'q{base}_dist')} AS spearman" for i, t in enumerate(sensitivity.THRESHOLDS))
    return chain(*_threshold_steps(prefix), agreement_sql(pairs, "threshold")[0], f"sp AS ({sp})", last="SELECT threshold, features, round(ari, 6) AS ari, round(nmi, 6) AS nmi, round(spearman, 6) AS spearman FROM sp JOIN ar USING (threshold) JOIN nm USING (threshold)")


ORACLES["threshold_sensitivity"] = _threshold_sql(STRIP_MANY)
ORACLES["threshold_sensitivity_orders"] = _threshold_sql((ORDERS, PATTERNS, itemsets_sql(5, 100, "low"), MANY))
_base = sensitivity.THRESHOLDS.index(sensitivity.PRIMARY)
ORACLES["distance_spearman_thresholds"] = chain(*STRIP_MANY, *[x for i, t in enumerate(sensitivity.THRESHOLDS) for x in (f"it{i} AS (SELECT * FROM many WHERE threshold = '{t}')", profile_sql(f"it{i}", name=f"q{i}_"))], last=" UNION ALL ".join(f"SELECT '{t}' AS threshold, round({spearman_sql(f'q{i}_dist', f'q{_base}_dist')}, 6) AS spearman" for i, t in enumerate(sensitivity.THRESHOLDS)))

_LOST = {"artificial_only": f"SELECT grp FROM items WHERE itemset & {data.STRIP.other} = 0", "no_road": f"SELECT grp FROM items WHERE itemset & {1 << data.ROAD_BIT} = 0", "15%": "SELECT grp FROM low WHERE sup * 100 >= n * 15"}
add("degenerate_groups", *STRIP_ITEMS, itemsets_sql(5, 100, "low"), last=" UNION ALL ".join(f"SELECT '{v}' AS variant, grp, grp NOT IN ({q}) AS degenerate FROM items_n" for v, q in _LOST.items()))

# ---- representation variants


def variant_sql(name: str, profile: str, extra: tuple[str, ...] = (), average: bool = False) -> None:
    pairs = f"SELECT '{name}' AS variant, x.cluster AS u, y.cluster AS v FROM z_lab x JOIN lab y ON x.grp = y.grp AND x.k = {K} AND y.k = {K}"
    ORACLES[f"variant_{name}"] = chain(*TREE, *extra, profile, tree_sql("z_", average), agreement_sql(pairs, "variant")[0], last=f"SELECT variant, (SELECT count(DISTINCT feature) FROM z_v) AS features, round(ari, 6) AS ari, round(nmi, 6) AS nmi, round({spearman_sql('z_dist', 'dist')}, 6) AS spearman FROM ar JOIN nm USING (variant)")


variant_sql("rounded", profile_sql(value="((200 * sup + n) // (2 * n))::double", name="z_"))
variant_sql("binary", profile_sql(value="1.0::double", name="z_"))
variant_sql("absolute", profile_sql(value="sup::double", name="z_"))
variant_sql("unnormalised", profile_sql(name="z_", unit=False))
variant_sql("cosine_average", profile_sql(name="z_", unit=False, cosine=True), average=True)
variant_sql("no_road", profile_sql(where=f"itemset & {1 << data.ROAD_BIT} = 0", name="z_"))
variant_sql("artificial_only", profile_sql(where=f"itemset & {data.STRIP.other} = 0", name="z_"))
variant_sql("unique_pattern", profile_sql("uitems", name="z_"), extra=(UNIQUE, itemsets_sql(name="uitems", pat="one")))
_CORE = [s.replace("u AS (", "cu0 AS (").replace("w0", "cw0").replace("w1", "cw1").replace("w2", "cw2") for s in (words_sql(core=True),)]
_CORE_TX = strip_tx_sql().replace("tx AS", "ctx AS").replace("FROM u a", "FROM cu0 a").replace(", u b", ", cu0 b")
_EXT_PAIRS = f"SELECT 1 AS one, x.cluster AS u, y.cluster AS v FROM z_lab x JOIN lab y ON x.grp = y.grp AND x.k = {K} AND y.k = {K}"
add("extent_sensitivity", *TREE, *_CORE, _CORE_TX, "cpat AS (SELECT grp, mask, count(*) AS weight FROM ctx GROUP BY 1, 2)", itemsets_sql(name="citems", pat="cpat"), profile_sql("citems", name="z_"), tree_sql("z_"), agreement_sql(_EXT_PAIRS, "one")[0], last=f"SELECT (SELECT count(DISTINCT feature) FROM z_v) AS features, round(ari, 6) AS ari, round(nmi, 6) AS nmi, round({spearman_sql('z_dist', 'dist')}, 6) AS spearman FROM ar JOIN nm USING (one)")

# ---- a layout that SQL can make

PLANE = """
pl AS (SELECT grp, coalesce(max(value) FILTER (feature = 2), 0) AS x, coalesce(max(value) FILTER (feature = 1048576), 0) AS y FROM prof GROUP BY 1),
lo AS (SELECT p.grp AS a, q.grp AS b, sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y)) AS d FROM pl p JOIN pl q ON p.grp <> q.grp),
lr AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY round(d, 10), b) AS rank FROM lo),
hr AS (SELECT a, b, row_number() OVER (PARTITION BY a ORDER BY round(d, 10), b) AS rank FROM dd)"""
add("trustworthiness_plane", *PROFILE, BOTH, PLANE, "gn AS (SELECT count(*) AS n FROM sq)", last="SELECT round(1 - 2 * (SELECT sum(greatest(0, hr.rank - 10)) FROM lr JOIN hr ON lr.a = hr.a AND lr.b = hr.b WHERE lr.rank <= 10) / (n * 10 * (2 * n - 31)), 6) AS trustworthiness FROM gn")
add("neighbour_overlap_plane", *PROFILE, BOTH, PLANE, last="SELECT round((SELECT count(*) FROM lr JOIN hr ON lr.a = hr.a AND lr.b = hr.b WHERE lr.rank <= 10 AND hr.rank <= 10) / ((SELECT count(*) FROM sq) * 10.0::double), 6) AS overlap")

PLANE_ITEMS = """
pit AS (SELECT grp, 1::bigint AS itemset, x AS rel FROM pl UNION ALL SELECT grp, 2::bigint, y FROM pl)"""
_PLANE_PAIRS = f"SELECT 1 AS one, x.cluster AS u, y.cluster AS v FROM p_lab x JOIN lab y ON x.grp = y.grp AND x.k = {K} AND y.k = {K}"
add("layout_metrics_plane", *TREE, BOTH, PLANE, PLANE_ITEMS, profile_sql("pit", name="p_", unit=False), tree_sql("p_"), agreement_sql(_PLANE_PAIRS, "one")[0], "gn AS (SELECT count(*) AS n FROM sq)", last=f"""
SELECT round(1 - 2 * (SELECT sum(greatest(0, hr.rank - 10)) FROM lr JOIN hr ON lr.a = hr.a AND lr.b = hr.b WHERE lr.rank <= 10) / (n * 10 * (2 * n - 31)), 6) AS trustworthiness,
       round((SELECT count(*) FROM lr JOIN hr ON lr.a = hr.a AND lr.b = hr.b WHERE lr.rank <= 10 AND hr.rank <= 10) / (n * 10.0::double), 6) AS overlap,
       round({spearman_sql("p_dist", "dist")}, 6) AS spearman, round(ari, 6) AS ari, round(nmi, 6) AS nmi FROM gn, ar JOIN nm USING (one)""")

# ---- non-artificial content and tests

VALUES = """
va AS (SELECT measure, grp, value, cluster FROM (UNPIVOT co ON mean_other, share_any, share_only INTO NAME measure VALUE value) JOIN l7 USING (grp))"""
add("nonartificial_measures", *STRIP, CONTENT, last="SELECT grp, round(mean_other, 6) AS mean_other, round(share_any, 6) AS share_any, round(share_only, 6) AS share_only FROM co")
add("nonartificial_median_by_cluster", *TREE, SEVEN, CONTENT, last="SELECT cluster, round(quantile_cont(share_any, 0.5), 6) AS median FROM co JOIN l7 USING (grp) GROUP BY 1")
KRUSKAL = """
kr AS (SELECT *, rank() OVER (PARTITION BY measure ORDER BY round(value, 10)) + (count(*) OVER (PARTITION BY measure, round(value, 10)) - 1) / 2.0 AS r FROM va),
kn AS (SELECT measure, count(*)::double AS n, count(DISTINCT cluster) - 1 AS df FROM kr GROUP BY 1),
kq AS (SELECT measure, sum(s * s / m) AS q FROM (SELECT measure, cluster, sum(r)::double AS s, count(*) AS m FROM kr GROUP BY 1, 2) GROUP BY 1),
kt AS (SELECT measure, sum(t * t * t - t) AS ties FROM (SELECT measure, round(value, 10) AS v, count(*)::double AS t FROM kr GROUP BY 1, 2) GROUP BY 1),
kw AS (SELECT measure, (12 / (n * (n + 1)) * q - 3 * (n + 1)) / (1 - ties / (n * n * n - n)) AS h, df FROM kn JOIN kq USING (measure) JOIN kt USING (measure))"""
add("kruskal_h", *TREE, SEVEN, CONTENT, VALUES, KRUSKAL, last="SELECT measure, round(h, 6) AS h, df FROM kw")
HOLM = """
pv AS (SELECT *, exp(-h / 2) * (1 + h / 2 + h * h / 8) AS p FROM kw WHERE df = 6 OR error('the tail is written for 6 degrees of freedom')),
hs AS (SELECT *, row_number() OVER (ORDER BY p, measure) AS i, least(1, (count(*) OVER () - row_number() OVER (ORDER BY p, measure) + 1) * p) AS s FROM pv)"""
add("holm_adjusted", *TREE, SEVEN, CONTENT, VALUES, KRUSKAL, HOLM, last="SELECT measure, round(h, 6) AS h, df, round(p, 9) AS p, round(max(s) OVER (ORDER BY i), 9) AS adjusted, true AS exploratory FROM hs")
add("eta_squared", *TREE, SEVEN, CONTENT, VALUES, last="SELECT measure, round(sum((c - m) * (c - m)) / sum((value - m) * (value - m)), 6) AS eta2 FROM (SELECT *, avg(value) OVER (PARTITION BY measure) AS m, avg(value) OVER (PARTITION BY measure, cluster) AS c FROM va) GROUP BY 1")


def cramers_sql(pairs: str, by: str) -> str:
    return f"""
xc AS (SELECT {by}, u, v, count(*)::double AS c FROM {pairs} GROUP BY 1, 2, 3),
xv AS (SELECT {by}, sqrt(greatest(0, sum(c * c / (r * q)) - 1) / (least(any_value(nu), any_value(nv)) - 1)) AS v FROM (SELECT *, sum(c) OVER (PARTITION BY {by}, u) AS r, sum(c) OVER (PARTITION BY {by}, v) AS q FROM xc)
  JOIN (SELECT {by}, count(DISTINCT u) AS nu, count(DISTINCT v) AS nv FROM xc GROUP BY 1) USING ({by}) GROUP BY 1)"""


_CV = "cp AS (SELECT -1 AS rep, grp, block AS u, cluster AS v FROM l7 JOIN blk USING (grp))"
add("cramers_v", *TREE, SEVEN, BLOCKS, _CV, cramers_sql("cp", "rep"), last="SELECT round(v, 6) AS v FROM xv")
_ORDER_TREE = (ORDERS, PATTERNS, itemsets_sql(), profile_sql(), tree_sql(), SEVEN)
_ORDER_CV = "cp AS (SELECT -1 AS rep, grp, n_regionkey::varchar AS u, cluster AS v FROM l7 JOIN nation ON n_nationkey::varchar = grp)"
for _name, _reps, _steps in (("cramers_v_permutation", 200, (*TREE, SEVEN, BLOCKS, _CV)), ("cramers_v_permutation_5000", 5000, (*TREE, SEVEN, BLOCKS, _CV)), ("cramers_v_orders_null", 5000, (*_ORDER_TREE, _ORDER_CV))):
    add(_name, *_steps, f"""
pi AS (SELECT *, row_number() OVER (ORDER BY grp) AS i FROM cp),
pm AS (SELECT t.rep, i, u, v, row_number() OVER (PARTITION BY t.rep ORDER BY md5('0|' || t.rep || '|' || grp), grp) AS j FROM pi, range({_reps}) t(rep)),
pn AS (SELECT a.rep, a.u, b.v FROM pm a JOIN pm b ON a.rep = b.rep AND a.i = b.j UNION ALL SELECT rep, u, v FROM cp)""", cramers_sql("pn", "rep"), last=f"SELECT round(s.v, 6) AS v, round((1 + (SELECT count(*) FROM xv WHERE rep >= 0 AND round(v, 10) >= round(s.v, 10))) / {_reps + 1}.0::double, 6) AS p FROM xv s WHERE rep = -1")

# ---- the aggregate baseline

COMPOSITION = """
cprof AS (SELECT grp, bit::bigint AS itemset, count(*)::double / sum(count(*)) OVER (PARTITION BY grp) AS rel FROM u GROUP BY grp, bit)"""
add("composition_profile", words_sql(), COMPOSITION, last="SELECT grp, itemset AS feature, round(rel, 6) AS value FROM cprof")
add("mix_entropy", words_sql(), COMPOSITION, last="SELECT grp, round(CASE WHEN count(*) > 1 THEN sum(-rel * ln(rel)) / ln(count(*)) ELSE 0 END, 6) AS mix FROM cprof GROUP BY 1")
add("composition_vs_itemset_agreement", *TREE, COMPOSITION, profile_sql("cprof", name="z_"), tree_sql("z_"), agreement_sql(_EXT_PAIRS, "one")[0], last=f"SELECT (SELECT count(DISTINCT feature) FROM z_v) AS features, round(ari, 6) AS ari, round(nmi, 6) AS nmi, round({spearman_sql('z_dist', 'dist')}, 6) AS spearman FROM ar JOIN nm USING (one)")

# ---- operators around the methods

_STRIP_CODES = "[" + ", ".join(map(str, data.STRIP.codes)) + "]"
_THEMED = f"cd AS (SELECT grp, ({_STRIP_CODES})[bit + 1] AS code FROM u)"
add("code_rollup", words_sql(), _THEMED, last="SELECT theme, code, count(*) AS n FROM (SELECT (code // 10000 * 10000)::bigint AS theme, (code // 100 * 100)::bigint AS code FROM cd) GROUP BY ROLLUP (theme, code)")
add("group_cube", words_sql(), _THEMED, BLOCKS, last="SELECT block, theme, count(*) AS n FROM (SELECT block, (code // 10000 * 10000)::bigint AS theme FROM cd JOIN blk USING (grp)) GROUP BY CUBE (block, theme)")
_THEMES = "[" + ", ".join(str(sorted(set(data.STRIP.themes)).index(t)) for t in data.STRIP.themes) + "]"
add("coarse_itemsets_strip", words_sql().replace("u AS (SELECT", "fine AS (SELECT"), f"u AS (SELECT * REPLACE (({_THEMES})[bit + 1] AS bit) FROM fine)", strip_tx_sql(), PATTERNS, itemsets_sql(), last=ITEM_ROWS)
add("approximate_patterns", *STRIP, last="SELECT DISTINCT grp, true AS near FROM pat")
add("support_quartiles", *STRIP_ITEMS, last="SELECT grp, itemset, ntile(4) OVER (PARTITION BY grp ORDER BY sup, itemset) AS quartile, round(percent_rank() OVER (PARTITION BY grp ORDER BY sup), 6) AS percent_rank FROM items")
add("nearest_words_tx", words_sql(), "tx AS (SELECT grp, bit_or(1::bigint << bit) OVER (PARTITION BY part ORDER BY lo ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS mask FROM u)", PATTERNS, last="SELECT * FROM pat")
add("map_dot_products", *PROFILE, last="SELECT p.grp, round(sum(p.value * coalesce(q.value, 0)), 6) AS dot FROM prof p LEFT JOIN (SELECT feature, value FROM prof WHERE grp = (SELECT min(grp) FROM prof)) q USING (feature) GROUP BY p.grp")
add("sample_by_language", words_sql(), BLOCKS, last="SELECT grp, count(*) AS n FROM u JOIN blk USING (grp) WHERE block = 'en' GROUP BY 1")
add("union_features", *STRIP_ITEMS, last="SELECT DISTINCT itemset FROM items")
add("common_itemsets", *STRIP_ITEMS, last="SELECT itemset FROM items GROUP BY 1 HAVING count(*) = (SELECT count(DISTINCT grp) FROM items)")
add("lost_between_thresholds", *STRIP_MANY, last="SELECT DISTINCT itemset FROM many WHERE threshold = '5%' AND itemset NOT IN (SELECT itemset FROM many WHERE threshold = '15%')")
add("union_drop_between_thresholds", *STRIP_MANY, last="SELECT share, features, lag(features) OVER (ORDER BY share) - features AS fewer FROM (SELECT replace(threshold, '%', '')::double AS share, count(DISTINCT itemset) AS features FROM many GROUP BY 1)")
ORACLES["asof_previous_event"] = "SELECT event_id, user_id, previous FROM (SELECT *, lag(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS previous FROM events) WHERE event_type = 'purchase'"
add("semi_groups_with_set", *STRIP_ITEMS, last=f"SELECT grp, n FROM items_n WHERE grp IN (SELECT grp FROM items WHERE itemset = {1 << 1 | 1 << 20})")
add("anti_missing_features", *STRIP_ITEMS, last="SELECT g.grp, f.itemset FROM (SELECT DISTINCT grp FROM items) g, (SELECT DISTINCT itemset FROM items WHERE k = 1) f WHERE NOT EXISTS (SELECT 1 FROM items i WHERE i.grp = g.grp AND i.itemset = f.itemset)")
add("json_code_source", EVENT_UNITS.replace("AS bit, props", "AS bit0, (props::json->>'$.k')::integer // 5 AS bit, props"), EVENT_TX, PATTERNS, last="SELECT * FROM pat")
PAGES = """
pg AS (SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS grp, page_id, list_distinct(list_transform(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1), lambda t: lower(t))) AS tags FROM pages),
pn AS (SELECT grp, count(*) AS n FROM pg GROUP BY 1), pe AS (SELECT grp, page_id, unnest(tags) AS item FROM pg),
p1 AS (SELECT grp, item FROM (SELECT grp, item, count(*) AS s FROM pe GROUP BY 1, 2) JOIN pn USING (grp) WHERE s * 10 >= n),
h1 AS (SELECT grp, page_id, item AS tags, item AS last FROM pe JOIN p1 USING (grp, item))"""
_LONGER = [f"h{k} AS (SELECT x.grp, x.page_id, x.tags || ' ' || y.item AS tags, y.item AS last FROM h{k - 1} x JOIN pe y ON x.grp = y.grp AND x.page_id = y.page_id AND y.item > x.last JOIN p1 ON p1.grp = y.grp AND p1.item = y.item)" for k in range(2, PAGE_ITEMS + 1)]
add("page_tag_itemsets", PAGES, *_LONGER, last="SELECT grp, tags, sup, n FROM (" + " UNION ALL ".join(f"SELECT grp, tags, count(*) AS sup FROM h{k} GROUP BY 1, 2" for k in range(1, PAGE_ITEMS + 1)) + ") JOIN pn USING (grp) WHERE sup * 10 >= n")
add("page_tag_masks", PAGES, last="SELECT grp, item AS tag, count(*) AS sup, any_value(n) AS n FROM pe JOIN pn USING (grp) GROUP BY 1, 2 HAVING count(*) * 10 >= any_value(n) * 9")
add("conversation_itemsets", "tx AS (SELECT 'all' AS grp, conv_id AS unit_id, bit_or(1::bigint << (CASE role WHEN 'user' THEN 0 WHEN 'assistant' THEN 4 ELSE 8 END + least(3, length(text) // 200))::integer) AS mask FROM conversations GROUP BY conv_id)", PATTERNS, itemsets_sql(), last=ITEM_ROWS)
add("benchmark_strip", words_sql("benchmark", "'benchmark|all'", "item_id"), strip_tx_sql(), PATTERNS, last="SELECT * FROM pat")
add("label_block_join", words_sql(), strip_tx_sql(), last="SELECT quality, count(*) AS n, sum(bit_count(mask))::bigint AS items FROM tx LEFT JOIN labels ON labels.doc_id = tx.unit_id // 1000000 GROUP BY 1")

# ---- streams: the batch result


def _window_tx(width_h: int, slide_h: int) -> str:
    w, s = width_h * 3_600_000_000, slide_h * 3_600_000_000
    return f"tx AS (SELECT grp, part, t // {s} * {s} - o * {s} AS start, bit_or(1::bigint << bit) AS mask FROM ev, range({width_h // slide_h}) r(o) WHERE t < t // {s} * {s} - o * {s} + {w} GROUP BY 1, 2, 3)"


add("stream_tumbling_sets", EVENT_UNITS, _window_tx(24, 24), PATTERNS, last="SELECT * FROM pat")
add("stream_sliding_sets", EVENT_UNITS, _window_tx(24, 12), PATTERNS, last="SELECT * FROM pat")
add("stream_patterns", EVENT_UNITS, _window_tx(6, 6), PATTERNS, last="SELECT * FROM pat")
add("stream_session_sets", EVENT_UNITS, "se AS (SELECT *, sum(fresh) OVER (PARTITION BY part ORDER BY t ROWS UNBOUNDED PRECEDING) AS sid FROM (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY part ORDER BY t) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM ev)), sn AS (SELECT grp, part, sid, count(*) AS n, bit_or(1::bigint << bit) AS mask FROM se GROUP BY 1, 2, 3)", last="SELECT grp, count(*) AS sessions, sum(n)::bigint AS events, sum(bit_count(mask))::bigint AS items FROM sn GROUP BY 1")
add("stream_interval_join", EVENT_UNITS, EVENT_TX, last="SELECT * FROM tx")

add("stream_closed_transactions", EVENT_UNITS, EVENT_TX, f"""
wm AS (SELECT (max(t) // 1000 - 3600000) AS ms FROM ev)""", last=f"SELECT part, unit_id, mask FROM tx JOIN (SELECT unit_id, part, t FROM ev) USING (unit_id), wm WHERE (t + {data.HOURS * HOUR}) // 1000 + 1 <= ms")

# a row of an arrival is late by the watermark that held before the arrival before it
add("stream_late_counts", EVENT_UNITS, "ar AS (SELECT unit_id % 4 AS batch, t FROM ev), wa AS (SELECT batch, max(max(t)) OVER (ORDER BY batch ROWS BETWEEN UNBOUNDED PRECEDING AND 2 PRECEDING) // 1000 * 1000 - 864000000000 AS wm FROM ar GROUP BY batch)", last="SELECT batch::bigint AS batch, count(*) AS rows, count(*) FILTER (t <= wm) AS late FROM ar JOIN wa USING (batch) GROUP BY batch")

# ---- SQL surface

add("sql_mine_udtf", EVENT_UNITS, EVENT_TX, PATTERNS, itemsets_sql(), last="SELECT grp, itemset, sup, n FROM items")
add("sql_contains_items", *STRIP, last=f"SELECT grp, sum(weight)::bigint AS sup FROM pat WHERE mask & {1 << 1 | 1 << 20} = {1 << 1 | 1 << 20} GROUP BY 1")
add("sql_union_of_sets", EVENT_UNITS, EVENT_TX, PATTERNS, last="SELECT grp, bit_or(mask) AS seen FROM pat GROUP BY 1")
add("sql_submasks", EVENT_UNITS, EVENT_TX, PATTERNS, "sb AS (SELECT grp, weight, (1::bigint << a) | (1::bigint << b) AS submask FROM pat, range(25) x(a), range(25) y(b) WHERE a <= b AND (mask >> a) & 1 = 1 AND (mask >> b) & 1 = 1)", last="SELECT grp, submask, sum(weight)::bigint AS sup FROM sb GROUP BY 1, 2")
