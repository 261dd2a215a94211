"""SQL of the workloads for DuckDB, by other means than the engine's: self joins, recursion, plain windows."""

from __future__ import annotations

from ..sources import DOCUMENT_CATEGORICAL, DOCUMENT_NUMERIC, LICENCES, PART_CATEGORICAL, PART_NUMERIC

WS, NOT_LETTER = r"[ \t\n\r\f]+", r"[^\p{L}]+"


def norm(value: str) -> str:
    return rf"trim(regexp_replace(lower({value}), '[^\p{{L}}\p{{N}}]+', ' ', 'g'))"


ITEMS = """
items AS (SELECT doc_id AS item_id, CAST(DATE '1990-01-01' + CAST(doc_id * 12775 // (SELECT count(*) FROM documents) AS INTEGER) AS DATE) AS pub_date, lang, source FROM documents)"""

LINKS = """
lines AS (SELECT DISTINCT doc_id, trim(x) AS line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x)) >= 40),
held AS (SELECT doc_id, line, lag(doc_id) OVER w AS prev, first_value(doc_id) OVER w AS head FROM lines WINDOW w AS (PARTITION BY line ORDER BY doc_id)),
links AS (SELECT doc_id AS src, dst, CAST(count(*) AS DOUBLE) AS relevance FROM (SELECT line, doc_id, prev AS dst FROM held WHERE prev IS NOT NULL UNION SELECT line, doc_id, head FROM held WHERE head < doc_id) GROUP BY 1, 2)"""

FEATURES_WIDE = rf"""
raw AS (
  SELECT doc_id AS item_id, lang, source, length(text) AS n_chars, len(list_filter(regexp_split_to_array(text, '{WS}'), lambda x: x <> '')) AS n_words,
    len(list_distinct(list_filter(regexp_split_to_array(lower(text), '{WS}'), lambda x: x <> ''))) AS n_distinct, length(regexp_replace(text, '{WS}', '', 'g')) AS n_solid,
    len(string_split(text, chr(10))) AS n_lines, length(text) - length(regexp_replace(text, '[!-/:-@\[-`{{-~]', '', 'g')) AS n_punct,
    nullif(regexp_extract(text, '{LICENCES}', 1), '') AS licence,
    list_sort(list_transform(regexp_split_to_array(lower(text), '{NOT_LETTER}'), lambda w: {{'n': -length(w), 'w': w}}))[1].w AS lead_term,
    substring(string_split(text, chr(10))[1], 1, 40) AS opening FROM documents),
wide AS (SELECT *, round(n_distinct / nullif(n_words, 0), 6) AS diversity, round(n_solid / nullif(n_words, 0), 6) AS word_length, round(n_punct / nullif(n_chars, 0), 6) AS punct_share FROM raw)"""


def long(numeric: dict[str, int], categorical: list[str], table: str = "wide") -> str:
    rows = [f"SELECT item_id, '{c}' AS axis, 'numeric' AS kind, {d} AS direction, CAST({c} AS DOUBLE) AS v_num, CAST(NULL AS VARCHAR) AS v_txt FROM {table}" for c, d in numeric.items()]
    rows += [f"SELECT item_id, '{c}' AS axis, 'categorical' AS kind, 1 AS direction, CAST(NULL AS DOUBLE) AS v_num, nullif({norm(c)}, '') AS v_txt FROM {table}" for c in categorical]
    return "\nfeatures AS (SELECT * FROM (" + " UNION ALL ".join(rows) + ") WHERE v_num IS NOT NULL OR v_txt IS NOT NULL)"


FEATURES = FEATURES_WIDE + "," + long(DOCUMENT_NUMERIC, DOCUMENT_CATEGORICAL)


def targets(n: int = 20) -> str:
    return f"\ntargets AS (SELECT t AS target_id FROM (SELECT src AS t FROM links UNION ALL SELECT dst FROM links) GROUP BY t ORDER BY count(*) DESC, t LIMIT {n})"


def net(depth: int = 2) -> str:
    two = depth > 1
    return f"""
r1 AS (SELECT target_id, dst AS item_id, max(relevance) AS relevance FROM targets JOIN links ON src = target_id WHERE dst <> target_id GROUP BY 1, 2),
c1 AS (SELECT target_id, item_id, relevance FROM (SELECT target_id, src AS item_id, relevance, row_number() OVER (PARTITION BY target_id ORDER BY relevance DESC, src) AS k FROM targets JOIN links ON dst = target_id) WHERE k <= 50),
r2 AS (SELECT target_id, dst AS item_id, max(links.relevance) AS relevance FROM r1 JOIN links ON src = item_id WHERE dst <> target_id AND {two} GROUP BY 1, 2),
c2 AS (SELECT target_id, item_id, max(relevance) AS relevance FROM (
  SELECT target_id, src AS item_id, links.relevance, row_number() OVER (PARTITION BY target_id, c1.item_id ORDER BY links.relevance DESC, src) AS k FROM c1 JOIN links ON dst = c1.item_id) WHERE k <= 50 AND item_id <> target_id AND {two} GROUP BY 1, 2),
layers AS (SELECT *, 'reference' AS relation, 1 AS layer FROM r1 UNION ALL SELECT *, 'citation', 1 FROM c1 UNION ALL SELECT *, 'reference', 2 FROM r2 UNION ALL SELECT *, 'citation', 2 FROM c2),
net AS (SELECT target_id, item_id, relation, layer, relevance FROM (SELECT *, row_number() OVER (PARTITION BY target_id, item_id ORDER BY layer, relation = 'citation', relevance DESC) AS k FROM layers) WHERE k = 1)"""


AXES = """
axes AS (SELECT target_id, axis, kind, direction, v_num AS t_num, v_txt AS t_txt FROM targets JOIN features ON item_id = target_id)"""

CLAIMS = """
claims AS (SELECT n.target_id, n.item_id, n.relation, n.layer, a.axis, a.kind, a.direction, a.t_num, a.t_txt, f.v_num, f.v_txt
  FROM net n JOIN axes a USING (target_id) LEFT JOIN features f ON f.item_id = n.item_id AND f.axis = a.axis)"""

VERDICT = """CASE WHEN kind = 'numeric' THEN CASE WHEN t_num IS NULL OR v_num IS NULL THEN NULL WHEN t_num = v_num THEN 0 WHEN (t_num - v_num) * direction > 0 THEN 1 ELSE -1 END
  ELSE CASE WHEN t_txt IS NULL OR v_txt IS NULL THEN NULL WHEN t_txt = v_txt THEN 0 ELSE 1 END END"""

DUELS = f"\nduels AS (SELECT *, CAST({VERDICT} AS INTEGER) AS s FROM claims)"


def omega(source: str, by: str = "target_id", alpha: str = "0.5", name: str = "scores") -> str:
    """Scores from a relation of verdict counts (by, axis, n1, n0, nm)."""
    return f"""
{name}_p AS (SELECT *, coalesce(n1 / nullif(n1 + n0 + nm, 0), 0) AS p1, coalesce((n1 + {alpha} * n0 - nm) / nullif(n1 + n0 + nm, 0), 0) AS sc FROM {source}),
{name}_w AS (SELECT *, CASE WHEN sum(p1) OVER (PARTITION BY {by}) > 0 THEN p1 / sum(p1) OVER (PARTITION BY {by}) ELSE 1.0 / count(*) OVER (PARTITION BY {by}) END AS w FROM {name}_p),
{name} AS (SELECT {by}, round(CASE WHEN sum(p1) > 0 THEN sum(p1 * sc) / sum(p1) ELSE sum(sc) / count(*) END, 6) AS omega, count(*) AS n_axes FROM {name}_w GROUP BY {by})"""


def counts(where: str = "true", name: str = "counts", source: str = "duels") -> str:
    return f"\n{name} AS (SELECT target_id, axis, count(*) FILTER (s = 1 AND {where}) AS n1, count(*) FILTER (s = 0 AND {where}) AS n0, count(*) FILTER (s = -1 AND {where}) AS nm FROM {source} GROUP BY 1, 2)"


def study(n: int = 20, depth: int = 2) -> str:
    return "WITH " + ",".join([ITEMS, LINKS, FEATURES, targets(n), net(depth), AXES, CLAIMS, DUELS])


PARTS_WIDE = """
per AS (SELECT l_partkey, CAST(min(l_shipdate) AS DATE) AS pub_date, count(*) AS n_lines, sum(CAST(round(l_discount * 100) AS BIGINT)) AS discount_sum, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity,
  count(DISTINCT l_suppkey) AS suppliers, count(*) FILTER (l_returnflag = 'R') AS returned FROM lineitem GROUP BY 1),
nat AS (SELECT l_partkey, n_name AS nation FROM (SELECT l_partkey, n_name, row_number() OVER (PARTITION BY l_partkey ORDER BY count(*) DESC, n_name) AS k FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY 1, 2) WHERE k = 1),
items AS (SELECT p_partkey AS item_id, pub_date, p_retailprice AS price, p_size AS size, round(discount_sum / n_lines, 6) AS discount, quantity, suppliers, round(returned / n_lines, 6) AS return_share,
  p_brand AS brand, p_type AS type, string_split(p_name, ' ')[1] AS adjective, string_split(p_name, ' ')[-1] AS noun, nation FROM part JOIN per ON p_partkey = per.l_partkey JOIN nat ON nat.l_partkey = p_partkey)"""

PART_LINKS = """
op AS (SELECT DISTINCT l_orderkey, l_partkey, pub_date FROM lineitem JOIN items ON item_id = l_partkey),
oph AS (SELECT l_orderkey, l_partkey, lag(l_partkey) OVER w AS prev, first_value(l_partkey) OVER w AS head FROM op WINDOW w AS (PARTITION BY l_orderkey ORDER BY pub_date, l_partkey)),
links AS (SELECT l_partkey AS src, dst, CAST(count(*) AS DOUBLE) AS relevance FROM (SELECT l_orderkey, l_partkey, prev AS dst FROM oph WHERE prev IS NOT NULL UNION SELECT l_orderkey, l_partkey, head FROM oph WHERE prev IS NOT NULL) GROUP BY 1, 2)"""

PARTS = "WITH " + ",".join([PARTS_WIDE, PART_LINKS, long(PART_NUMERIC, PART_CATEGORICAL, "items"), targets(), net(1), AXES, CLAIMS, DUELS])


def report(field: str) -> str:
    return f""",{counts()},{counts("relation = 'reference'", "ref_counts")},{omega("counts")},{omega("ref_counts", name="ref_scores")}
SELECT t.target_id, i.{field} AS field, (SELECT count(*) FROM links WHERE dst = t.target_id) AS cites, (SELECT count(*) FROM net n WHERE n.target_id = t.target_id) AS network_size,
  (SELECT count(*) FROM axes a WHERE a.target_id = t.target_id) AS n_axes, s.omega, CASE WHEN EXISTS (SELECT 1 FROM net n WHERE n.target_id = t.target_id AND relation = 'reference') THEN r.omega END AS omega_refs
FROM targets t JOIN items i ON i.item_id = t.target_id LEFT JOIN scores s ON s.target_id = t.target_id LEFT JOIN ref_scores r ON r.target_id = t.target_id"""


TIMELINE = """
tl AS (SELECT target_id, item_id, relation, is_target, pub_date, row_number() OVER (PARTITION BY target_id ORDER BY pub_date, item_id) AS pos FROM (
  SELECT target_id, item_id, relation, false AS is_target FROM net UNION ALL SELECT target_id, target_id, 'target', true FROM targets) JOIN items USING (item_id)),
vals AS (SELECT target_id, item_id, axis, kind, direction, v_num, v_txt FROM claims UNION ALL SELECT target_id, target_id, axis, kind, direction, t_num, t_txt FROM axes),
placed AS (SELECT v.*, tl.pos FROM vals v JOIN tl ON v.target_id = tl.target_id AND v.item_id = tl.item_id WHERE v_num IS NOT NULL OR v_txt IS NOT NULL),
adv0 AS (SELECT target_id, axis, pos, item_id, kind, CAST(CASE WHEN kind = 'numeric' THEN
    CASE WHEN b IS NULL OR v_num * direction > b THEN 1 WHEN v_num * direction = b THEN 0 ELSE -1 END ELSE CASE WHEN k = 1 THEN 1 ELSE 0 END END AS INTEGER) AS s
  FROM (SELECT *, max(v_num * direction) OVER (PARTITION BY target_id, axis ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b, row_number() OVER (PARTITION BY target_id, axis, v_txt ORDER BY pos) AS k FROM placed)),
adv AS (SELECT *, count(*) FILTER (s = 1) OVER (PARTITION BY target_id, axis ORDER BY pos) AS nu FROM adv0)"""

PACE = """
m AS (SELECT target_id, count(*) AS m FROM axes GROUP BY 1),
won AS (SELECT tl.target_id, tl.pos, count(adv.s) AS n_won FROM tl LEFT JOIN adv ON adv.target_id = tl.target_id AND adv.pos = tl.pos AND adv.s = 1 GROUP BY 1, 2),
paced AS (SELECT tl.target_id, tl.item_id, tl.relation, tl.is_target, tl.pub_date, tl.pos, n_won, round(sum(n_won) OVER w / m, 6) AS nu_bar, round(n_won / m, 6) AS d_nu_bar, round(ln(1 + sum(n_won) OVER w / m), 6) AS log_nu
  FROM tl JOIN won USING (target_id, pos) JOIN m USING (target_id) WINDOW w AS (PARTITION BY target_id ORDER BY pos))"""


def series(key: str) -> str:
    join = "JOIN part ON l_partkey = p_partkey" if key == "p_brand" else ""
    return f"""WITH ls AS (SELECT CAST({key} AS VARCHAR) AS series, row_number() OVER (PARTITION BY {key} ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS pos,
  l_extendedprice / l_quantity AS unit_price, l_discount, l_suppkey, l_returnflag FROM lineitem {join}),
vals AS (SELECT series, 'unit_price' AS axis, pos, -unit_price AS v FROM ls UNION ALL SELECT series, 'discount', pos, l_discount FROM ls),
st AS (SELECT *, max(v) OVER (PARTITION BY series, axis ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM vals),
vd AS (SELECT series, axis, pos, CAST(CASE WHEN b IS NULL OR v > b THEN 1 WHEN v = b THEN 0 ELSE -1 END AS INTEGER) AS s FROM st),
rec AS (SELECT *, count(*) FILTER (s = 1) OVER (PARTITION BY series, axis ORDER BY pos) AS nu FROM vd)"""


EVENTS = """ev AS (SELECT event_type AS series, event_id, value, row_number() OVER (PARTITION BY event_type ORDER BY ts, event_id) AS pos FROM events)"""
TOLERANT = f"""WITH RECURSIVE {EVENTS},
win AS (SELECT series, pos, value FROM ev WHERE pos = 1
  UNION ALL
  SELECT series, pos, value FROM (SELECT e.series, e.pos, e.value, row_number() OVER (PARTITION BY e.series ORDER BY e.pos) AS k FROM win w JOIN ev e ON e.series = w.series AND e.pos > w.pos AND e.value - w.value > 0.05 * greatest(abs(e.value), abs(w.value))) WHERE k = 1)"""


def axis(extra: str = "") -> str:
    """Nodes, similar pairs, density clusters and confidence edges of the parts value axis."""
    return f"""WITH RECURSIVE
first AS (SELECT l_partkey, CAST(min(l_shipdate) AS DATE) AS pub_date FROM lineitem GROUP BY 1),
pv AS (SELECT p_partkey AS item_id, pub_date, lower(concat_ws(' ', p_type, p_name)) AS value FROM part JOIN first ON p_partkey = l_partkey),
w1 AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY value ORDER BY pub_date, item_id) AS k FROM pv) WHERE k = 1),
nodes AS MATERIALIZED (SELECT row_number() OVER (ORDER BY pub_date, item_id) AS pos, item_id, pub_date, CAST(year(pub_date) AS INTEGER) AS year, CAST(year(pub_date) * 12 + month(pub_date) AS INTEGER) AS period, value, list_distinct(list_filter(regexp_split_to_array(value, '{WS}'), lambda x: x <> '')) AS tokens FROM w1),
rel AS MATERIALIZED (SELECT a, b, sim FROM (SELECT x.pos AS a, y.pos AS b, round(len(list_intersect(x.tokens, y.tokens)) / len(list_distinct(list_concat(x.tokens, y.tokens))), 6) AS sim FROM nodes x JOIN nodes y ON x.pos < y.pos) WHERE sim >= 0.5),
near AS MATERIALIZED (SELECT a, b FROM rel WHERE sim >= 0.6 UNION ALL SELECT b, a FROM rel WHERE sim >= 0.6),
core AS MATERIALIZED (SELECT pos FROM nodes WHERE (SELECT count(*) FROM near WHERE a = pos) + 1 >= 3),
reach(a, b) AS (SELECT pos, pos FROM core UNION SELECT r.a, n.b FROM reach r JOIN near n ON n.a = r.b JOIN core c ON c.pos = n.b),
lab AS MATERIALIZED (SELECT a AS pos, min(b) AS label FROM reach GROUP BY 1),
clus AS MATERIALIZED (SELECT n.pos, l.pos IS NOT NULL AS is_core, coalesce(l.label, (SELECT min(k.label) FROM near JOIN lab k ON k.pos = near.b WHERE near.a = n.pos)) AS cluster FROM nodes n LEFT JOIN lab l USING (pos)),
conf AS MATERIALIZED (SELECT * FROM (SELECT x.pos AS src, y.pos AS dst, CAST(y.period - x.period AS INTEGER) AS gap, CAST(CASE
    WHEN cx.cluster = cy.cluster AND coalesce(rel.sim, 0) >= 0.6 THEN 5 WHEN cx.cluster = cy.cluster THEN 4 WHEN rel.sim IS NULL THEN 0
    WHEN cx.cluster IS NOT NULL AND cy.cluster IS NOT NULL THEN 3 WHEN cx.cluster IS NOT NULL OR cy.cluster IS NOT NULL THEN 2 ELSE 1 END AS INTEGER) AS conf
  FROM nodes x JOIN nodes y ON x.pos < y.pos JOIN clus cx ON cx.pos = x.pos JOIN clus cy ON cy.pos = y.pos LEFT JOIN rel ON rel.a = x.pos AND rel.b = y.pos) WHERE conf > 0){extra}"""


def forest(gamma: float = 1, delta: float = 1) -> str:
    """An edge is kept when its ends are not joined by better edges: the best worst rank of any path equals its own."""
    return f""",
ranked AS MATERIALIZED (SELECT src, dst, conf, gap, sigma, row_number() OVER (ORDER BY sigma DESC, dst - src, src, dst) AS rk FROM (SELECT *, round(pow(conf, {gamma}) / pow(gap + 1, {delta}), 6) AS sigma FROM conf)),
und AS MATERIALIZED (SELECT src AS a, dst AS b, rk FROM ranked UNION ALL SELECT dst, src, rk FROM ranked),
bott(a, b, r) USING KEY (a, b) AS (
  SELECT a, b, rk FROM und
  UNION
  SELECT x.a, e.b, min(greatest(x.r, e.rk)) FROM bott x JOIN und e ON e.a = x.b LEFT JOIN recurring.bott k ON k.a = x.a AND k.b = e.b
  WHERE x.a <> e.b AND (k.r IS NULL OR greatest(x.r, e.rk) < k.r) GROUP BY 1, 2),
forest AS MATERIALIZED (SELECT src, dst, conf, gap, sigma FROM ranked JOIN bott ON bott.a = src AND bott.b = dst AND bott.r = rk)"""


def embedded(value: str) -> str:
    """Vector of hashed character trigrams of a value, as list expressions."""
    text = f"('  ' || {norm(value)} || ' ')"
    hashes = f"list_transform(range(1, length({text}) - 1), lambda i: (unicode(substr({text}, i, 1)) * 7919::BIGINT + unicode(substr({text}, i + 1, 1)) * 104729::BIGINT + unicode(substr({text}, i + 2, 1)) * 1299709::BIGINT) % 1000003)"
    return f"list_transform(range(0, 64), lambda j: coalesce(list_sum(list_transform(list_filter({hashes}, lambda h: h % 64 = j), lambda h: CASE WHEN (h // 64) % 2 = 0 THEN 1.0::DOUBLE ELSE -1.0::DOUBLE END)), 0.0::DOUBLE))"


def ascii_only(value: str) -> str:
    """Letters beyond ASCII as capitals, which normalised values lack: the engine's edit distance counts bytes."""
    return f"translate({value}, 'äöüßéèêëàâçîïôûùñáíóúœæÿ', 'ABCDEFGHIJKLMNOPQRSTUVWX')"


def edit_similarity(a: str, b: str) -> str:
    return f"round(1 - levenshtein({ascii_only(a)}, {ascii_only(b)}) / greatest(length({a}), length({b})), 6)"


def cosine(a: str, b: str) -> str:
    return f"round(list_dot_product({a}, {b}) / nullif(sqrt(list_dot_product({a}, {a}) * list_dot_product({b}, {b})), 0), 6)"


def jaccard(a: str, b: str) -> str:
    return f"round(len(list_intersect({a}, {b})) / len(list_distinct(list_concat({a}, {b}))), 6)"


def token_list(value: str) -> str:
    return f"list_distinct(list_filter(string_split({value}, ' '), lambda x: x <> ''))"


VECTORS = "vec AS MATERIALIZED (SELECT vec_id AS item_id, CAST(embedding AS DOUBLE[]) AS v, label FROM embeddings)"
VECTOR_SIM = "round(list_dot_product(x.v, y.v) / sqrt(list_dot_product(x.v, x.v) * list_dot_product(y.v, y.v)), 6)"
VECTOR_CLUSTERS = f"""WITH RECURSIVE {VECTORS},
rel AS MATERIALIZED (SELECT x.item_id AS a, y.item_id AS b FROM vec x JOIN vec y ON x.item_id < y.item_id WHERE {VECTOR_SIM} >= 0.33),
near AS MATERIALIZED (SELECT a, b FROM rel UNION ALL SELECT b, a FROM rel),
core AS MATERIALIZED (SELECT item_id AS pos FROM vec WHERE (SELECT count(*) FROM near WHERE a = item_id) + 1 >= 4),
reach(a, b) AS (SELECT pos, pos FROM core UNION SELECT r.a, n.b FROM reach r JOIN near n ON n.a = r.b JOIN core c ON c.pos = n.b),
lab AS MATERIALIZED (SELECT a AS pos, min(b) AS label FROM reach GROUP BY 1),
found AS (SELECT item_id AS vec_id, l.pos IS NOT NULL AS is_core, coalesce(l.label, (SELECT min(k.label) FROM near JOIN lab k ON k.pos = near.b WHERE near.a = item_id)) AS cluster FROM vec LEFT JOIN lab l ON l.pos = item_id)"""


CHAIN = study().replace("WITH ", "WITH RECURSIVE ", 1) + f""",{TIMELINE},
win AS MATERIALIZED (SELECT a.target_id, a.axis, a.pos, a.item_id, CAST(year(i.pub_date) AS INTEGER) AS year, coalesce(p.v_txt, CAST(CAST(p.v_num AS DECIMAL(20,6)) AS VARCHAR)) AS value FROM adv a JOIN placed p USING (target_id, axis, pos) JOIN items i ON i.item_id = a.item_id WHERE a.s = 1),
node AS MATERIALIZED (SELECT row_number() OVER (ORDER BY target_id, axis, pos) AS n, *, {norm("value")} AS nv, {embedded("value")} AS v, {token_list(norm("value"))} AS tk FROM win),
near AS MATERIALIZED (SELECT x.n AS a, y.n AS b, {cosine("x.v", "y.v")} AS sim, {jaccard("x.tk", "y.tk")} AS lex, {edit_similarity("x.nv", "y.nv")} AS ed FROM node x JOIN node y ON x.target_id = y.target_id AND x.axis = y.axis AND x.n < y.n),
close AS MATERIALIZED (SELECT a, b FROM near WHERE sim >= 0.5 UNION ALL SELECT b, a FROM near WHERE sim >= 0.5),
reach(a, b) AS (SELECT DISTINCT a, a FROM close UNION SELECT r.a, c.b FROM reach r JOIN close c ON c.a = r.b),
lab AS MATERIALIZED (SELECT a AS n, min(b) AS label FROM reach GROUP BY 1),
cl AS MATERIALIZED (SELECT node.*, label FROM node LEFT JOIN lab USING (n)),
edge AS MATERIALIZED (SELECT * FROM (SELECT near.a AS src, near.b AS dst, y.year - x.year AS gap, CASE WHEN x.label = y.label AND lex >= 0.5 THEN 5 WHEN x.label = y.label THEN 4 WHEN NOT (ed >= 0.5 AND sim >= 0.2) THEN 0
    WHEN x.label IS NOT NULL AND y.label IS NOT NULL THEN 3 WHEN x.label IS NOT NULL OR y.label IS NOT NULL THEN 2 ELSE 1 END AS conf FROM near JOIN cl x ON x.n = near.a JOIN cl y ON y.n = near.b) WHERE conf > 0),
ranked AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY sigma DESC, dst - src, src, dst) AS rk FROM (SELECT *, round(conf / (gap + 1), 6) AS sigma FROM edge)),
und AS MATERIALIZED (SELECT src AS a, dst AS b, rk FROM ranked UNION ALL SELECT dst, src, rk FROM ranked),
bott(a, b, r) USING KEY (a, b) AS (
  SELECT a, b, rk FROM und
  UNION
  SELECT x.a, e.b, min(greatest(x.r, e.rk)) FROM bott x JOIN und e ON e.a = x.b LEFT JOIN recurring.bott k ON k.a = x.a AND k.b = e.b
  WHERE x.a <> e.b AND (k.r IS NULL OR greatest(x.r, e.rk) < k.r) GROUP BY 1, 2),
trees AS MATERIALIZED (SELECT src, dst, conf, gap, sigma FROM ranked JOIN bott ON bott.a = src AND bott.b = dst AND bott.r = rk)"""

def semantic(where: str, k: int) -> str:
    return f"""WITH {VECTORS}, targets AS (SELECT item_id AS target_id FROM vec WHERE {where}),
net AS (SELECT * FROM (SELECT x.item_id AS target_id, y.item_id, 'similar' AS relation, 1 AS layer, round(list_dot_product(x.v, y.v), 6) AS relevance, row_number() OVER (PARTITION BY x.item_id ORDER BY round(list_dot_product(x.v, y.v), 6) DESC, y.item_id) AS k
  FROM targets JOIN vec x ON x.item_id = target_id JOIN vec y ON y.item_id <> x.item_id) WHERE k <= {k})"""


def associated(a: str, b: str, table: str = "graph") -> str:
    return f"""SELECT x.value AS value_a, y.value AS value_b, count(*) AS support, round(count(*) / any_value(na), 6) AS confidence, round(count(*) * any_value(n) / (any_value(na) * any_value(nb)), 6) AS lift
FROM {table} x JOIN {table} y ON x.item_id = y.item_id AND x.axis = '{a}' AND y.axis = '{b}' JOIN (SELECT value, count(*) AS na FROM {table} WHERE axis = '{a}' GROUP BY 1) p ON p.value = x.value
JOIN (SELECT value, count(*) AS nb FROM {table} WHERE axis = '{b}' GROUP BY 1) q ON q.value = y.value CROSS JOIN (SELECT count(DISTINCT item_id) AS n FROM {table}) GROUP BY 1, 2"""


def tournament(items: str, group: str, numeric: dict[str, int], categorical: list[str]) -> str:
    """Counts by comparing every item with all others of its group."""
    rows = []
    for c, d in numeric.items():
        better = f"x.{c} > y.{c}" if d > 0 else f"x.{c} < y.{c}"
        worse = f"x.{c} < y.{c}" if d > 0 else f"x.{c} > y.{c}"
        rows.append(f"SELECT x.{group}, x.item_id, '{c}' AS axis, count(*) FILTER ({better}) AS n_win, count(*) FILTER (x.{c} = y.{c} AND x.item_id <> y.item_id) AS n_draw, count(*) FILTER ({worse}) AS n_loss FROM t x JOIN t y ON x.{group} = y.{group} GROUP BY 1, 2")
    rows += [f"SELECT x.{group}, x.item_id, '{c}', count(*) FILTER (x.{c} <> y.{c}), count(*) FILTER (x.{c} = y.{c} AND x.item_id <> y.item_id), CAST(0 AS BIGINT) FROM t x JOIN t y ON x.{group} = y.{group} GROUP BY 1, 2" for c in categorical]
    return f"WITH t AS ({items}), games AS ({' UNION ALL '.join(rows)})"


PART_GAMES = tournament("SELECT p_partkey AS item_id, p_brand, p_retailprice, p_size, p_type FROM part", "p_brand", {"p_retailprice": -1, "p_size": 1}, ["p_type"])
CUSTOMER_GAMES = tournament("SELECT c_custkey AS item_id, c_nationkey, c_acctbal, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS n_orders, c_mktsegment FROM customer", "c_nationkey", {"c_acctbal": 1, "n_orders": 1}, ["c_mktsegment"])


def games_omega(games: str, group: str) -> str:
    return games + f""", gc AS (SELECT item_id AS target_id, {group}, axis, n_win AS n1, n_draw AS n0, n_loss AS nm FROM games),{omega("gc", f"{group}, target_id")}
SELECT {group}, target_id AS item_id, omega, n_axes FROM scores"""


def ranks(value: str, name: str, table: str) -> str:
    return f"(rank() OVER (ORDER BY {value}) + (count(*) OVER (PARTITION BY {value}) - 1) / 2) AS {name}"


CONVERSATIONS = rf"conv AS (SELECT conv_id, turn, role, length(text) AS n_chars, len(list_distinct(list_filter(regexp_split_to_array(lower(text), '{WS}'), lambda x: x <> ''))) AS n_distinct, lower(list_filter(regexp_split_to_array(text, '{WS}'), lambda x: x <> '')[1]) AS opening FROM conversations)"
PAGES = f"pg AS (SELECT page_id AS item_id, nullif(regexp_extract(url, '^https?://([^/:?#]+)', 1), '') AS host, {norm(chr(110) + 'ullif(regexp_extract(html, ' + chr(39) + '<title>([^<]*)</title>' + chr(39) + ', 1), ' + chr(39) * 2 + ')')} AS title_norm, len(string_split(html, '<a ')) AS link_pieces, length(html) AS n_chars FROM pages)"

WHY = """concat_ws(' ', axis, coalesce(CAST(CAST(t_num AS DECIMAL(20,6)) AS VARCHAR), t_txt, 'none'), CASE WHEN s = 1 THEN 'ahead of' WHEN s = 0 THEN 'level with' WHEN s = -1 THEN 'behind' ELSE 'not comparable with' END, coalesce(CAST(CAST(v_num AS DECIMAL(20,6)) AS VARCHAR), v_txt, 'none'))"""

CORPUS = "WITH " + ",".join([LINKS, FEATURES]) + f""",
played AS (SELECT target_id, axis, CAST({VERDICT} AS INTEGER) AS s FROM (SELECT src AS target_id, m.axis, m.kind, m.direction, m.v_num AS t_num, m.v_txt AS t_txt, o.v_num, o.v_txt FROM links JOIN features m ON m.item_id = src JOIN features o ON o.item_id = dst AND o.axis = m.axis)),{counts(source="played")},{omega("counts")}"""

LIN = """,
lin(root, node, depth) USING KEY (root, node) AS (
  SELECT pos, pos, CAST(0 AS BIGINT) FROM nodes WHERE pos NOT IN (SELECT dst FROM forest)
  UNION
  SELECT l.root, f.dst, min(l.depth + 1) FROM lin l JOIN forest f ON f.src = l.node LEFT JOIN recurring.lin k ON k.root = l.root AND k.node = f.dst WHERE k.depth IS NULL OR l.depth + 1 < k.depth GROUP BY 1, 2)"""
PROFILES = ", pf AS MATERIALIZED (SELECT target_id, item_id, list(axis || '=' || s ORDER BY axis) AS p, list(axis ORDER BY axis) AS ax FROM duels WHERE s IS NOT NULL GROUP BY 1, 2)"
SHARED = """, vs AS MATERIALIZED (SELECT DISTINCT d.doc_id AS item_id, 'passage ' || b.item_id AS value FROM documents d JOIN benchmark b ON contains(d.text, b.text) UNION SELECT item_id, v_txt FROM features WHERE axis = 'licence')"""
SIGNS = "CASE WHEN kind = 'numeric' THEN sign((t_num - v_num) * direction) WHEN t_txt IS NULL OR v_txt IS NULL THEN NULL ELSE abs(sign(CASE WHEN t_txt < v_txt THEN -1 WHEN t_txt > v_txt THEN 1 ELSE 0 END)) END"


def scaled(verdict: str, source: str, name: str) -> str:
    """Score on any scale: won, lost and level parts of each axis, weighted by what is won."""
    return f"""
{name}_a AS (SELECT target_id, sum(greatest(f, 0)) / nullif(count(f), 0) AS w, (sum(greatest(f, 0)) + 0.5 * count(*) FILTER (f = 0) - sum(greatest(-f, 0))) / nullif(count(f), 0) AS sc, count(f) AS n FROM (SELECT target_id, axis, CAST({verdict} AS DOUBLE) AS f FROM {source}) GROUP BY target_id, axis),
{name} AS (SELECT target_id, round(CASE WHEN sum(w) > 0 THEN sum(coalesce(w, 0) * coalesce(sc, 0)) / sum(w) ELSE sum(coalesce(sc, 0)) / count(*) END, 6) AS omega, CAST(sum(n) AS BIGINT) AS n FROM {name}_a GROUP BY 1)"""


NOISY = f""", noisy AS (SELECT * REPLACE (v_num * (1 + 0.05::DOUBLE * (CAST(CAST('0x' || substr(md5(concat_ws('|', target_id, item_id, axis, 3)), 1, 8) AS BIGINT) % 2001 AS DOUBLE) / 1000.0::DOUBLE - 1.0::DOUBLE)) AS v_num) FROM claims),
after AS (SELECT *, CAST({VERDICT} AS INTEGER) AS s FROM noisy)"""


def uncertain(errs: int, votes: int) -> str:
    """Two runs of an extractor that errs, by majority, and the share of equal answers."""
    def run(r: int) -> str:
        calls = " UNION ALL ".join(f"SELECT doc_id, lang, {r * 100 + k} AS call FROM documents" for k in range(votes))
        answer = f"CASE WHEN d % 100 < {errs} THEN 'wrong ' || (d % 7) ELSE lang END"
        return f"(SELECT doc_id, CASE WHEN count(*) = 1 THEN min(v) END AS v FROM (SELECT *, max(n) OVER (PARTITION BY doc_id) AS most FROM (SELECT doc_id, {answer} AS v, count(*) AS n FROM (SELECT doc_id, lang, CAST('0x' || substr(md5(doc_id || '|' || call), 1, 8) AS BIGINT) AS d FROM ({calls})) GROUP BY 1, 2)) WHERE n = most GROUP BY 1)"
    return f"SELECT {errs} AS errs, {votes} AS votes, count(*) AS cells, round(avg(CASE WHEN a.v IS NOT DISTINCT FROM b.v THEN 1.0 ELSE 0.0 END), 6) AS agree_share FROM {run(0)} a JOIN {run(1)} b USING (doc_id)"


SWEEP_ROWS = " UNION ALL ".join(f"SELECT {a} AS alpha" for a in (0.0, 0.25, 0.5, 1.0))
RAW_WEIGHTS = {
    "win_rate": "p1", "uniform": "1.0",
    "entropy": "CASE WHEN p1 > 0 THEN -p1 * ln(p1) ELSE 0 END + CASE WHEN p0 > 0 THEN -p0 * ln(p0) ELSE 0 END + CASE WHEN pm > 0 THEN -pm * ln(pm) ELSE 0 END",
}
FIVE = """CASE WHEN kind = 'numeric' THEN CASE WHEN s = 0 OR abs(t_num - v_num) / greatest(abs(t_num), abs(v_num)) >= 0.25 THEN s ELSE s * 0.5 END ELSE s END"""
SCALES = {"ternary": "CAST(s AS DOUBLE)", "ternary_strict": "CASE WHEN kind = 'categorical' AND s = 1 AND v_txt > t_txt THEN -1.0 ELSE s END", "five": FIVE, "binary": "CASE WHEN s IS NULL THEN NULL WHEN s = 1 THEN 1.0 ELSE 0.0 END"}

QUANTITIES = rf"""WITH qs AS (SELECT doc_id AS item_id, CAST(n_chars AS VARCHAR) || CASE WHEN doc_id % 3 = 0 THEN 'k' WHEN doc_id % 3 = 1 THEN ' chars' ELSE '%' END || ' of ' || coalesce(string_split(text, chr(10))[1], '') AS t FROM documents),
qt AS (SELECT item_id, CAST(regexp_extract(t, '^([0-9]+)', 1) AS DOUBLE) * CASE WHEN item_id % 3 = 0 THEN 1000 ELSE 1 END AS value, CASE WHEN item_id % 3 = 2 THEN '%' WHEN item_id % 3 = 1 THEN 'chars' ELSE 'of' END AS unit FROM qs)"""

SQL: dict[str, str] = {
    "w01_report_documents": study() + report("lang"),
    "w01b_report_parts": PARTS + report("brand"),
    "w02_duel_log": study(1) + f" SELECT target_id, item_id, relation, layer, axis, t_num, t_txt, v_num, v_txt, s, {WHY} AS why FROM duels",
    "w03_axes_documents": study() + " SELECT target_id, axis, kind, direction, t_num, t_txt FROM axes",
    "w03_axes_pages": f"WITH {PAGES} SELECT * FROM pg",
    "w03_axes_conversations": f"WITH {CONVERSATIONS} SELECT * FROM conv",
    "w04_curves_one_layer": study(1, 1) + f",{TIMELINE} SELECT * FROM adv",
    "w05_curves_two_layers": study(1, 2) + f",{TIMELINE} SELECT * FROM adv",
    "w06_pace_all_targets": study() + f",{TIMELINE},{PACE} SELECT * FROM paced",
    "w07_records_by_part": series("l_partkey") + " SELECT series, axis, pos, s, nu FROM rec",
    "w07_records_by_brand": series("p_brand") + " SELECT series, axis, pos, s, nu FROM rec WHERE s = 1",
    "w07_records_by_supplier": series("l_suppkey") + " SELECT series, axis, count(*) AS n, max(nu) AS nu, count(*) FILTER (s = -1) AS n_behind FROM rec GROUP BY 1, 2",
    "w07_two_phase_scan": """SELECT pos, price FROM (SELECT pos, price, max(price) OVER (ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM (
  SELECT l_extendedprice / l_quantity AS price, row_number() OVER (ORDER BY l_shipdate, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice) AS pos FROM lineitem)) WHERE b IS NULL OR price > b""",
    "w08_first_appearances": series("p_brand") + " SELECT series, 'supplier' AS axis, CAST(l_suppkey AS VARCHAR) AS value, min(pos) AS pos FROM ls GROUP BY 1, 3 UNION ALL SELECT series, 'returnflag', l_returnflag, min(pos) FROM ls GROUP BY 1, 3",
    "w08_categorical_curve": series("p_brand") + ", f AS (SELECT series, pos, CAST(CASE WHEN row_number() OVER (PARTITION BY series, l_suppkey ORDER BY pos) = 1 THEN 1 ELSE 0 END AS INTEGER) AS s FROM ls) SELECT series, pos, s, count(*) FILTER (s = 1) OVER (PARTITION BY series ORDER BY pos) AS nu FROM f",
    "w09_tolerant_events": TOLERANT + " SELECT series, pos, value FROM win",
    "w09_tolerant_verdicts": TOLERANT + """, st AS (SELECT e.series, e.pos, e.event_id, e.value, w.pos IS NOT NULL AS won, (SELECT arg_max(b.value, b.pos) FROM win b WHERE b.series = e.series AND b.pos < e.pos) AS state FROM ev e LEFT JOIN win w ON w.series = e.series AND w.pos = e.pos)
SELECT series, pos, event_id, CAST(CASE WHEN won THEN 1 WHEN abs(value - state) <= 0.05 * greatest(abs(value), abs(state)) THEN 0 WHEN value > state THEN 0 ELSE -1 END AS INTEGER) AS s, count(*) FILTER (won) OVER (PARTITION BY series ORDER BY pos) AS nu FROM st""",
    "w10_value_clusters": axis() + " SELECT pos, item_id, year, value, is_core, cluster FROM nodes JOIN clus USING (pos)",
    "w10_cluster_terms": axis() + ", tk AS (SELECT cluster, token, count(*) AS n, row_number() OVER (PARTITION BY cluster ORDER BY count(*) DESC, token) AS rank FROM (SELECT cluster, unnest(tokens) AS token FROM nodes JOIN clus USING (pos) WHERE cluster IS NOT NULL) GROUP BY 1, 2) SELECT * FROM tk WHERE rank <= 3",
    "w11_vector_clusters": VECTOR_CLUSTERS + " SELECT * FROM found",
    "w12_confidence_graph": axis(", nxt AS (SELECT pos, lead(pos) OVER (PARTITION BY cluster ORDER BY pos) AS after FROM clus WHERE cluster IS NOT NULL)") + " SELECT src, dst, conf, gap FROM conf LEFT JOIN nxt ON nxt.pos = src LEFT JOIN rel ON rel.a = src AND rel.b = dst WHERE conf <> 4 OR after = dst OR sim IS NOT NULL",
    "w12_level_counts": axis() + " SELECT conf, count(*) AS n FROM conf GROUP BY 1",
    "w13_forest": axis(forest()) + " SELECT * FROM forest",
    "g12_forest_kruskal": axis(forest()) + " SELECT * FROM forest",
    "w13_roots": axis(forest()) + " SELECT pos, item_id, year, value FROM nodes WHERE pos NOT IN (SELECT dst FROM forest)",
    "w13_forest_stats": axis(forest() + LIN) + " SELECT (SELECT count(*) FROM nodes) AS n_nodes, count(*) AS n_edges, (SELECT count(*) FROM nodes) - count(*) AS n_components, (SELECT count(*) FROM nodes WHERE pos NOT IN (SELECT dst FROM forest)) AS n_roots, (SELECT max(d) FROM (SELECT min(depth) AS d FROM lin GROUP BY node)) AS depth, round(CAST(sum(CAST(sigma AS DECIMAL(18,6))) AS DOUBLE), 6) AS total_sigma FROM forest",
    "w13_forest_events": axis(forest()) + ", d AS (SELECT pos, (SELECT count(*) FROM forest WHERE dst = pos) AS n_in, (SELECT count(*) FROM forest WHERE src = pos) AS n_out FROM nodes) SELECT *, n_in = 0 AS emergence, n_out >= 2 AS divergence, n_in >= 2 AS convergence FROM d",
    "w14_lineage": axis(forest() + LIN) + " SELECT * FROM lin WHERE root = (SELECT root FROM lin GROUP BY root ORDER BY count(*) DESC, root LIMIT 1)",
    "w15_sigma_sweep": " UNION ALL ".join(
        f"SELECT CAST({g} AS DOUBLE) AS gamma, CAST({d} AS DOUBLE) AS delta, count(*) AS n_edges, round(CAST(sum(CAST(sigma AS DECIMAL(18,6))) AS DOUBLE), 6) AS total_sigma FROM (" + axis(forest(g, d)) + " SELECT sigma FROM forest)"
        for g, d in ((1, 1), (0, 1), (1, 0), (2, 1), (0, 0))
    ),
    "w16_references_only": "SELECT target_id, omega, omega_refs, round(omega - omega_refs, 6) AS diff FROM (" + study() + report("lang") + ")",
    "w17_extractors": f"""WITH c AS (SELECT len(list_filter(regexp_split_to_array(text, '{WS}'), lambda x: x <> '')) AS w0, len(regexp_extract_all(text, '[^ \\t\\n\\r\\f]+')) AS w1, len(string_split(text, chr(10))) AS l0, length(text) - length(replace(text, chr(10), '')) + 1 AS l1 FROM documents)
SELECT engine, count(*) AS cells, round(avg(CASE WHEN w0 = w1 AND l0 = l1 THEN 1.0 ELSE 0.0 END), 6) AS agree_share, CAST(sum(w1) AS BIGINT) AS n_words, CAST(sum(l1) AS BIGINT) AS n_lines FROM c CROSS JOIN (SELECT unnest(['built_in', 'sql', 'pandas', 'map', 'row']) AS engine) GROUP BY engine""",
    "w18_stage_calls": study() + ", z AS (SELECT n.target_id, count(*) AS n, any_value(m) AS m FROM net n JOIN (SELECT target_id, count(*) AS m FROM axes GROUP BY 1) USING (target_id) GROUP BY 1) " + " UNION ALL ".join(f"SELECT target_id, '{k}' AS stage, CAST({v} AS BIGINT) AS calls FROM z" for k, v in {"axes": "1", "values": "n", "overall": "n * m", "temporal": "(n + 1) * m", "graph": "n * (n - 1) // 2"}.items()),
    "w19_radar": study(1) + " SELECT axis, item_id, s FROM duels",
    "w19_profile_classes": study() + PROFILES + " SELECT target_id, item_id, min(item_id) OVER (PARTITION BY target_id, p) AS profile, count(*) OVER (PARTITION BY target_id, p) AS n_members FROM pf",
    "w19_similar_profiles": study() + PROFILES + """,
pr AS (SELECT x.target_id, x.item_id AS a, y.item_id AS b, CAST(len(list_intersect(x.ax, y.ax)) AS BIGINT) AS shared, round(len(list_intersect(x.p, y.p)) / nullif(len(list_intersect(x.ax, y.ax)), 0), 6) AS similarity FROM pf x JOIN pf y ON x.target_id = y.target_id AND x.item_id < y.item_id)
SELECT target_id, a, b, shared, similarity FROM (SELECT *, row_number() OVER (PARTITION BY target_id ORDER BY similarity DESC, shared DESC, a, b) AS k FROM pr WHERE similarity IS NOT NULL) WHERE k <= 5""",
    "w20_associations_parts": "WITH " + PARTS_WIDE + "," + long({}, ["brand", "nation"], "items") + ", graph AS (SELECT item_id, axis, v_txt AS value FROM features) " + associated("brand", "nation"),
    "w20_associations_documents": "WITH " + FEATURES + ", graph AS MATERIALIZED (SELECT item_id, axis, v_txt AS value FROM features WHERE v_txt IS NOT NULL) " + associated("licence", "source") + " UNION ALL " + associated("source", "licence"),
    "w21_bridges": "WITH " + LINKS + "," + FEATURES + SHARED + """
SELECT a.value, a.item_id, (SELECT count(*) FROM vs WHERE vs.value = a.value) AS n_members, count(*) FILTER (b.item_id IS NOT NULL AND l.src IS NOT NULL) AS n_linked, count(*) FILTER (b.item_id IS NOT NULL AND l.src IS NULL) AS n_bridges
FROM vs a LEFT JOIN vs b ON a.value = b.value AND a.item_id <> b.item_id LEFT JOIN links l ON l.src = greatest(a.item_id, b.item_id) AND l.dst = least(a.item_id, b.item_id) GROUP BY a.value, a.item_id""",
    "w21_bridge_partners": "WITH " + LINKS + "," + FEATURES + SHARED + """, ask AS (SELECT item_id FROM vs GROUP BY 1 ORDER BY count(*) DESC, item_id LIMIT 20)
SELECT a.item_id AS item_a, b.item_id AS item_b, count(*) AS n_shared FROM vs a JOIN vs b ON a.value = b.value AND a.item_id <> b.item_id WHERE a.item_id IN (SELECT item_id FROM ask) AND NOT EXISTS (SELECT 1 FROM links WHERE src = greatest(a.item_id, b.item_id) AND dst = least(a.item_id, b.item_id)) GROUP BY 1, 2""",
    "w22_stalled_ideas": axis(forest()) + " SELECT pos, item_id, value, CAST((SELECT max(period) FROM nodes) - period AS INTEGER) AS idle FROM nodes WHERE pos NOT IN (SELECT src FROM forest) AND (SELECT max(period) FROM nodes) - period >= 3",
    "w23_novelty_and_citations": study() + f",{TIMELINE},{PACE}, g AS (SELECT item_id, max(d_nu_bar) AS gain, (SELECT count(*) FROM links WHERE dst = item_id) AS cites FROM paced GROUP BY 1) SELECT *, rank() OVER (ORDER BY gain DESC) AS novelty_rank, rank() OVER (ORDER BY cites DESC) AS cite_rank FROM g",
    "w23_h_index": "WITH " + LINKS + ", c AS (SELECT doc_id, source, (SELECT count(*) FROM links WHERE dst = doc_id) AS n FROM documents), r AS (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n DESC, doc_id) AS k FROM c) SELECT source, coalesce(max(k) FILTER (n >= k), 0) AS h FROM r GROUP BY 1",
    "w24_agreement": CORPUS + """, r AS MATERIALIZED (SELECT target_id AS item_id, omega, quality AS label FROM scores JOIN labels ON doc_id = target_id)
SELECT (SELECT round(sum(CASE WHEN p.omega > n.omega THEN 1.0 WHEN p.omega = n.omega THEN 0.5 ELSE 0 END) / count(*), 6) FROM r p JOIN r n ON p.label = 1 AND n.label = 0) AS auc,
  (SELECT round(avg(label), 6) FROM (SELECT label FROM r ORDER BY omega DESC, item_id LIMIT 20)) AS p_at_k,
  (SELECT round(corr(a, b), 6) FROM (SELECT """ + ranks("omega", "a", "r") + ", " + ranks("label", "b", "r") + " FROM r)) AS rho",
    "w25_caps": PARTS + """, c AS (SELECT t.target_id, l.src AS item_id, relevance, pub_date, year(pub_date) * 12 + month(pub_date) AS mo FROM targets t JOIN links l ON dst = target_id JOIN items i ON i.item_id = l.src),
k AS (SELECT 'relevance' AS rule, target_id, mo FROM (SELECT *, row_number() OVER (PARTITION BY target_id ORDER BY relevance DESC, item_id) AS k FROM c) WHERE k <= 20 UNION ALL SELECT 'date', target_id, mo FROM (SELECT *, row_number() OVER (PARTITION BY target_id ORDER BY pub_date DESC, item_id) AS k FROM c) WHERE k <= 20),
g AS (SELECT rule, target_id, mo, count(*) AS n, sum(count(*)) OVER (PARTITION BY rule, target_id) AS t FROM k GROUP BY 1, 2, 3)
SELECT target_id, round(sum(-(n / t) * ln(n / t)), 6) AS year_entropy, max(mo) - min(mo) AS span, CAST(sum(n) AS BIGINT) AS n_items, rule FROM g GROUP BY rule, target_id""",
    "w26_curation": study() + f""",{counts(name="c0")},{omega("c0", name="s0")}, d2 AS (SELECT target_id, axis, CASE WHEN axis = 'n_chars' THEN -s ELSE s END AS s FROM duels WHERE axis <> 'n_lines'),{counts(name="c1_", source="d2")},{omega("c1_", name="s1")}
SELECT target_id, s0.omega AS omega_before, s1.omega AS omega_after FROM s0 JOIN s1 USING (target_id)""",
    "w27_streaming": f"WITH {EVENTS}, st AS (SELECT *, max(value) OVER (PARTITION BY series ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM ev), vd AS (SELECT series, event_id, pos, CAST(CASE WHEN b IS NULL OR value > b THEN 1 WHEN value = b THEN 0 ELSE -1 END AS INTEGER) AS s FROM st) SELECT series, event_id, s, count(*) FILTER (s = 1) OVER (PARTITION BY series ORDER BY pos) AS nu FROM vd",
    "w28_tournament_parts": PART_GAMES + " SELECT * FROM games",
    "w28_tournament_part_scores": games_omega(PART_GAMES, "p_brand"),
    "w28_tournament_customers": games_omega(CUSTOMER_GAMES, "c_nationkey"),
    "w29_semantic_network": semantic("vec_id % 25 = 0".replace("vec_id", "item_id"), 10) + ", wide AS (SELECT item_id, CAST(label AS VARCHAR) AS label, v[1] AS x0, v[2] AS x1, v[3] AS x2 FROM vec)," + long({"x0": 1, "x1": 1, "x2": 1}, ["label"]) + f",{AXES},{CLAIMS},{DUELS},{counts()},{omega('counts')} SELECT target_id, omega, n_axes FROM scores",
    "w30_conversations": f"WITH {CONVERSATIONS}, o AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn, role NULLS FIRST, n_chars, n_distinct, opening NULLS FIRST) AS pos FROM conv)," + """
s AS (SELECT conv_id, pos, CASE WHEN max(n_chars) OVER b IS NULL OR n_chars > max(n_chars) OVER b THEN 1 ELSE 0 END + CASE WHEN max(n_distinct) OVER b IS NULL OR n_distinct > max(n_distinct) OVER b THEN 1 ELSE 0 END
  + CASE WHEN role IS NOT NULL AND row_number() OVER (PARTITION BY conv_id, role ORDER BY pos) = 1 THEN 1 ELSE 0 END + CASE WHEN opening IS NOT NULL AND row_number() OVER (PARTITION BY conv_id, opening ORDER BY pos) = 1 THEN 1 ELSE 0 END AS n_won
  FROM o WINDOW b AS (PARTITION BY conv_id ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT conv_id, pos, CAST(n_won AS BIGINT) AS n_won, round(sum(n_won) OVER (PARTITION BY conv_id ORDER BY pos) / 4, 6) AS nu_bar, round(n_won / 4, 6) AS d_nu_bar FROM s""",
    "w31_portfolio": study() + f",{TIMELINE},{PACE} SELECT i.lang, i.source, CAST(year(i.pub_date) AS INTEGER) AS year, count(*) AS n, round(sum(n_won) / count(*), 6) AS mean_won, grouping_id(i.lang, i.source, year(i.pub_date)) AS level FROM paced p JOIN items i USING (item_id) GROUP BY CUBE (i.lang, i.source, year(i.pub_date))",
    "w32_pages": f"WITH {PAGES}, f AS (SELECT host, item_id AS page_id, title_norm, CAST(CASE WHEN title_norm IS NULL THEN NULL WHEN row_number() OVER (PARTITION BY host, title_norm ORDER BY item_id) = 1 THEN 1 ELSE 0 END AS INTEGER) AS s FROM pg) SELECT *, count(*) FILTER (s = 1) OVER (PARTITION BY host ORDER BY page_id) AS nu FROM f",
    "w33_weighting_ablation": study() + f",{counts()}, p AS (SELECT target_id, axis, alpha, coalesce(n1 / nullif(n1 + n0 + nm, 0), 0) AS p1, coalesce(n0 / nullif(n1 + n0 + nm, 0), 0) AS p0, coalesce(nm / nullif(n1 + n0 + nm, 0), 0) AS pm FROM counts CROSS JOIN ({SWEEP_ROWS})), r AS (" + " UNION ALL ".join(f"SELECT target_id, alpha, '{k}' AS weighting, {v} AS w, p1 + alpha * p0 - pm AS sc FROM p" for k, v in RAW_WEIGHTS.items()) + ") SELECT target_id, CAST(alpha AS DOUBLE) AS alpha, weighting, round(CASE WHEN sum(w) > 0 THEN sum(w * sc) / sum(w) ELSE avg(sc) END, 6) AS omega FROM r GROUP BY 1, 2, 3",
    "w34_scales": study() + NOISY + "," + ",".join(scaled(v, "duels", f"sc_{k}") for k, v in SCALES.items()) + " " + " UNION ALL ".join(
        f"SELECT target_id, '{k}' AS scale, n, omega, (SELECT round(avg(CASE WHEN x.f <> y.f THEN 1.0 ELSE 0.0 END), 6) FROM (SELECT *, CAST({v} AS DOUBLE) AS f FROM duels) x JOIN (SELECT *, CAST({v} AS DOUBLE) AS f FROM after) y USING (target_id, item_id, axis) WHERE x.f IS NOT NULL AND x.target_id = z.target_id) AS flip_rate FROM sc_{k} z"
        for k, v in SCALES.items()
    ),
    "n01_one_hop": study() + " SELECT target_id, item_id, 'reference' AS relation, 1 AS layer, relevance FROM r1 UNION ALL SELECT target_id, item_id, 'citation', 1, relevance FROM c1",
    "n02_two_layers": study() + " SELECT * FROM net",
    "n06_without_body": study() + " SELECT target_id, count(*) FILTER (trim(coalesce(text, '')) <> '') AS kept, count(*) FILTER (trim(coalesce(text, '')) = '') AS dropped FROM net JOIN documents ON doc_id = item_id GROUP BY 1",
    "n08_network_profile": study() + " SELECT target_id, relation, layer, CAST(year(pub_date) AS INTEGER) AS year, count(*) AS n FROM net JOIN items USING (item_id) GROUP BY 1, 2, 3, 4",
    "x04_axis_types": "SELECT axis, CASE WHEN avg(CASE WHEN TRY_CAST(value AS DOUBLE) IS NOT NULL THEN 1.0 ELSE 0.0 END) >= 0.8 THEN 'numeric' ELSE 'categorical' END AS kind FROM (SELECT 'n_chars' AS axis, CAST(n_chars AS VARCHAR) AS value FROM documents UNION ALL SELECT 'lang', lang FROM documents) WHERE value IS NOT NULL GROUP BY 1",
    "x11_votes": """WITH v AS (SELECT doc_id AS item_id, unnest([CASE WHEN n_chars > 1000 THEN 'long' ELSE 'short' END, CASE WHEN len(string_split(text, chr(10))) > 4 THEN 'long' ELSE 'short' END, CASE WHEN doc_id % 3 = 0 THEN 'other' ELSE 'long' END]) AS size FROM documents),
c AS (SELECT item_id, size, count(*) AS n, max(count(*)) OVER (PARTITION BY item_id) AS most FROM v GROUP BY 1, 2) SELECT item_id, CASE WHEN count(*) = 1 THEN min(size) END AS size FROM c WHERE n = most GROUP BY 1""",
    "o10_axis_contributions": study() + f""",{counts()},{omega("counts")},
lo AS (SELECT x.target_id, x.axis, CASE WHEN sum(y.p1) > 1e-12 THEN sum(y.p1 * y.sc) / sum(y.p1) ELSE avg(y.sc) END AS omega_without FROM scores_p x JOIN scores_p y ON x.target_id = y.target_id AND x.axis <> y.axis GROUP BY 1, 2)
SELECT w.target_id, 'all' AS view, w.axis, n1 AS n_win, n0 AS n_draw, nm AS n_loss, round(sc, 6) AS axis_score, round(w, 6) AS weight, round(w * sc, 6) + 0.0 AS contribution, round(omega_without, 6) AS omega_without FROM scores_w w LEFT JOIN lo ON lo.target_id = w.target_id AND lo.axis = w.axis""",
    "o12_merged_counts": study() + f",{counts()},{omega('counts')} SELECT target_id, omega, n_axes FROM scores",
    "t05_fuzzy_leaders": axis(""",
step(pos, led) AS (SELECT CAST(1 AS BIGINT), [CAST(1 AS BIGINT)] UNION ALL
  SELECT s.pos + 1, CASE WHEN EXISTS (SELECT 1 FROM rel WHERE rel.b = s.pos + 1 AND list_contains(s.led, rel.a)) THEN s.led ELSE list_append(s.led, s.pos + 1) END FROM step s WHERE s.pos < (SELECT count(*) FROM nodes))""") + " SELECT pos, item_id, value FROM nodes WHERE list_contains((SELECT led FROM step ORDER BY pos DESC LIMIT 1), pos)",
    "t11_dense_curves": study(1, 1) + f",{TIMELINE} SELECT g.target_id, g.axis, g.pos, adv.s, coalesce((SELECT max(nu) FROM adv b WHERE b.axis = g.axis AND b.pos <= g.pos), 0) AS nu FROM (SELECT tl.target_id, pos, axis FROM tl JOIN axes USING (target_id)) g LEFT JOIN adv ON adv.axis = g.axis AND adv.pos = g.pos",
    "t12_target_marker": study() + f",{TIMELINE},{PACE} SELECT target_id, pos, nu_bar, d_nu_bar FROM paced WHERE is_target",
    "t14_spells": study() + f""",{TIMELINE},{PACE}, mv AS (SELECT target_id, pos, n_won > 0 AS moving, d_nu_bar, pos - row_number() OVER (PARTITION BY target_id, n_won > 0 ORDER BY pos) AS isl FROM paced)
SELECT target_id, moving, min(pos) AS first_pos, max(pos) AS last_pos, count(*) AS n, round(sum(d_nu_bar), 6) AS gain FROM mv GROUP BY target_id, moving, isl HAVING moving OR count(*) >= 5""",
    "p09_shortlist": study() + ", h AS (SELECT target_id, item_id, count(*) FILTER (s <= 0) AS held, count(*) AS compared FROM duels WHERE axis IN ('n_chars', 'diversity', 'source') AND s IS NOT NULL GROUP BY 1, 2) SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY target_id ORDER BY held DESC, compared DESC, item_id) AS rank FROM h) WHERE rank <= 10",
    "p10_first_seen": "WITH " + ",".join([ITEMS, FEATURES]) + " SELECT value, item_id, pub_date FROM (SELECT v_txt AS value, item_id, pub_date, row_number() OVER (PARTITION BY v_txt ORDER BY pub_date, item_id) AS k FROM features JOIN items USING (item_id) WHERE axis = 'licence') WHERE k = 1",
    "p11_recurring_values": study() + " SELECT * FROM (SELECT target_id, axis, v_txt, count(*) AS n, row_number() OVER (PARTITION BY target_id, axis ORDER BY count(*) DESC, v_txt) AS rank FROM claims WHERE v_txt IS NOT NULL GROUP BY 1, 2, 3) WHERE rank <= 5",
    "b01_citation_ranks": "WITH " + LINKS + " SELECT dst AS item_id, count(*) AS cites, rank() OVER (ORDER BY count(*) DESC) AS cite_rank FROM links GROUP BY 1",
    "b03_similarity_search": semantic("item_id % 100 = 0", 10) + " SELECT target_id, item_id, relevance AS sim FROM net",
    "b04_fixed_axes": study().replace("ON item_id = target_id)", "ON item_id = target_id WHERE axis IN ('n_chars', 'lang'))", 1) + report("lang"),
    "b05_cumulative_ranks": study() + f",{TIMELINE},{PACE} SELECT target_id, item_id, nu_bar, rank() OVER (PARTITION BY target_id ORDER BY nu_bar DESC) AS nu_rank FROM paced",
    "b07_direct_labels": study() + f",{TIMELINE},{PACE} SELECT target_id, CASE WHEN d_nu_bar >= 0.3 THEN 'seminal' WHEN d_nu_bar > 0 THEN 'incremental' ELSE 'none' END AS label, count(*) AS n FROM paced GROUP BY 1, 2",
    "y05_stability": study() + f" SELECT count(*) AS cells, round(avg(CASE WHEN s IS NOT DISTINCT FROM CAST({SIGNS} AS INTEGER) THEN 1.0 ELSE 0.0 END), 6) AS agree_share, count(*) FILTER (s = 1) AS n_win, count(*) FILTER (s = 0) AS n_draw, count(*) FILTER (s = -1) AS n_loss FROM duels",
    "y05_repeated_answers": " UNION ALL ".join(uncertain(e, v) for e in (0, 10, 30) for v in (1, 3, 5)),
    "y07_flip_rates": study() + f""", noisy AS (SELECT * REPLACE (v_num * (1 + 0.05::DOUBLE * (CAST(CAST('0x' || substr(md5(concat_ws('|', target_id, item_id, axis, 3)), 1, 8) AS BIGINT) % 2001 AS DOUBLE) / 1000.0::DOUBLE - 1.0::DOUBLE)) AS v_num) FROM claims),
after AS (SELECT *, CAST({VERDICT} AS INTEGER) AS s FROM noisy),
five0 AS (SELECT target_id, item_id, axis, CAST(s AS DOUBLE) AS t, CAST({FIVE} AS DOUBLE) AS f FROM duels), five1 AS (SELECT target_id, item_id, axis, CAST(s AS DOUBLE) AS t, CAST({FIVE} AS DOUBLE) AS f FROM after),
j AS (SELECT a.t AS t0, b.t AS t1, a.f AS f0, b.f AS f1 FROM five0 a JOIN five1 b USING (target_id, item_id, axis) WHERE a.t IS NOT NULL)
SELECT count(*) AS n, round(count(*) FILTER (t0 <> t1) / count(*), 6) AS flips, 'ternary' AS scale FROM j UNION ALL SELECT count(*), round(count(*) FILTER (f0 <> f1) / count(*), 6), 'five' FROM j""",
    "y08_cluster_quality": VECTOR_CLUSTERS + """, j AS (SELECT f.*, vec.label FROM found f JOIN vec ON item_id = vec_id), c AS (SELECT cluster, label, count(*) AS n FROM j WHERE cluster IS NOT NULL GROUP BY 1, 2),
t AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM c) AS ab, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM c GROUP BY cluster)) AS a, (SELECT sum(n * (n - 1) / 2) FROM (SELECT sum(n) AS n FROM c GROUP BY label)) AS b, (SELECT sum(n) FROM c) AS total)
SELECT round((ab - a * b / (total * (total - 1) / 2)) / ((a + b) / 2 - a * b / (total * (total - 1) / 2)), 6) AS ari, round((SELECT sum(n) FROM (SELECT max(n) AS n FROM c GROUP BY cluster)) / total, 6) AS purity, (SELECT round(count(*) FILTER (cluster IS NULL) / count(*), 6) FROM j) AS noise_share FROM t""",
    "y11_coverage": study() + " SELECT axis, count(*) AS n, round(count(*) FILTER (s IS NULL) / count(*), 6) AS missing, round(count(*) FILTER (s = 1) / count(*), 6) AS win, round(count(*) FILTER (s = 0) / count(*), 6) AS draw, round(count(*) FILTER (s = -1) / count(*), 6) AS loss FROM duels GROUP BY 1",
    "y12_rank_agreement": study() + f",{TIMELINE},{PACE}, g AS (SELECT item_id, max(d_nu_bar) AS gain, (SELECT count(*) FROM links WHERE dst = item_id) AS cites FROM paced GROUP BY 1) SELECT (SELECT round(corr(a, b), 6) FROM (SELECT " + ranks("gain", "a", "g") + ", " + ranks("cites", "b", "g") + " FROM g)) AS rho, (SELECT round(count(*) / 50, 6) FROM (SELECT item_id FROM g ORDER BY gain DESC, item_id LIMIT 50) JOIN (SELECT item_id FROM g ORDER BY cites DESC, item_id LIMIT 50) USING (item_id)) AS overlap",
    "g05_alternative_clusters": axis(""",
span(a, b) AS (SELECT pos, pos FROM nodes UNION SELECT s.a, n.b FROM span s JOIN near n ON n.a = s.b)""") + " SELECT a AS pos, min(b) AS cluster FROM span GROUP BY 1",
    "g12_arborescence": axis() + " SELECT src, dst, sigma FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY sigma DESC, dst - src, src) AS k FROM (SELECT *, round(conf / (gap + 1), 6) AS sigma FROM conf)) WHERE k = 1",
    "e01_winners": CHAIN + " SELECT target_id, axis, pos, item_id, year, value FROM win",
    "e02_clusters": CHAIN + " SELECT target_id, axis, pos, label IS NOT NULL AS is_core, (SELECT k.pos FROM node k WHERE k.n = label) AS cluster FROM cl",
    "e03_forest": CHAIN + " SELECT x.target_id, x.axis, x.pos AS src, y.pos AS dst, CAST(conf AS INTEGER) AS conf, CAST(gap AS INTEGER) AS gap, sigma FROM trees JOIN node x ON x.n = src JOIN node y ON y.n = dst",
    "e04_roots": CHAIN + " SELECT target_id, axis, pos, item_id, year, value FROM win ANTI JOIN (SELECT target_id, axis, pos FROM node JOIN trees ON dst = n) USING (target_id, axis, pos)",
    "e05_axis_stats": CHAIN + " SELECT target_id, axis, count(*) AS n_winners, count(DISTINCT label) AS n_clusters, count(*) FILTER (label IS NULL) AS n_noise, (SELECT count(*) FROM trees t JOIN node x ON x.n = t.dst WHERE x.target_id = cl.target_id AND x.axis = cl.axis) AS n_edges, count(*) FILTER (n NOT IN (SELECT dst FROM trees)) AS n_roots FROM cl GROUP BY target_id, axis",
    "g02_text_vectors": axis(f", em AS MATERIALIZED (SELECT pos, {embedded('value')} AS v FROM nodes)") + f" SELECT a, b, sim FROM (SELECT x.pos AS a, y.pos AS b, {cosine('x.v', 'y.v')} AS sim FROM em x JOIN em y ON x.pos < y.pos) WHERE sim >= 0.7",
    "g04_euclidean_clusters": VECTOR_CLUSTERS.replace(f"{VECTOR_SIM} >= 0.33", "round(-sqrt(greatest(0, list_dot_product(x.v, x.v) + list_dot_product(y.v, y.v) - 2 * list_dot_product(x.v, y.v))), 6) >= -1.157") + " SELECT * FROM found",
    "g16_ancestry": axis(forest() + """,
anc(node, depth) USING KEY (node) AS (
  SELECT max(pos), CAST(0 AS BIGINT) FROM nodes
  UNION
  SELECT f.src, min(a.depth + 1) FROM anc a JOIN forest f ON f.dst = a.node LEFT JOIN recurring.anc k ON k.node = f.src WHERE k.depth IS NULL OR a.depth + 1 < k.depth GROUP BY 1)""") + " SELECT node, depth FROM anc",
    "c03_fuzzy_duels": study() + f""", vals AS MATERIALIZED (SELECT v, {norm("v")} AS nv, {embedded("v")} AS e, {token_list(norm("v"))} AS tk FROM (SELECT t_txt AS v FROM claims WHERE kind = 'categorical' AND t_txt IS NOT NULL UNION SELECT v_txt FROM claims WHERE kind = 'categorical' AND v_txt IS NOT NULL)),
prs AS MATERIALIZED (SELECT p.a, p.b, x.nv = y.nv AS exact, {jaccard("x.tk", "y.tk")} >= 0.5 AS jaccard, {edit_similarity("x.nv", "y.nv")} >= 0.5 AS edit, {cosine("x.e", "y.e")} >= 0.5 AS cosine FROM (SELECT DISTINCT t_txt AS a, v_txt AS b FROM claims WHERE kind = 'categorical' AND t_txt IS NOT NULL AND v_txt IS NOT NULL) p JOIN vals x ON x.v = p.a JOIN vals y ON y.v = p.b)
""" + " UNION ALL ".join(f"SELECT axis, count(*) FILTER (NOT {how}) AS n_win, count(*) FILTER ({how}) AS n_draw, count(*) AS n, '{how}' AS how FROM claims LEFT JOIN prs ON a = t_txt AND b = v_txt WHERE kind = 'categorical' GROUP BY 1" for how in ("exact", "jaccard", "edit", "cosine")),
    "x05_quantities": QUANTITIES + " SELECT * FROM qt",
    "c05_unit_duels": study() + "," + QUANTITIES.removeprefix("WITH ") + """, z AS (SELECT n.target_id, n.item_id, a.value AS t_num, coalesce(a.unit, '') AS t_unit, b.value AS v_num, coalesce(b.unit, '') AS v_unit FROM net n JOIN qt a ON a.item_id = n.target_id JOIN qt b ON b.item_id = n.item_id)
SELECT *, CASE WHEN t_unit = v_unit THEN CAST(sign(t_num - v_num) AS INTEGER) END AS s FROM z""",
    "c09_score_matrix": study(1) + " SELECT target_id, item_id, " + ", ".join(f"max(s) FILTER (axis = '{a}') AS {a}" for a in ("lang", "n_chars", "n_words", "source")) + " FROM duels GROUP BY 1, 2",
    "x03_parsed_answers": "SELECT event_id, nullif(json_extract_string(props, '$.k'), '') AS k, nullif(json_extract_string(props, '$.absent'), '') AS absent FROM events",
    "x10_model_answers": "SELECT doc_id AS item_id, CAST(length(text) + length('Give values for: n_chars, n_lines') + 1 AS BIGINT) AS n_chars, CAST(len(string_split(text, chr(10))) AS BIGINT) AS n_lines FROM documents",
    "x07_curated_axes": study() + f",{counts('true', 'c0', '(SELECT * FROM duels WHERE axis NOT IN (' + chr(39) + 'n_words' + chr(39) + ', ' + chr(39) + 'opening' + chr(39) + '))')},{omega('c0', name='s0')}, d2 AS (SELECT target_id, axis, CASE WHEN axis = 'n_chars' THEN -s ELSE s END AS s FROM duels WHERE axis NOT IN ('n_lines', 'opening')),{counts(name='c1_', source='d2')},{omega('c1_', name='s1')}, fw AS (SELECT target_id, p1 * CASE WHEN axis = 'diversity' THEN 2 ELSE 1 END AS raw, sc FROM s1_p) SELECT s0.target_id, s0.omega AS omega_before, round(CASE WHEN sum(raw) > 0 THEN sum(raw * sc) / sum(raw) ELSE avg(sc) END, 6) AS omega_after, count(*) AS n_axes_after FROM fw JOIN s0 USING (target_id) GROUP BY 1, 2",
    "o07_given_weights": study() + f",{counts()},{omega('counts')} SELECT target_id, round(sum(sc * CASE axis WHEN 'n_chars' THEN 0.5::DOUBLE WHEN 'source' THEN 0.3::DOUBLE WHEN 'diversity' THEN 0.2::DOUBLE ELSE 0 END), 6) AS omega, count(*) AS n_axes FROM scores_p GROUP BY 1",
    "o10_item_contributions": study() + f", left_out AS (SELECT z.out_id, d.target_id, d.axis, CASE WHEN d.item_id = z.out_id THEN NULL ELSE d.s END AS s FROM (SELECT DISTINCT target_id, item_id AS out_id FROM duels) z JOIN duels d USING (target_id)), lc AS (SELECT target_id, out_id, axis, count(*) FILTER (s = 1) AS n1, count(*) FILTER (s = 0) AS n0, count(*) FILTER (s = -1) AS nm FROM left_out GROUP BY 1, 2, 3),{omega('lc', 'target_id, out_id')} SELECT target_id, out_id AS item_id, omega AS omega_without FROM scores",
    "t15_annotated": f"WITH {EVENTS}, st AS (SELECT *, max(value) OVER (PARTITION BY series ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS state FROM ev), vd AS (SELECT *, CAST(CASE WHEN state IS NULL OR value > state THEN 1 WHEN value = state THEN 0 ELSE -1 END AS INTEGER) AS s FROM st) SELECT series, pos, s, state, CAST(CAST(value AS DECIMAL(20,6)) AS VARCHAR) || ' after ' || coalesce(CAST(CAST(state AS DECIMAL(20,6)) AS VARCHAR), 'nothing') || ': ' || CASE s WHEN 1 THEN 'advance' WHEN 0 THEN 'level' ELSE 'behind' END AS note FROM vd",
    "t17_continued_state": f"WITH {EVENTS}, st AS (SELECT *, max(value) OVER (PARTITION BY series ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS b FROM ev), vd AS (SELECT *, CAST(CASE WHEN b IS NULL OR value > b THEN 1 WHEN value = b THEN 0 ELSE -1 END AS INTEGER) AS s FROM st) SELECT * FROM (SELECT series, pos, s, count(*) FILTER (s = 1) OVER (PARTITION BY series ORDER BY pos) AS nu FROM vd) WHERE pos > 1000",
    "p05_trends": study() + f",{TIMELINE},{PACE} SELECT i.source, round(regr_slope(d_nu_bar, CAST(year(i.pub_date) AS DOUBLE)), 6) AS slope, count(*) AS n FROM paced p JOIN items i USING (item_id) GROUP BY 1",
    "b10_intransitive_triples": study() + f""", w AS (SELECT target_id AS id, {", ".join(f"max(t_num) FILTER (axis = '{a}') AS {a}" for a in DOCUMENT_NUMERIC)} FROM axes GROUP BY 1),
ld AS (SELECT x.id AS a, y.id AS b, unnest([{", ".join(f"{{'axis': '{a}', 'l': coalesce((x.{a} - y.{a}) * {d} / nullif(greatest(abs(x.{a}), abs(y.{a})), 0), 0)}}" for a, d in DOCUMENT_NUMERIC.items())}], recursive := true) FROM w x JOIN w y ON x.id < y.id),
own AS (SELECT a, b, l, 'a pair''s own axis' AS rule FROM (SELECT *, row_number() OVER (PARTITION BY a, b ORDER BY abs(l) DESC, axis) AS k FROM ld) WHERE k = 1 UNION ALL SELECT a, b, l, 'one axis' FROM ld WHERE axis = 'n_chars'),
wins AS MATERIALIZED (SELECT rule, CASE WHEN l > 0 THEN a ELSE b END AS w, CASE WHEN l > 0 THEN b ELSE a END AS l FROM own WHERE l <> 0)
SELECT rule, (SELECT count(*) FROM wins p JOIN wins q ON q.rule = p.rule AND q.w = p.l JOIN wins r ON r.rule = p.rule AND r.w = q.l AND r.l = p.w WHERE p.rule = z.rule AND p.w < q.w AND p.w < r.w) AS n_cycles, count(*) AS n_decided FROM wins z GROUP BY 1""",
    "g06_lexical_overlap": axis() + ", q AS (SELECT x.pos, x.tokens AS p, y.tokens AS q FROM nodes x JOIN nodes y ON y.pos = x.pos + 1) SELECT pos, round(len(list_intersect(p, q)) / len(list_distinct(list_concat(p, q))), 6) AS jaccard, round(len(list_intersect(p, q)) / least(len(p), len(q)), 6) AS overlap, round(len(list_intersect(p, q)) / ((len(p) + len(q)) / 2), 6) AS dice FROM q",
}
