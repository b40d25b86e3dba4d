"""SQL prefixes shared by the checks of the queries."""

from __future__ import annotations

AS_OF = 1_705_276_800_000_000  # 2024-01-15


def _capsule(kind: str, body: str, us: str, parents: str = "[]::VARCHAR[]", amends: str = "''", retracts: str = "''") -> str:
    return f"sha256(CAST(to_json({{'amends': {amends}, 'author': '', 'body': CAST(to_json({body}) AS VARCHAR), 'kind': '{kind}', 'parents': {parents}, 'retracts': {retracts}, 'us': {us}}}) AS VARCHAR))"


def _money(c: str) -> str:
    return f"CAST(CAST({c} AS DECIMAL(18,2)) AS VARCHAR)"


_subj = _capsule("subject", f"{{'balance': {_money('c_acctbal')}, 'key': c_custkey, 'nation': c_nationkey, 'segment': c_mktsegment}}", "0")
SUBJ = f"WITH subj AS (SELECT c_custkey, {_subj} AS id FROM customer) "
_epi = _capsule("episode", f"{{'key': o_orderkey, 'priority': o_orderpriority, 'status': o_orderstatus, 'total': {_money('o_totalprice')}}}", "epoch_us(o_orderdate)", "[subj.id]")
EPI = SUBJ + f", epi AS (SELECT o_orderkey, o_custkey, subj.id AS root, epoch_us(o_orderdate) AS us, {_epi} AS id FROM orders JOIN subj ON c_custkey = o_custkey) "
_item = _capsule(
    "item", f"{{'discount': {_money('l_discount')}, 'flag': l_returnflag, 'line': l_linenumber, 'part': l_partkey, 'price': {_money('l_extendedprice')}, 'quantity': {_money('l_quantity')}, 'state': l_linestatus, 'supplier': l_suppkey, 'tax': {_money('l_tax')}}}",
    "epoch_us(l_shipdate)", "[epi.id]")
ITEM = EPI + f", item AS (SELECT l_orderkey, l_partkey, l_returnflag, o_custkey, epi.id AS parent, root, epoch_us(l_shipdate) AS us, {_item} AS id FROM lineitem JOIN epi ON o_orderkey = l_orderkey) "
STAR = ITEM + ", star AS (SELECT id, id AS root, 0 AS us FROM subj UNION ALL SELECT id, root, us FROM epi UNION ALL SELECT id, root, us FROM item) "

_OBS = """obs AS (
SELECT *, CASE WHEN event_type = 'signup' THEN last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY us, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) END AS amended,
CASE WHEN event_type = 'error' AND lag(event_type) OVER (PARTITION BY user_id ORDER BY us, event_id) <> 'error' THEN lag(event_id) OVER (PARTITION BY user_id ORDER BY us, event_id) END AS retracted
FROM (SELECT event_id, user_id, event_type, value, epoch_us(ts) AS us, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events)) """
OBS = "WITH " + _OBS
_event = f"{{'event': event_id, 'k': k, 'type': event_type, 'value': {_money('value')}}}"
SIG = SUBJ + ", " + _OBS + f", sig AS (SELECT event_id, {_capsule('signal', _event, 'us', '[subj.id]')} AS id FROM obs JOIN subj ON c_custkey = user_id WHERE event_type IN ('view', 'click', 'purchase')) "
_amd = _capsule("amendment", _event, "us", "[subj.id]", amends="coalesce(target, '')")
_rtr = _capsule("retraction", _event, "us", "[subj.id]", retracts="coalesce(target, '')")
CORR = SIG + (
    f", amd AS (SELECT event_id, 'amendment' AS kind, {_amd} AS id, coalesce(target, '') AS amends, '' AS retracts FROM (SELECT obs.*, sig.id AS target FROM obs LEFT JOIN sig ON sig.event_id = amended WHERE event_type = 'signup') JOIN subj ON c_custkey = user_id)"
    f", made AS (SELECT event_id, id FROM sig UNION ALL SELECT event_id, id FROM amd)"
    f", rtr AS (SELECT event_id, 'retraction' AS kind, {_rtr} AS id, '' AS amends, coalesce(target, '') AS retracts FROM (SELECT obs.*, made.id AS target FROM obs LEFT JOIN made ON made.event_id = retracted WHERE event_type = 'error') JOIN subj ON c_custkey = user_id) "
)
THREADS = """WITH RECURSIVE t AS (SELECT conv_id, turn, coalesce(role, '') AS role, sha256(coalesce(text, '')) AS digest, row_number() OVER (PARTITION BY conv_id ORDER BY turn, coalesce(role, ''), sha256(coalesce(text, ''))) AS i, count(*) OVER (PARTITION BY conv_id) AS n FROM conversations),
chain AS (SELECT conv_id, i, n, sha256(concat_ws('|', '', CAST(turn AS VARCHAR), role, digest)) AS head FROM t WHERE i = 1
UNION ALL SELECT t.conv_id, t.i, t.n, sha256(concat_ws('|', chain.head, CAST(t.turn AS VARCHAR), t.role, t.digest)) FROM chain JOIN t ON t.conv_id = chain.conv_id AND t.i = chain.i + 1) """
_note = _capsule("note", "{'digest': sha256(text), 'doc': doc_id, 'lang': coalesce(lang, ''), 'source': coalesce(source, '')}", "0", "[subj.id]")
NOTES = SUBJ + f", note AS (SELECT doc_id, {_note} AS id FROM documents, (SELECT count(*) AS n FROM customer) JOIN subj ON c_custkey = doc_id % n) "


def _status(source: str) -> str:
    return f""", ret AS (SELECT DISTINCT retracted AS node FROM {source} WHERE retracted IS NOT NULL),
am AS (SELECT amended AS node, event_id, us, row_number() OVER (PARTITION BY amended ORDER BY us DESC, event_id DESC) AS r FROM {source} WHERE amended IS NOT NULL AND k % 2 = 0 AND event_id NOT IN (SELECT node FROM ret)),
st AS (SELECT o.event_id AS node, CASE WHEN ret.node IS NOT NULL THEN 'retracted' WHEN am.node IS NOT NULL THEN 'superseded' WHEN event_type = 'signup' AND k % 2 = 1 THEN 'pending_amendment' ELSE 'current' END AS status,
CASE WHEN ret.node IS NULL THEN coalesce(am.event_id, o.event_id) END AS current FROM {source} o LEFT JOIN ret ON ret.node = o.event_id LEFT JOIN am ON am.node = o.event_id AND am.r = 1) """


STATUS = OBS + _status("obs")
STATUS_AS_OF = OBS + f", past AS (SELECT * FROM obs WHERE us <= {AS_OF}) " + _status("past")


def _cand(window: int) -> str:
    return f""", cand AS (SELECT a.user_id AS scope, a.event_id AS src, b.event_id AS dst, a.k AS k1, b.k AS k2, b.us - a.us AS gap, greatest(a.us, b.us) AS link_us, 'etype:' || a.event_type AS tag,
10 * (100 - abs(a.k - b.k)) + 100 - (100 * (b.us - a.us)) // {window} AS score FROM obs a JOIN obs b ON a.user_id = b.user_id AND a.event_type = b.event_type AND (a.us < b.us OR a.us = b.us AND a.event_id < b.event_id)
WHERE a.event_type IN ('view', 'click', 'purchase') AND b.us - a.us <= {window}) """


_RANKED = """, ends AS (SELECT scope, src, dst, node, row_number() OVER (PARTITION BY scope, node ORDER BY score DESC, src, dst) AS r FROM (SELECT *, unnest([src, dst]) AS node FROM cand)),
ranked AS (SELECT c.*, e1.r AS r1n, e2.r AS r2n FROM cand c JOIN ends e1 ON e1.scope = c.scope AND e1.src = c.src AND e1.dst = c.dst AND e1.node = c.src JOIN ends e2 ON e2.scope = c.scope AND e2.src = c.src AND e2.dst = c.dst AND e2.node = c.dst) """
R1 = OBS + _cand(604_800_000_000)
R1_RANKED = R1 + _RANKED
R2_RANKED = OBS + _cand(259_200_000_000) + _RANKED
R1_KEPT = R1_RANKED + ", kept AS (SELECT * FROM ranked WHERE r1n <= 3 AND r2n <= 3) "
_NODES = ", nodes AS (SELECT event_id AS node, user_id AS scope, us, event_type, CASE event_type WHEN 'signup' THEN 'amendment' WHEN 'error' THEN 'retraction' ELSE 'signal' END AS kind, CASE WHEN k >= 90 THEN 2 WHEN k >= 70 THEN 1 ELSE 0 END AS level, 5 + k % 7 AS tokens FROM obs) "
NODES = OBS + _NODES
R1_NODES = R1_KEPT + _NODES
R1_STATUS = R1_KEPT + _status("obs")
R3 = ITEM + """, tagged AS (SELECT id, o_custkey, l_orderkey, us, p_brand, p_type FROM item JOIN part ON p_partkey = l_partkey),
cand AS (SELECT a.o_custkey AS scope, a.id AS src, b.id AS dst, 2 AS shared, 100 + 100 - (100 * (b.us - a.us)) // 15552000000000 AS score FROM tagged a JOIN tagged b ON a.o_custkey = b.o_custkey AND a.p_brand = b.p_brand AND a.p_type = b.p_type
AND (a.us < b.us OR a.us = b.us AND a.id < b.id) WHERE a.l_orderkey <> b.l_orderkey AND b.us - a.us <= 15552000000000) """
R4 = ITEM + """, r4 AS (SELECT a.o_custkey AS scope, a.id AS src, b.id AS dst, 100 - least(100, (b.us - a.us) // 2592000000000) AS score FROM item a JOIN item b ON a.o_custkey = b.o_custkey AND a.l_partkey = b.l_partkey
WHERE a.l_returnflag = 'R' AND a.l_orderkey <> b.l_orderkey AND b.us > a.us) """
PRIO = """WITH h AS (SELECT max(epoch_us(o_orderdate)) AS h FROM orders), l AS (SELECT o_custkey, max(epoch_us(o_orderdate)) AS last FROM orders GROUP BY 1),
prio AS (SELECT c_custkey AS scope, CASE WHEN c_acctbal < 0 THEN 4 WHEN last IS NULL OR last >= h - 94672800000000 THEN 2 ELSE 3 END AS class FROM customer LEFT JOIN l ON o_custkey = c_custkey, h) """


def _by_source(name: str, where: str) -> str:
    """Pairs of ``cand`` under a condition, by rank 3 or better at their source among all pairs there."""
    own = f"SELECT scope, src, dst, score FROM cand WHERE {where}"
    return f"{name} AS (SELECT scope, src, dst FROM (SELECT *, row_number() OVER (PARTITION BY scope, node ORDER BY score DESC, src, dst) AS r FROM (SELECT *, unnest([src, dst]) AS node FROM ({own}))) WHERE r <= 3 AND node = src)"


_NEW = "(SELECT event_id FROM obs WHERE us >= 1706140800000000)"
INCIDENT = R1 + f", {_by_source('exact', 'true')}, {_by_source('before', f'src NOT IN {_NEW} AND dst NOT IN {_NEW}')}, {_by_source('touch', f'src IN {_NEW} OR dst IN {_NEW}')}, patched AS (SELECT * FROM before UNION SELECT * FROM touch) "
CONTEXT = R1_STATUS + _NODES + """, seen AS (SELECT n.node, n.scope, n.us FROM nodes n JOIN st ON st.node = n.node WHERE kind = 'signal' AND level <= 1 AND st.current = n.node),
anchors AS (SELECT scope AS anchor, arg_max(node, us) AS node FROM seen GROUP BY 1),
e AS (SELECT k.src AS x, k.dst AS y FROM kept k JOIN seen a ON a.node = k.src JOIN seen b ON b.node = k.dst), both_ways AS (SELECT x, y FROM e UNION SELECT y, x FROM e),
got1 AS (SELECT anchor, node, 0 AS hop FROM anchors UNION SELECT DISTINCT anchor, y, 1 FROM anchors JOIN both_ways ON x = node),
beyond1 AS (SELECT DISTINCT anchor, y AS node FROM got1 JOIN both_ways ON x = node WHERE hop = 1 AND (anchor, y) NOT IN (SELECT (anchor, node) FROM got1)),
got2 AS (SELECT anchor, node, hop FROM got1 UNION ALL SELECT anchor, node, 2 FROM beyond1) """
CONTAINS = "WITH truth AS (SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)) "
#: The same with facts up to a time only.
CONTEXT_AS_OF = "WITH " + _OBS.replace("obs AS (", "obs_all AS (", 1) + f", obs AS (SELECT * FROM obs_all WHERE us <= {AS_OF}) " + CONTEXT.removeprefix(OBS)
