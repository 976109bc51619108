"""The SQL that each exact query equals."""

from __future__ import annotations

from rangeann.functions.predicates import ALL_MASKS, ALLEN, atoms_of
from rangeann.queries import APPROXIMATE

V1R1 = "SELECT vec_id AS id, embedding AS vec, (vec_id*7919)%1000 AS l, (vec_id*7919)%1000 + (vec_id*vec_id*31 + vec_id*17)%97 AS r, label FROM embeddings"
RANGES = {
    "v1r2": "SELECT l_orderkey AS id, min(l_extendedprice) AS l, max(l_extendedprice) AS r FROM lineitem GROUP BY 1",
    "v1r3": "SELECT l_orderkey AS id, epoch_us(min(l_shipdate)) AS l, epoch_us(max(l_shipdate)) AS r FROM lineitem GROUP BY 1",
    "v1r5": "SELECT o_orderkey AS id, epoch_us(o_orderdate) AS l, epoch_us(o_orderdate) AS r FROM orders",
}
LETTERS = "CAST([" + ", ".join(f"length(text)-length(replace(text,'{c}',''))" for c in "abcdefghijklmnopqrstuvwxyz") + "] AS FLOAT[])"
V2R1 = f"SELECT doc_id AS id, {LETTERS} AS vec, (doc_id*7919)%1000 AS l, (doc_id*7919)%1000 + (doc_id*doc_id*31 + doc_id*17)%97 AS r FROM documents"
#: The atoms.
ATOM = {1: "(l<=lq AND lq<=r AND r<=rq)", 2: "(l<=lq AND rq<=r)", 3: "(lq<=l AND l<=rq AND rq<=r)", 4: "(lq<=l AND r<=rq)"}
RELATION = {
    "before": "r<lq", "meets": "r=lq AND l<lq", "overlaps": "l<lq AND lq<r AND r<rq", "finished_by": "l<lq AND r=rq", "contains": "l<lq AND rq<r", "starts": "l=lq AND r<rq", "equals": "l=lq AND r=rq",
    "started_by": "l=lq AND rq<r", "during": "lq<l AND r<rq", "finishes": "lq<l AND r=rq", "overlapped_by": "lq<l AND l<rq AND rq<r", "met_by": "l=rq AND rq<r", "after": "l>rq",
}


def objects(name: str) -> str:
    if name in ("v1r1", "v2r1"):
        return V1R1 if name == "v1r1" else V2R1
    return f"SELECT e.vec_id AS id, e.embedding AS vec, x.l, x.r FROM embeddings e JOIN ({RANGES[name]}) x ON x.id = e.vec_id"


def windows(width: int) -> str:
    return f"SELECT vec_id AS qid, embedding AS qvec, 100+(vec_id*37)%800 AS lq, 100+(vec_id*37)%800+{width} AS rq FROM embeddings WHERE vec_id%50=0"


def fixed(lq: str, rq: str) -> str:
    return f"SELECT vec_id AS qid, embedding AS qvec, {lq} AS lq, {rq} AS rq FROM embeddings WHERE vec_id%50=0"


def day(d: str) -> str:
    return f"epoch_us(TIMESTAMP '{d}')"


def mask(m: int) -> str:
    return "(" + " OR ".join(ATOM[a] for a in atoms_of(m)) + ")"


def distance(a: str, b: str) -> str:
    return f"sqrt(list_sum(list_transform(list_zip({a},{b}), lambda x: (x[1]::DOUBLE-x[2]::DOUBLE)*(x[1]::DOUBLE-x[2]::DOUBLE))))"


def knn(objs: str, queries: str, condition: str, k: int = 10) -> str:
    return f"""WITH o AS ({objs}), q AS ({queries}), p AS (SELECT qid, id, {distance("vec", "qvec")} AS d FROM o JOIN q ON {condition}),
    n AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d, id) AS rank FROM p) SELECT qid, rank, id, round(d, 6) AS dist FROM n WHERE rank <= {k}"""


DOC_QUERIES = f"SELECT id AS qid, vec AS qvec, 100+(id*37)%800 AS lq, 100+(id*37)%800+55 AS rq FROM ({V2R1}) WHERE id%50=0"
PRICE, SHIP = fixed("20000.0::DOUBLE", "60000.0::DOUBLE"), fixed(day("1997-01-01"), day("2000-01-01"))
STAB, ORDER = fixed(day("1995-06-01"), day("1995-06-01")), fixed(day("1998-01-01"), day("1998-08-27"))
PLAIN = windows(55)


def zero(name: str) -> str:
    return f"SELECT '{name}' AS \"check\", CAST(0 AS BIGINT) AS violations"


SESSIONS = """e AS (SELECT user_id, event_id, event_type, value, epoch_us(ts) AS moment FROM events),
b AS (SELECT *, CASE WHEN moment - lag(moment) OVER (PARTITION BY user_id ORDER BY moment, event_id) <= 21600000000 THEN 0 ELSE 1 END AS begins FROM e),
n AS (SELECT *, CAST(sum(begins) OVER (PARTITION BY user_id ORDER BY moment, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS number FROM b)"""
NODES = "SELECT id, l + 1 AS l, r + 1 AS r FROM o"


def members(orient: str) -> str:
    key = "r" if orient == "LU" else "l"
    version = {"LU": "l + 1", "RD": "2048 - r", "LD": "2048 - l"}[orient]
    return f"SELECT '{orient}' AS orient, CAST(j AS INTEGER) AS level, CAST((1 << j) | ({key} >> (11 - j)) AS INTEGER) AS node, id, {version} AS version FROM o, generate_series(0, 11) g(j)"


ALL_MEMBERS = " UNION ALL ".join(members(o) for o in ("LU", "RD", "LD"))

ORACLES: dict[str, str] = {}
for _m in ALL_MASKS:
    ORACLES[f"rr_mask_{_m:02d}"] = ORACLES[f"vtg_mask_{_m:02d}"] = knn(V1R1, PLAIN, mask(_m))
for _m in (2, 8, 15):
    ORACLES[f"vtg_price_{_m:02d}"] = knn(objects("v1r2"), PRICE, mask(_m))
    ORACLES[f"vtg_ship_{_m:02d}"] = knn(objects("v1r3"), SHIP, mask(_m))
ORACLES["vtg_docs_15"] = ORACLES["doc_vector_knn"] = knn(V2R1, DOC_QUERIES, mask(15))
ORACLES |= {f"allen_{n}": f"WITH o AS ({V1R1}), q AS ({PLAIN}) SELECT qid, count(*) AS n FROM o JOIN q ON {RELATION[n]} GROUP BY qid" for n in ALLEN}
for _n, _o, _q, _m in (("prknn", "v1r5", ORDER, 8), ("iiknn", "v1r3", SHIP, 8), ("stab", "v1r3", STAB, 2)):
    ORACLES[f"{_n}_exact"] = ORACLES[f"{_n}_vtg"] = knn(objects(_o), _q, mask(_m))
ORACLES |= {
    "pre_filter": knn(V1R1, PLAIN, mask(15)),
    "atomic_union": knn(V1R1, PLAIN, mask(15)),
    "vtg_small_set": knn(V1R1, PLAIN, mask(15)),
    "knn_all": knn(V1R1, windows(0), "true"),
    "knn_self_join": knn("SELECT vec_id AS id, embedding AS vec FROM embeddings", "SELECT vec_id AS qid, embedding AS qvec FROM embeddings", "id <> qid", 3),
    "residual_label": knn(V1R1, windows(300), f"label = 3 AND {mask(15)}"),
    "box_plan_equiv": f"WITH o AS ({V1R1}), q AS ({PLAIN}) " + " UNION ALL ".join(f"SELECT CAST({m} AS INTEGER) AS mask, qid, count(*) AS n FROM o JOIN q ON {mask(m)} GROUP BY qid" for m in ALL_MASKS),
    "domain_rank": f"WITH o AS ({objects('v1r3')}), v AS (SELECT l AS value FROM o UNION SELECT r FROM o) SELECT value, dense_rank() OVER (ORDER BY value) AS rank FROM v",
    "tree_path": f"WITH o AS ({V1R1}) SELECT id, CAST((1 << j) | (r >> (11 - j)) AS INTEGER) AS node FROM o, generate_series(0, 11) g(j)",
    "tree_cover_members": f"WITH o AS ({V1R1}), q AS ({PLAIN}) SELECT qid, id FROM o JOIN q ON r BETWEEN lq AND rq",
    "udtf_cover": f"WITH o AS ({V1R1}), q AS ({PLAIN}) SELECT qid, id FROM o JOIN q ON r BETWEEN lq AND rq",
    "tree_node_sizes": f"WITH o AS ({V1R1}), m AS ({members('LU')}) SELECT level, node, count(*) AS n, min(version) AS first_version FROM m GROUP BY ALL",
    "size_cube": f"WITH o AS ({V1R1}), m AS ({ALL_MEMBERS}) SELECT orient, level, count(*) AS n FROM m GROUP BY CUBE (orient, level)",
    "size_rollup": f"WITH o AS ({V1R1}), m AS ({ALL_MEMBERS}) SELECT orient, level, count(*) AS n FROM m GROUP BY ROLLUP (orient, level)",
    "size_grouping_sets": f"WITH o AS ({V1R1}), m AS ({ALL_MEMBERS}) SELECT orient, level, count(*) AS n FROM m GROUP BY GROUPING SETS ((orient, level), (orient), ())",
    "version_asof": f"WITH v AS (SELECT DISTINCT l FROM ({objects('v1r3')})) SELECT o_orderkey AS id, (SELECT max(l) FROM v WHERE l <= epoch_us(o_orderdate)) AS version FROM orders",
    "interval_overlap_join": f"WITH o AS ({V1R1}), q AS ({windows(100)}) SELECT id AS a, qid AS b FROM o JOIN q ON l <= rq AND lq <= r",
    "session_overlap_counts": f"WITH {SESSIONS}, s AS (SELECT user_id, number, (min(moment) - 1704067200000000) // 3600000000 AS l, (max(moment) - 1704067200000000) // 3600000000 AS r FROM n GROUP BY 1, 2) SELECT a.user_id AS a_user, count(*) AS n FROM s a JOIN s b ON a.l <= b.r AND b.l <= a.r AND a.user_id <> b.user_id GROUP BY 1",
    "interval_semi": f"WITH o AS ({V1R1}), q AS ({PLAIN}) SELECT qid FROM q WHERE EXISTS (SELECT 1 FROM o WHERE l <= lq AND rq <= r)",
    "interval_anti": f"WITH o AS ({V1R1}), q AS ({windows(90)}) SELECT qid FROM q WHERE NOT EXISTS (SELECT 1 FROM o WHERE l <= lq AND rq <= r)",
    "range_theta_join": "WITH s AS (SELECT epoch_us(least(o_orderdate, l_shipdate)) AS l, epoch_us(greatest(o_orderdate, l_shipdate)) AS r FROM lineitem JOIN orders ON l_orderkey = o_orderkey), y AS (SELECT CAST(y AS INTEGER) AS year, epoch_us(make_timestamp(y, 1, 1, 0, 0, 0)) AS lq, epoch_us(make_timestamp(y + 1, 1, 1, 0, 0, 0)) AS rq FROM generate_series(1992, 2001) g(y)) "
    + " UNION ALL ".join(f"SELECT CAST({m} AS INTEGER) AS mask, year, count(*) AS n FROM s JOIN y ON {mask(m)} GROUP BY year" for m in (1, 2, 4, 8, 15)),
    "session_objects": f"WITH {SESSIONS} SELECT user_id, number, min(moment) AS l, max(moment) AS r, count(*) AS n, " + ", ".join(f"count(*) FILTER (event_type = '{k}') AS n_{k}" for k in ("click", "view", "purchase", "signup", "error")) + ", min(value) AS low, max(value) AS high FROM n GROUP BY 1, 2",
    "price_band": RANGES["v1r2"],
    "ship_window": RANGES["v1r3"],
    "selectivity_grid": f"WITH o AS ({V1R1}) " + " UNION ALL ".join(f"SELECT CAST({m} AS INTEGER) AS mask, CAST({w} AS INTEGER) AS width, round(avg(CASE WHEN {mask(m)} THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 9) AS share FROM o, ({windows(w)}) q" for m in ALL_MASKS for w in (0, 5, 55, 100, 300)),
    "running_births": f"WITH o AS ({V1R1}), b AS (SELECT l AS version, count(*) AS born FROM o GROUP BY l) SELECT version, born, CAST(sum(born) OVER (ORDER BY version) AS BIGINT) AS alive FROM b",
    "lead_version": f"WITH v AS (SELECT DISTINCT l AS version FROM ({V1R1})) SELECT version, lead(version) OVER (ORDER BY version) AS ends FROM v",
    "topk_single": f"WITH q AS (SELECT embedding AS qvec FROM embeddings WHERE vec_id = 0), p AS (SELECT vec_id AS id, {distance('embedding', 'qvec')} AS d FROM embeddings, q) SELECT id, round(d, 6) AS dist FROM p ORDER BY d, id LIMIT 10",
    "nearest_min_by": f"WITH t AS ({knn(V1R1, PLAIN, mask(15), 1)}) SELECT qid, id, dist FROM t",
    "set_identity": f"WITH o AS ({V1R1}), q AS ({PLAIN}) SELECT 'except' AS what, count(*) AS n FROM o JOIN q ON {mask(15)} AND NOT {mask(2)} UNION ALL SELECT 'intersect', count(*) FROM o JOIN q ON {mask(8)}",
    "json_filter": "SELECT event_type, count(*) AS n, max(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS most FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) >= 50 GROUP BY 1",
    "map_counts": "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1",
    "udaf_topk": f"WITH t AS ({knn(V1R1, PLAIN, mask(15))}) SELECT qid, string_agg(CAST(id AS VARCHAR), ',' ORDER BY rank) AS ids FROM t GROUP BY qid",
    "sql_rr_match": f"WITH o AS ({V1R1}), q AS (SELECT embedding AS qvec, 300 AS lq, 400 AS rq FROM embeddings WHERE vec_id = 0), p AS (SELECT id, round({distance('vec', 'qvec')}, 6) AS dist FROM o JOIN q ON {mask(15)}) SELECT id, dist FROM p ORDER BY dist, id LIMIT 10",
    "residual_vtg": knn(V1R1, windows(300), f"label = 3 AND {mask(15)}"),
    "stream_inserted": knn(V1R1, PLAIN, mask(15)),
    "standing": f"WITH o AS ({V1R1}) SELECT id, rank() OVER w AS rank, dense_rank() OVER w AS dense, ntile(4) OVER (PARTITION BY label ORDER BY l, id) AS quarter, round(percent_rank() OVER w, 9) AS relative, round(cume_dist() OVER w, 9) AS up_to FROM o WINDOW w AS (PARTITION BY label ORDER BY l)",
    "recent_sessions": f"WITH {SESSIONS}, s AS (SELECT user_id, number, min(moment) AS l FROM n GROUP BY 1, 2) SELECT user_id, number, count(*) OVER (PARTITION BY user_id ORDER BY l RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM s",
    "node_entries": f"WITH o AS ({V1R1}), m AS ({members('LU')}) SELECT orient, level, node, arg_min(id, version * 1000000 + id) AS id FROM m GROUP BY ALL",
    "hashed_members": "SELECT l_orderkey, count(*) AS n, max(l_quantity) AS most FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderdate >= TIMESTAMP '1998-01-01' GROUP BY 1",
    "months": "SELECT epoch_us(date_trunc('month', l_shipdate)) AS month, count(*) AS n, max(date_diff('day', o_orderdate, l_shipdate)) AS most_days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "approximate_counts": "SELECT true AS count_ok, true AS middle_ok",
    "bsp_search": "SELECT true AS recall_ok",
    "stream_sliding": "SELECT epoch_us(time_bucket(INTERVAL '6 hours', ts) - i * INTERVAL '6 hours') AS start, count(*) AS n FROM events, generate_series(0, 3) g(i) GROUP BY 1",
    "stream_static_join": "SELECT event_type, count(*) AS n FROM events WHERE user_id % 2 = 0 GROUP BY 1",
    "stream_windows": "SELECT epoch_us(date_trunc('day', ts)) AS start, count(*) AS n FROM events GROUP BY 1",
    "stream_equals_batch": f"WITH {SESSIONS} SELECT user_id, min(moment) AS l, max(moment) AS r, count(*) AS n FROM n GROUP BY user_id, number",
}
ORACLES |= {n: zero(n) for n in ("label_equiv", "degree_bound", "birth_order", "visited_unqualified", "plan_le_two", "cover_bound", "edge_count_bound", "variant_agreement", "allen_partition", "unreached", "sorted_within")}
ORACLES |= {n: " UNION ALL ".join(f"SELECT '{n}' AS method, CAST({ef} AS INTEGER) AS ef, true AS recall_ok, true AS rde_ok" for ef in (50, 100)) for n in APPROXIMATE}
ORACLES["reported"] = " UNION ALL ".join(
    f"SELECT '{claim}' AS claim, true AS holds"
    for claim in (
        "recall and distances rise with the width", "fewer distances than an exact scan at recall 0.99", "fewer distances than post-filter", "no distance outside the predicate, post-filter many",
        "distances rise with the objects, but slower", "edges and bytes rise with the objects", "edges rise with the degree",
    )
)
