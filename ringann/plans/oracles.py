"""SQL of the registered queries: definitions over all pairs, without any index."""

from __future__ import annotations

import numpy as np

from ringann.functions import theory
from ringann.operators import families
from ringann.operators.baselines import _gaussian, stop_limit
from ringann.plans.settings import BITS, CAUCHY, CP, D, EVERY, HP, K, LAM, LEVELS, M, MH, RESULTS, RINGS, RP, VISITED, W, of_width
from ringann.sources.workloads import MONTHS, MULTIPLIER

E = "SELECT vec_id AS id, embedding::DOUBLE[] AS v FROM embeddings"
SIGNS = "SELECT vec_id AS id, list_transform(embedding, lambda x: CASE WHEN x > 0 THEN 1.0::DOUBLE ELSE 0.0 END) AS v FROM embeddings"
LOWERED = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _shingles(table: str, ident: str) -> str:
    return f"""SELECT id, CASE WHEN len(w) = 0 THEN []::BIGINT[] ELSE list_sort(list_distinct(list_transform(range(1, greatest(len(w) - 2, 1) + 1), lambda i: ('0x' || substr(md5(array_to_string(w[i:i+2], ' ')), 1, 7))::BIGINT))) END AS v
      FROM (SELECT {ident} AS id, regexp_extract_all({LOWERED}, '[^\\x20\\x09-\\x0D]+') AS w FROM {table})"""


def _data(points: str = E, every: int = EVERY, rest: int = 0) -> str:
    return f"e AS ({points}), q AS (SELECT * FROM e WHERE id % {every} = {rest}), x AS (SELECT * FROM e)"


def _knn(pairs: str, dist: str, k: int = K, digits: int = 6) -> str:
    """Nearest k of a relation pairs(qid, obj_id, qv, v)."""
    return f"""SELECT qid, rnk::INT AS rnk, obj_id, round(dist, {digits}) AS dist FROM (SELECT qid, obj_id, dist, row_number() OVER (PARTITION BY qid ORDER BY dist, obj_id) AS rnk
  FROM (SELECT qid, obj_id, ({dist})::DOUBLE AS dist FROM {pairs})) WHERE rnk <= {k}"""


EUCLID, ANGLE = "list_distance(qv, v)", "acos(greatest(-1, least(1, list_cosine_similarity(qv, v))))"
MANHATTAN = "list_sum(list_transform(range(1, len(v) + 1), lambda i: abs(v[i] - qv[i])))"
HAMMING = "list_sum(list_transform(range(1, len(v) + 1), lambda i: CASE WHEN v[i] <> qv[i] THEN 1 ELSE 0 END))"
JACCARD = "CASE WHEN len(v) + len(qv) = 0 THEN 0 ELSE 1 - len(list_intersect(v, qv))::DOUBLE / (len(v) + len(qv) - len(list_intersect(v, qv))) END"
ALL = "(SELECT q.id AS qid, q.v AS qv, x.id AS obj_id, x.v AS v FROM q JOIN x ON q.id <> x.id)"


def _numbers(a: np.ndarray) -> str:
    return "[" + ", ".join(repr(float(v)) for v in a) + "]"


def _products(a: np.ndarray) -> str:
    return "[" + ", ".join(f"list_inner_product(v, {_numbers(a[:, j])})" for j in range(a.shape[1])) + "]"


def _project(rel: str, family) -> str:
    """rel(id, v) with codes."""
    if isinstance(family, families.RandomProjection):
        return f"SELECT id, v, list_transform(range(1, {family.m + 1}), lambda i: floor((y[i] + {_numbers(family.b)}[i]) / {family.w})::INT) AS codes FROM (SELECT id, v, {_products(family.a)} AS y FROM {rel})"
    if isinstance(family, families.Hyperplane):
        return f"SELECT id, v, list_transform({_products(family.a)}, lambda c: (c >= 0)::INT) AS codes FROM {rel}"
    if isinstance(family, families.BitSampling):
        return f"SELECT id, v, list_transform([{', '.join(str(int(i) + 1) for i in family.at)}], lambda i: v[i]::INT) AS codes FROM {rel}"
    if isinstance(family, families.MinHash):
        pairs = list(zip(family.a.tolist(), family.b.tolist()))
        return f"SELECT id, v, [{', '.join(f'coalesce(list_min(list_transform(v, lambda s: (s * {a} + {b}) % {families.PRIME})), {families.PRIME})::INT' for a, b in pairs)}] AS codes FROM {rel}"
    turned = ", ".join(_products(family.rotation_matrix(j)) for j in range(family.m))
    axis = "list_position(list_transform(y, lambda c: abs(c)), list_max(list_transform(y, lambda c: abs(c))))"
    return f"SELECT id, v, list_transform(yy, lambda y: (2 * ({axis} - 1) + CASE WHEN y[{axis}] < 0 THEN 1 ELSE 0 END)::INT) AS codes FROM (SELECT id, v, [{turned}] AS yy FROM {rel})"


BITS_SQL = "list_transform(range(1, len(a) + 1), lambda i: CASE WHEN a[i] = b[i] THEN '1' ELSE '0' END)"
RUN = f"least(len(a), list_max(list_transform(string_split(repeat(array_to_string({BITS_SQL}, ''), 2), '0'), lambda s: length(s))))::INT"
SAME = "list_sum(list_transform(range(1, len(a) + 1), lambda i: CASE WHEN a[i] = b[i] THEN 1 ELSE 0 END))"
LCP = f"coalesce(nullif(list_position({BITS_SQL}, '0'), 0) - 1, len(a))::INT"


def _coded(family, points: str = E, own: bool = False, tag: str = "", **which) -> str:
    """CTEs up to rl(qid, obj_id, qv, v, a, b, run_len); own: the query itself counts as an object."""
    return f"""{_data(points, **which)}, cx{tag} AS ({_project('x', family)}), cq{tag} AS ({_project('q', family)}),
  pr{tag} AS (SELECT cq.id AS qid, cq.v AS qv, cx.id AS obj_id, cx.v AS v, cq.codes AS b, cx.codes AS a FROM cq{tag} cq JOIN cx{tag} cx ON {'TRUE' if own else 'cq.id <> cx.id'}), rl{tag} AS (SELECT *, {RUN} AS run_len FROM pr{tag})"""


def _best(lam: int, rel: str = "rl", name: str = "cand") -> str:
    return f"{name} AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY run_len DESC, obj_id) AS place FROM {rel}) WHERE place <= {lam})"


def _ring(family, dist: str, k: int = K, points: str = E, lam: int = LAM) -> str:
    return f"WITH {_coded(family, points)}, {_best(lam + k - 1)} {_knn('cand', dist, k)}"


def _search(family=RP, lam: int = LAM, k: int = K, digits: int = 12, **which) -> str:
    """CTEs with found and truth."""
    return f"{_coded(family, **which)}, {_best(lam + k - 1)}, found AS ({_knn('cand', EUCLID, k, digits)}), truth AS ({_knn(ALL, EUCLID, k, digits)})"


PER_QUERY = "SELECT t.qid, avg(CASE WHEN t.obj_id IN (SELECT obj_id FROM found g WHERE g.qid = t.qid) THEN 1.0 ELSE 0.0 END) AS recall, avg(f.dist / t.dist) AS ratio FROM truth t JOIN found f ON f.qid = t.qid AND f.rnk = t.rnk GROUP BY t.qid"


def _study(name: str, cases: list[tuple[str, str]]) -> str:
    """Mean recall and ratio of every case (value, CTEs with found and truth)."""
    return " UNION ALL ".join(f"(WITH {ctes} SELECT round(avg(recall), 6) AS recall, round(avg(ratio), 6) AS ratio, {value} AS {name} FROM ({PER_QUERY}))" for value, ctes in cases)


def _rank(own: bool = True, columns: str = "qid, place::INT AS rnk, obj_id, run_len") -> str:
    return f"WITH {_coded(RP, own=own)}, {_best(LAM)} SELECT {columns} FROM cand"


TURN = "list_concat(codes[rot + 1:], codes[1:rot])"


def _near_in_order(asked: str, keys: str) -> str:
    """CTEs with bnd({keys}, rot, lower, upper, lower_len, upper_len): neighbours among cx of asked({keys}, codes) in every rotation."""
    lcp = lambda side: f"CASE WHEN {side} IS NULL THEN 0 ELSE (SELECT {LCP} FROM (SELECT {side}.s AS a, qs AS b)) END"
    return f"""rots AS (SELECT unnest(range(0, {M})) AS rot), xs AS (SELECT id, rot, {TURN} AS s FROM cx CROSS JOIN rots), qs AS (SELECT {keys}, rot, {TURN} AS qs FROM {asked} CROSS JOIN rots),
  near AS (SELECT {keys}, qs.rot, qs, max(CASE WHEN s <= qs THEN struct_pack(s := s, id := xs.id) END) AS low, min(CASE WHEN s > qs THEN struct_pack(s := s, id := xs.id) END) AS up FROM qs JOIN xs ON qs.rot = xs.rot GROUP BY {keys}, qs.rot, qs),
  bnd AS (SELECT {keys}, rot::INT AS rot, low.id AS lower, up.id AS upper, ({lcp('low')})::INT AS lower_len, ({lcp('up')})::INT AS upper_len FROM near)"""


BOUNDS = f"WITH {_coded(RP, own=True)}, {_near_in_order('(SELECT id AS qid, codes FROM cq)', 'qid')} SELECT * FROM bnd"


def _probes(n_probes: int, n_alt: int = 4) -> str:
    """CTEs with probes(qid, probe_no, score, delta, codes) of RP, the empty one first; cx, cq given before."""
    steps = "[1, 2, 3, -1, -2, -3]"
    edge = "CASE WHEN d > 0 THEN power(d * w - r, 2) ELSE power(r + (-d - 1) * w, 2) END"
    bound = (n_probes - 2) // M  # so many alternatives of every position are surely enough
    return f"""yq AS (SELECT id AS qid, {_products(RP.a)} AS y FROM q), pos AS (SELECT qid, p, (y[p + 1] + {_numbers(RP.b)}[p + 1]) / {RP.w} AS z FROM yq CROSS JOIN (SELECT unnest(range(0, {M})) AS p)),
  alts AS (SELECT qid, p, (row_number() OVER (PARTITION BY qid, p ORDER BY score) - 1) AS a, code, score FROM (
    SELECT qid, p, (floor(z) + d)::INT AS code, {edge} AS score FROM (SELECT qid, p, z, (z - floor(z)) * {RP.w} AS r, {RP.w} AS w, unnest({steps}) AS d FROM pos))),
  few AS (SELECT * FROM alts WHERE a < {n_alt}), lim AS (SELECT qid, max(score) + 1e-9 AS lim FROM alts WHERE a = {bound} GROUP BY qid),
  vecs(qid, p, score, delta) AS (SELECT f.qid, p, score, [struct_pack(p := p, c := code)] FROM few f JOIN lim USING (qid) WHERE score <= lim
    UNION ALL SELECT f.qid, f.p, v.score + f.score, list_append(v.delta, struct_pack(p := f.p, c := f.code)) FROM vecs v JOIN few f ON f.qid = v.qid AND f.p - v.p BETWEEN 1 AND 2 JOIN lim ON lim.qid = v.qid WHERE v.score + f.score <= lim),
  probes AS (SELECT n.qid, (n - 1)::INT AS probe_no, score, delta, list_transform(range(0, {M}), lambda i: coalesce(list_filter(delta, lambda s: s.p = i)[1].c, cq.codes[i + 1])) AS codes FROM (
    SELECT qid, score, delta, row_number() OVER (PARTITION BY qid ORDER BY score, len(delta)) AS n FROM (SELECT qid, score, delta FROM vecs UNION ALL SELECT id, 0, [] FROM q)) n JOIN cq ON cq.id = n.qid WHERE n <= {n_probes})"""


def _probed(n_probes: int, k: int = K) -> str:
    """CTEs with cand: the best objects by their longest run with the query or a probe."""
    return f"""RECURSIVE {_coded(RP)}, {_probes(n_probes)}, many AS (SELECT r.qid, obj_id, qv, v, max(run_len) AS run_len FROM (SELECT pr.qid, obj_id, qv, v, {RUN.replace('b[i]', 'codes[i]')} AS run_len FROM pr JOIN probes USING (qid)) r GROUP BY r.qid, obj_id, qv, v), {_best(LAM + k - 1, 'many')}"""


def _rounds(level: str, levels: int, source: str) -> str:
    """Nearest K at the first level with K candidates or more; source(qid, qv, obj_id, v, a, b), level gives an object's first level."""
    return f"""{source}, lv AS (SELECT qid, qv, obj_id, v, {level} AS level FROM pr), sums AS (SELECT qid, l, (SELECT count(*) FROM lv WHERE lv.qid = q0.qid AND lv.level <= l) AS n FROM (SELECT id AS qid FROM q) q0 CROSS JOIN (SELECT unnest(range(0, {levels})) AS l)),
  stop AS (SELECT qid, coalesce(min(CASE WHEN n >= {K} THEN l END), {levels - 1}) AS stop FROM sums GROUP BY qid) {_knn('(SELECT lv.* FROM lv JOIN stop USING (qid) WHERE level <= stop)', EUCLID)}"""


def _first_level(tests: list[str]) -> str:
    return "CASE " + " ".join(f"WHEN {t} THEN {i}" for i, t in enumerate(tests)) + " ELSE 99 END"


def _near(a: str, b: str, half: float) -> str:
    return f"list_sum(list_transform(range(1, {M + 1}), lambda i: CASE WHEN abs({a}[i] - {b}[i]) <= {half!r} THEN 1 ELSE 0 END))"


_QA, _PJ, _EDGE = _gaussian(D, M, 7), _gaussian(D, 6, 7), _gaussian(D, 2, 7)
AWARE = f"{_data()}, px AS (SELECT *, {_products(_QA)} AS a FROM x), pq AS (SELECT *, {_products(_QA)} AS b FROM q), pr AS (SELECT pq.id AS qid, pq.v AS qv, px.id AS obj_id, px.v AS v, a, b FROM px JOIN pq ON pq.id <> px.id)"


def _visits(**which) -> str:
    return f"{_data(**which)}, px AS (SELECT *, {_products(_PJ)} AS a FROM x), pq AS (SELECT *, {_products(_PJ)} AS b FROM q), pr AS (SELECT pq.id AS qid, pq.v AS qv, px.id AS obj_id, px.v AS v, list_distance(a, b) AS far, row_number() OVER (PARTITION BY pq.id ORDER BY list_distance(a, b), px.id) AS place FROM px JOIN pq ON pq.id <> px.id)"


VISITS = _visits()


def _early() -> str:
    limit = stop_limit(6, 0.8)
    return f"""WITH {VISITS}, seen AS (SELECT *, list_distance(qv, v) AS dist FROM pr WHERE place <= 100), kth AS (SELECT *, list_sort(list(dist) OVER (PARTITION BY qid ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))[{K}] AS kth FROM seen),
  cut AS (SELECT qid, min(place) AS stop FROM kth WHERE kth IS NOT NULL AND power(far * 1.5 / kth, 2) >= {limit!r} GROUP BY qid) {_knn('(SELECT seen.* FROM seen LEFT JOIN cut USING (qid) WHERE stop IS NULL OR place < stop)', EUCLID)}"""


def _blocked() -> str:
    """Two halvings, five boundary objects on each of two projections, the two nearest blocks."""
    return f"""WITH {AWARE}, c0 AS (SELECT quantile_disc(v[1], 0.5) AS c FROM e), b1 AS (SELECT id, v, (v[1] > c)::INT AS b FROM e CROSS JOIN c0), c1 AS (SELECT b, quantile_disc(v[2], 0.5) AS c FROM b1 GROUP BY b),
  blk AS (SELECT id, v, 2 * b1.b + (v[2] > c)::INT AS block FROM b1 JOIN c1 ON b1.b = c1.b),
  lines AS (SELECT id, v, block, row_number() OVER (PARTITION BY block, j ORDER BY y[j], id) - 1 AS r, count(*) OVER (PARTITION BY block, j) AS n FROM (SELECT *, {_products(_EDGE)} AS y, unnest([1, 2]) AS j FROM blk)),
  ends AS (SELECT DISTINCT block, id, v FROM lines WHERE list_contains(list_transform(range(0, 5), lambda i: floor(i * (n - 1) / 4)::BIGINT), r)),
  close AS (SELECT qid, block FROM (SELECT qid, block, row_number() OVER (PARTITION BY qid ORDER BY far, block) AS n FROM (SELECT q.id AS qid, block, min(list_distance(q.v, ends.v)) AS far FROM q CROSS JOIN ends GROUP BY q.id, block)) WHERE n <= 2)
  {_knn(f"(SELECT pr.* FROM pr JOIN blk ON blk.id = pr.obj_id JOIN close ON close.qid = pr.qid AND close.block = blk.block WHERE {_near('a', 'b', 1.5)} >= 5)", EUCLID)}"""


def _slots(k: int) -> str:
    return "(" + " OR ".join("(" + " AND ".join(f"a[{i + j + 1}] = b[{i + j + 1}]" for j in range(k)) + ")" for i in range(0, M, 2)) + ")"


def _probe_tables() -> str:
    """Four tables of two codes; per query and table the five best of the buckets with each code moved by at most one slot."""
    table = f"""SELECT qid, t, k1, k2, row_number() OVER (PARTITION BY qid, t ORDER BY s1 + s2) AS n FROM (SELECT u.qid, u.p // 2 AS t, u.code AS k1, u.score AS s1, w.code AS k2, w.score AS s2 FROM mv u JOIN mv w ON u.qid = w.qid AND u.p % 2 = 0 AND w.p = u.p + 1)"""
    mv = f"""mv AS (SELECT qid, p, (floor(z) + d)::INT AS code, CASE d WHEN 0 THEN 0 WHEN 1 THEN power((1 - (z - floor(z))) * {RP.w}, 2) ELSE power((z - floor(z)) * {RP.w}, 2) END AS score FROM (SELECT qid, p, z, unnest([0, 1, -1]) AS d FROM pos))"""
    pos = f"yq AS (SELECT id AS qid, {_products(RP.a)} AS y FROM q), pos AS (SELECT qid, p, (y[p + 1] + {_numbers(RP.b)}[p + 1]) / {RP.w} AS z FROM yq CROSS JOIN (SELECT unnest(range(0, {M})) AS p))"
    return f"WITH {_coded(RP)}, {pos}, {mv}, keys AS (SELECT * FROM ({table}) WHERE n <= 5) {_knn('(SELECT DISTINCT pr.* FROM pr JOIN keys k ON k.qid = pr.qid AND a[2 * t + 1] = k1 AND a[2 * t + 2] = k2)', EUCLID)}"


def _vertices(n: int, columns: str, rel: str = "q", name: str = "vert") -> str:
    """The n best vertices of every position, by their gap to the best one; place 0 is the code."""
    turned = ", ".join(f"list_transform({_products(CP.rotation_matrix(j))}, lambda c: c / sqrt(list_sum(list_transform({_products(CP.rotation_matrix(j))}, lambda g: g * g))))" for j in range(M))
    return f"""yy AS (SELECT id, [{turned}] AS yy FROM {rel}), flat AS (SELECT id, p, 2 * (i - 1) + s AS code, (1 - 2 * s) * yy[p + 1][i] AS c FROM (SELECT id, yy, p, i, unnest([0, 1]) AS s FROM (SELECT id, yy, p, unnest(range(1, {CP.dim + 1})) AS i FROM (SELECT id, yy, unnest(range(0, {M})) AS p FROM yy)))),
  {name} AS (SELECT * FROM (SELECT id, p, code::INT AS code, power(max(c) OVER (PARTITION BY id, p) - c, 2) AS score, row_number() OVER (PARTITION BY id, p ORDER BY c DESC, code) - 1 AS place FROM flat) WHERE place < {n}) {columns}"""


def _ladder() -> str:
    parts, tags = [], []
    for i in range(4):
        f = of_width(W * 1.5**i)
        parts.append(_coded(f, tag=str(i)) if i == 0 else _coded(f, tag=str(i)).split(", x AS (SELECT * FROM e), ", 1)[1])
        parts.append(_best(LAM, f"rl{i}", f"cand{i}"))
        tags.append(f"SELECT {i} AS level, * FROM ({_knn(f'cand{i}', EUCLID, 1, 12)}) WHERE dist <= {0.5 * 1.5 ** (i + 1)!r}")
    return f"WITH {', '.join(parts)}, hits AS ({' UNION ALL '.join(tags)}) SELECT qid, level::INT AS level, obj_id, round(dist, 6) AS dist FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY level) AS n FROM hits) WHERE n = 1"


def _values(rows) -> str:
    return ", ".join("(" + ", ".join("NULL" if v is None else f"'{v}'" if isinstance(v, str) else f"{v!r}::DOUBLE" if isinstance(v, float) else str(v) for v in r) + ")" for r in rows)


RESULT_ROWS = f"res AS (SELECT * FROM (VALUES {_values(RESULTS)}) t(method, params, recall, ratio, seconds, index_bytes))"


def _setting(ctes: str, method: str, params: str, cost: int, row_bytes: int) -> str:
    """A measured row from CTEs with found and truth."""
    return f"""(WITH {ctes} SELECT '{method}' AS method, '{params}' AS params, round(avg(r), 4) AS recall, {float(cost)!r}::DOUBLE AS seconds, (SELECT count(*) FROM embeddings) * {row_bytes} AS index_bytes
      FROM (SELECT t.qid, avg(CASE WHEN f.obj_id IS NULL THEN 0.0 ELSE 1.0 END) AS r FROM truth t LEFT JOIN found f ON f.qid = t.qid AND f.obj_id = t.obj_id GROUP BY t.qid))"""


def _measured(**which) -> str:
    """CTE res with the settings that the reductions measure."""
    rings = [_setting(_search(families.RandomProjection(D, m, W, seed=7), lam, **which), "ring", f"m={m},lam={lam}", lam + K - 1, 8 + 12 * m) for m, lam in RINGS]
    visits = [_setting(f"{_visits(**which)}, found AS ({_knn(f'(SELECT * FROM pr WHERE place <= {v})', EUCLID, K, 12)}), truth AS ({_knn(ALL, EUCLID, K, 12)})", "projected_incremental", f"visits={v}", v, 8 + 8 * 6) for v in VISITED]
    return f"res AS ({' UNION ALL '.join(rings + visits)})"


MEASURED_ROWS = _measured()


def _hashed(rows: str, d: int) -> str:
    """Signed hashed byte trigrams of rows(id, t), of length 1."""
    return f"""WITH h AS (SELECT id, hex(encode(t)) AS x FROM ({rows})), g AS (SELECT id, (('0x' || substr(x, 2 * i - 1, 6))::BIGINT * {MULTIPLIER}) % 4294967296 AS h FROM (SELECT id, x, unnest(range(1, length(x) // 2 - 1)) AS i FROM h WHERE length(x) >= 6)),
  s AS (SELECT id, (h // 256) % {d} AS slot, sum(CASE WHEN h >= 2147483648 THEN -1 ELSE 1 END)::DOUBLE AS n FROM g GROUP BY id, slot), l AS (SELECT id, sqrt(sum(n * n)) AS len FROM s GROUP BY id HAVING sum(n * n) > 0)
  SELECT l.id AS obj_id, list_transform(range(0, {d}), lambda i: round(coalesce(mm[i], 0) / len, 6)) AS vec FROM l JOIN (SELECT id, map(list(slot), list(n)) AS mm FROM s GROUP BY id) y USING (id)"""


def _standard(rows: str, columns: list[str], keep: str = "obj_id, ") -> str:
    cells = ", ".join(f"CASE WHEN stddev_pop({c}) OVER () > 0 THEN round(({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER (), 6) ELSE 0.0 END" for c in columns)
    return f"SELECT {keep}[{cells}] AS vec FROM ({rows})"


_P1, _P2 = theory.rp_collision_prob(0.5, 2.0), theory.rp_collision_prob(1.0, 2.0)
HEAD = f"WITH {_search()}"
PARTS = "SELECT l_partkey AS obj_id, avg(l_quantity) AS qty, avg(l_extendedprice) AS price, avg(l_discount) AS disc, avg(l_tax) AS tax, count(*)::DOUBLE AS n, avg((l_returnflag = 'R')::INT) AS ret, avg((l_linestatus = 'F')::INT) AS fin, coalesce(stddev_samp(l_quantity), 0) AS qty_sd, " + ", ".join(f"avg((month(l_shipdate) = {i})::INT) AS m{i}" for i in range(1, 13)) + " FROM lineitem GROUP BY l_partkey"
CUSTOMERS = "SELECT c_custkey AS obj_id, c_acctbal AS bal, coalesce(n, 0)::DOUBLE AS n, coalesce(avg_price, 0) AS avg_price, coalesce(max_price, 0) AS max_price FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n, avg(o_totalprice) AS avg_price, max(o_totalprice) AS max_price FROM orders GROUP BY o_custkey) ON o_custkey = c_custkey"
STRIPPED = r"trim(regexp_replace(regexp_replace(regexp_replace(coalesce(html, ''), '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \t\n\r]+', ' ', 'g'))"
SIZES = "SELECT year(l_shipdate)::INT AS year, count(*)::BIGINT AS n FROM lineitem GROUP BY ALL"

ORACLES = {
    "exact_knn_euclid": f"WITH {_data()} {_knn(ALL, EUCLID)}",
    "exact_knn_angular": f"WITH {_data()} {_knn(ALL, ANGLE)}",
    "exact_knn_manhattan": f"WITH {_data()} {_knn(ALL, MANHATTAN)}",
    "exact_knn_jaccard": f"WITH {_data(_shingles('documents', 'doc_id'))} {_knn(ALL, JACCARD)}",
    "codes_random_projection": f"WITH {_data()} SELECT id AS obj_id, codes FROM ({_project('e', RP)})",
    "codes_hyperplane": f"WITH {_data()} SELECT id AS obj_id, codes FROM ({_project('e', HP)})",
    "codes_hadamard_crosspoly": f"WITH {_data()} SELECT id AS obj_id, codes FROM ({_project('e', CP)})",
    "codes_cauchy": f"WITH {_data()} SELECT id AS obj_id, codes FROM ({_project('e', CAUCHY)})",
    "codes_bits": f"WITH {_data(SIGNS)} SELECT id AS obj_id, codes FROM ({_project('e', BITS)})",
    "codes_minhash": f"WITH {_data(_shingles('documents', 'doc_id'))} SELECT id AS obj_id, codes FROM ({_project('e', MH)})",
    "sensitivity": """SELECT family, round(p1, 6) AS p1, round(p2, 6) AS p2, round(ln(1 / p1) / ln(1 / p2), 6) AS rho FROM (SELECT 'hyperplane' AS family, 1 - 0.4 / pi() AS p1, 1 - 0.8 / pi() AS p2 UNION ALL SELECT 'bits', 1 - 4.0 / 64, 1 - 8.0 / 64
      UNION ALL SELECT 'cross_polytope', exp(-0.16 / (4 - 0.16) * ln(64)), exp(-0.64 / (4 - 0.64) * ln(64)) UNION ALL SELECT 'minhash', 0.8, 0.6
      UNION ALL SELECT 'cauchy', 2 * atan(16) / pi() - ln(1 + 256) / (pi() * 16), 2 * atan(8) / pi() - ln(1 + 64) / (pi() * 8))""",
    "collision_profile": f"WITH {_coded(RP)} SELECT floor({EUCLID} / 0.1)::BIGINT AS bin, round(avg({SAME} / len(a)), 6) AS share, count(*)::BIGINT AS pairs FROM pr GROUP BY bin",
    "run_length_pairs": f"""WITH {_coded(RP)} SELECT qid, obj_id, run_len, {LCP} AS lcp, ({SAME})::INT AS equal, CASE WHEN run_len = 0 THEN 0 ELSE instr(repeat(array_to_string({BITS_SQL}, ''), 2), repeat('1', run_len)) - 1 END::INT AS start,
      a[7] = b[7] AND a[8] = b[8] AND a[1] = b[1] AS aligned FROM rl""",
    "rotation_orders": f"""WITH {_coded(RP)}, r AS (SELECT rot, id, row_number() OVER (PARTITION BY rot ORDER BY list_concat(codes[rot + 1:], codes[1:rot]), id) AS rank FROM cx CROSS JOIN (SELECT unnest(range(0, {M})) AS rot))
      SELECT a.rot::INT AS rot, a.rank::INT AS rank, a.id AS obj_id, b.rank::INT AS next_rank FROM r a JOIN r b ON a.id = b.id AND b.rot = (a.rot + 1) % {M}""",
    "bounds_narrowed": BOUNDS,
    "bounds_simple": BOUNDS,
    "k_search_kernel": _rank(),
    "k_search_brute": _rank(),
    "k_search_prefix": _rank(),
    "k_search_window": _rank(columns="qid, place::INT AS rnk, run_len"),
    "ring_search_euclid": _ring(RP, EUCLID),
    "ring_search_angular": _ring(HP, ANGLE),
    "ring_search_crosspoly": _ring(CP, ANGLE),
    "ring_search_manhattan": _ring(CAUCHY, MANHATTAN),
    "ring_search_hamming": _ring(BITS, HAMMING, points=SIGNS),
    "ring_search_jaccard": _ring(MH, JACCARD, points=_shingles("documents", "doc_id")),
    "ring_search_shard": f"WITH {_coded(RP)}, cand AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid, obj_id % 3 ORDER BY run_len DESC, obj_id) AS place FROM rl) WHERE place <= {LAM + K - 1}) {_knn('cand', EUCLID)}",
    "ring_top1": _ring(RP, EUCLID, 1),
    "ring_probe": f"WITH {_probed(M + 1)} {_knn('cand', EUCLID)}",
    "ring_probe_trivial": f"WITH {_probed(M + 1)} {_knn('cand', EUCLID)}",
    "probe_work": f"""WITH RECURSIVE {_coded(RP, own=True)}, {_probes(M + 1)}, {_near_in_order('probes', 'qid, probe_no')}
      SELECT f.qid, count(DISTINCT CASE WHEN (f.delta[1].p - rot + {M}) % {M} <= greatest(lower_len, upper_len) THEN f.probe_no * {M} + rot END)::BIGINT AS skipping, (count(DISTINCT f.probe_no) * {M})::BIGINT AS trivial
      FROM probes f JOIN probes part ON part.qid = f.qid AND part.delta = f.delta[2:] JOIN bnd ON bnd.qid = part.qid AND bnd.probe_no = part.probe_no WHERE f.probe_no > 0 GROUP BY f.qid""",
    "alternatives_projection": f"""WITH e AS ({E}), s AS (SELECT * FROM e WHERE id % 10 = 0), pos AS (SELECT id, p, (y[p + 1] + {_numbers(RP.b)}[p + 1]) / {RP.w} AS z FROM (SELECT id, {_products(RP.a)} AS y FROM s) CROSS JOIN (SELECT unnest(range(0, {M})) AS p))
      SELECT id AS obj_id, p::INT AS pos, place::INT AS place, code, round(score, 6) AS score FROM (SELECT id, p, code, score, row_number() OVER (PARTITION BY id, p ORDER BY score) - 1 AS place FROM (
        SELECT id, p, (floor(z) + d)::INT AS code, CASE WHEN d > 0 THEN power(d * w - r, 2) ELSE power(r + (-d - 1) * w, 2) END AS score FROM (SELECT id, p, z, (z - floor(z)) * {RP.w} AS r, {RP.w} AS w, unnest([1, 2, 3, -1, -2, -3]) AS d FROM pos))) WHERE place < 4""",
    "alternatives_crosspoly": f"WITH e AS ({E}), s AS (SELECT * FROM e WHERE id % 10 = 0), {_vertices(6, '', 's')} SELECT id AS obj_id, p::INT AS pos, (place - 1)::INT AS place, code, round(score, 6) AS score FROM vert WHERE place > 0",
    "perturbations": f"WITH RECURSIVE {_coded(RP)}, {_probes(M + 1)} SELECT qid, probe_no, round(score, 6) AS score, coalesce(array_to_string(list_transform(delta, lambda s: s.p || '=' || s.c), ' '), '') AS changes FROM probes",
    "ring_knn_graph": f"WITH {_coded(RP, every=1)}, {_best(LAM + 4)} {_knn('cand', EUCLID, 5)}",
    "ring_pairs": f"WITH {_coded(RP, every=1)}, {_best(LAM + 4)} SELECT DISTINCT least(qid, obj_id) AS a, greatest(qid, obj_id) AS b, dist FROM ({_knn('cand', EUCLID, 5)}) WHERE dist <= 1.1",
    "ann_join_filtered": f"""WITH {_coded(RP)}, ev AS (SELECT rl.* FROM (SELECT cq.id AS qid, cq.v AS qv, cx.id AS obj_id, cx.v AS v, run_len FROM (SELECT * FROM (SELECT cq.id AS qid, cx.id AS obj_id, cq.codes AS b, cx.codes AS a FROM cq CROSS JOIN cx) t, LATERAL (SELECT {RUN} AS run_len) u) m JOIN cq ON cq.id = m.qid JOIN cx ON cx.id = m.obj_id) rl
        JOIN embeddings l ON l.vec_id = rl.obj_id WHERE label % 2 = 0), {_best(2 * LAM + K - 1, 'ev')} {_knn('(SELECT * FROM cand WHERE obj_id > qid)', EUCLID)}""",
    "index_stats": f"SELECT ceil(n / 200.0)::BIGINT AS shards, n::BIGINT AS objects, (n * (8 + 12 * {M}))::BIGINT AS index_bytes FROM (SELECT count(*) AS n FROM embeddings)",
    "c_ann_check": f"{HEAD} SELECT t.qid, bool_or(t.rnk = 1 AND f.dist <= 1.1 * t.dist + 1e-12) AS nearest, bool_and(f.dist <= 1.1 * t.dist + 1e-12) AS all_k FROM truth t JOIN found f ON f.qid = t.qid AND f.rnk = t.rnk GROUP BY t.qid",
    "near_neighbor": f"WITH {_search(k=1, digits=6)} SELECT q.id AS qid, coalesce(f.obj_id, -1) AS obj_id, coalesce(f.dist, -1) AS dist FROM q LEFT JOIN (SELECT * FROM found WHERE dist <= 1.2) f ON f.qid = q.id",
    "near_neighbor_theory": "",
    "radius_ladder": _ladder(),
    "radius_ladder_shared": f"WITH {_coded(CP)}, {_best(LAM)}, found AS ({_knn('cand', ANGLE, 1, 12)}) SELECT qid, l::INT AS level, obj_id, round(dist, 6) AS dist FROM (SELECT *, CASE WHEN dist <= 0.375 THEN 0 ELSE ceil(ln(dist / 0.375) / ln(1.25) - 1e-12) END AS l FROM found) WHERE l < 6",
    "static_concat": f"WITH {_coded(RP)} {_knn(f'(SELECT * FROM pr WHERE {_slots(2)})', EUCLID)}",
    "static_concat_angular": f"WITH {_coded(CP)} {_knn(f'(SELECT * FROM pr WHERE {_slots(2)})', ANGLE)}",
    "prefix_widening": f"WITH {_coded(RP)}, two AS (SELECT * FROM pr WHERE {_slots(2)}), enough AS (SELECT qid FROM two GROUP BY qid HAVING count(*) >= 60) {_knn(f'(SELECT * FROM two WHERE qid IN (SELECT qid FROM enough) UNION ALL SELECT * FROM pr WHERE qid NOT IN (SELECT qid FROM enough) AND {_slots(1)})', EUCLID)}",
    "multiprobe_static": _probe_tables(),
    "crosspoly_probe": f"WITH {_coded(CP)}, {_vertices(4, '')} {_knn('(SELECT DISTINCT pr.* FROM pr JOIN vert ON vert.id = pr.qid AND a[p + 1] = code)', ANGLE)}",
    "collision_count": f"WITH {_coded(RP)} {_knn(f'(SELECT * FROM pr WHERE {SAME} >= 4)', EUCLID)}",
    "collision_count_angular": f"WITH {_coded(CP)} {_knn(f'(SELECT * FROM pr WHERE {SAME} >= 2)', ANGLE)}",
    "collision_rounds": f"WITH {_rounds(_first_level([SAME.replace('a[i] = b[i]', f'floor(a[i] / {2**i}.0) = floor(b[i] / {2**i}.0)') + ' >= 6' for i in range(3)]), 3, _coded(RP))}",
    "collision_touched": f"WITH {_coded(RP)} SELECT qid, count(*) FILTER (WHERE {SAME} > 0)::BIGINT AS touched FROM pr GROUP BY qid",
    "query_aware_count": f"WITH {AWARE} {_knn(f'(SELECT * FROM pr WHERE {_near("a", "b", W / 2)} >= 6)', EUCLID)}",
    "query_aware_rounds": f"WITH {_rounds(_first_level([_near('a', 'b', 1.5**i / 2) + ' >= 6' for i in range(4)]), 4, AWARE)}",
    "query_aware_blocked": _blocked(),
    "projected_incremental": f"WITH {VISITS} {_knn('(SELECT * FROM pr WHERE place <= 100)', EUCLID)}",
    "projected_early_stop": _early(),
    "random_candidates": f"SELECT vec_id AS qid, least({K}, (SELECT count(*) FROM embeddings))::BIGINT AS n FROM embeddings WHERE vec_id % {EVERY} = 0",
    "recall_ratio": f"{HEAD} SELECT qid, round(recall, 6) AS recall, round(ratio, 6) AS ratio FROM ({PER_QUERY})",
    "result_sets": f"{HEAD} SELECT qid, obj_id, 'hit' AS side FROM truth SEMI JOIN found USING (qid, obj_id) UNION ALL SELECT qid, obj_id, 'missed' FROM truth ANTI JOIN found USING (qid, obj_id) UNION ALL SELECT qid, obj_id, 'wrong' FROM found ANTI JOIN truth USING (qid, obj_id)",
    "impact_of_m": _study("m", [(f"{m}::INT", _search(families.RandomProjection(D, m, W, seed=7))) for m in (2, 4, 8)]),
    "impact_of_probes": _study("probes", [("1::INT", _search()), (f"{M + 1}::INT", f"{_probed(M + 1)}, found AS ({_knn('cand', EUCLID, K, 12)}), truth AS ({_knn(ALL, EUCLID, K, 12)})")]),
    "impact_of_lambda": _study("lam", [(f"{lam}::INT", _search(lam=lam)) for lam in (10, 50, 200)]),
    "sensitivity_to_k": _study("k", [(f"{k}::INT", _search(k=k)) for k in (1, 5, 10, 20)]),
    "width_tuning": _study("width", [(f"{w}::DOUBLE", _search(of_width(w), rest=25)) for w in (1.0, 2.0, 4.0)]),
    "lambda_table": f"SELECT year, m, round(raw, 3) AS raw, least(n, greatest(1, ceil(raw)))::BIGINT AS lambda FROM (SELECT year, n, m, power(m, 1 - r) * n * power({1 - _P1!r}, -r) * {1 - _P2!r} * power(ln(2), r) / {_P2!r} AS raw FROM ({SIZES}) CROSS JOIN (SELECT unnest([8, 16, 64, 256, 512])::INT AS m, ln({_P2!r}) / ln({_P1!r}) AS r))",
    "alpha_table": f"""SELECT year, alpha, m, least(n, greatest(1, ceil(power(m, 1 - 1 / rho) * n * power(1 - p1, -1 / rho) * (1 - p2) * power(ln(2), 1 / rho) / p2)))::BIGINT AS lambda
      FROM (SELECT year, n, alpha, p1, p2, rho, greatest(1, round(power(n, alpha * rho)))::BIGINT AS m FROM ({SIZES}) CROSS JOIN (SELECT unnest([0.0, 0.5, 1.0])::DOUBLE AS alpha, 1 - 0.4 / pi() AS p1, 1 - 0.8 / pi() AS p2, ln(1 - 0.4 / pi()) / ln(1 - 0.8 / pi()) AS rho))""",
    "complexity_table": f"""SELECT year, method, round(alpha, 2) AS alpha, round(m, 2) AS m, round(lam, 2) AS lam, round(space / 1e6, 3) AS space, round(build_time / 1e6, 3) AS build_time, round(query_time / 1e6, 3) AS query_time FROM (SELECT year, n::DOUBLE AS n FROM ({SIZES})) s, LATERAL (
      SELECT 'static_concat' AS method, NULL::DOUBLE AS alpha, NULL::DOUBLE AS m, NULL::DOUBLE AS lam, power(n, 1.5) AS space, power(n, 1.5) * 64 * ln(n) AS build_time, power(n, 0.5) * (64 * ln(n) + 64) AS query_time
      UNION ALL SELECT 'collision_count', NULL, NULL, NULL, n * ln(n), n * ln(n) * (64 + ln(n)), n * ln(n)
      UNION ALL SELECT 'ring', 0.0, 1.0, n, n, n * (64 + ln(n)), n * 64
      UNION ALL SELECT 'ring', a, power(n, a * 0.5), power(n, 1 - a * 0.5), power(n, 1 + a * 0.5), power(n, 1 + a * 0.5) * (64 + ln(n)), power(n, a * 0.5) * (64 + ln(n)) + power(n, 1 - a * 0.5) * 64 FROM (VALUES (1.0), (2.0)) t(a)) c""",
    "cp_quality": f"WITH {_data()} SELECT qid, rnk, round(CASE WHEN dist < 2 THEN exp(-dist * dist / (4 - dist * dist) * ln({D})) ELSE 0 END, 6) AS p FROM ({_knn(ALL, EUCLID, K, 12)})",
    "run_distribution": f"""WITH {_coded(RP)}, tr AS ({_knn(ALL, EUCLID, K, 12)}), near AS (SELECT tr.rnk, run_len AS run, {SAME} AS same FROM tr JOIN rl ON rl.qid = tr.qid AND rl.obj_id = tr.obj_id),
      ps AS (SELECT rnk, sum(same)::DOUBLE / (count(*) * {M}) AS p FROM near GROUP BY rnk), obs AS (SELECT rnk, x, avg((run <= x)::INT) AS observed FROM near CROSS JOIN (SELECT unnest(range(0, {M + 1})) AS x) GROUP BY rnk, x),
      s AS (SELECT n, least({M}, list_max(list_transform(string_split(repeat(lpad(bin(n), {M}, '0'), 2), '0'), lambda x: length(x)))) AS run, bit_count(n::INT) AS ones FROM (SELECT unnest(range(0, {2**M})) AS n))
      SELECT obs.rnk, x::INT AS x, round(p, 6) AS p, round(observed, 6) AS observed, (SELECT round(sum(CASE WHEN run <= x THEN power(p, ones) * power(1 - p, {M} - ones) ELSE 0 END), 6) FROM s) AS exact, round(exp(-{M} * (1 - p) * power(p, x)), 6) AS lim FROM obs JOIN ps USING (rnk)""",
    "run_quantiles": """SELECT m, p, round(ln(ln(2) / (m * (1 - p))) / ln(p), 6) AS median, round(ln(-ln(0.9) / (m * (1 - p))) / ln(p), 6) AS q90, round(1 - exp(-m * (1 - p) * power(p, 3)), 6) AS near, round(exp(-m * (1 - p / 2) * power(p / 2, 3)), 6) AS far
      FROM (SELECT unnest([16, 64, 256])::INT AS m) CROSS JOIN (SELECT unnest([0.5, 0.8])::DOUBLE AS p)""",
    "concatenation": f"""SELECT year, k, tables, round(power(0.6, k), 6) AS prob, round(1 - power(1 - power(0.6, k), tables), 6) AS hit, (factorial(16) / (factorial(k) * factorial(16 - k)))::BIGINT AS combinations, round(n * (1 - power(0.95, k)), 3) AS touched
      FROM ({SIZES}) CROSS JOIN (SELECT unnest([1, 2, 4, 8])::INT AS k) CROSS JOIN (SELECT unnest([1, 8, 32])::INT AS tables)""",
    "static_plan": "SELECT n, ceil(ln(n) / ln(1 / 0.4))::INT AS k, ceil(power(n, ln(1 / 0.8) / ln(1 / 0.4)) / 0.8)::INT AS tables FROM (SELECT unnest([1000, 100000, 10000000])::BIGINT AS n)",
    "hash_cost": f"SELECT family, d, objects, round(objects * {M} * CASE family WHEN 'random_projection' THEN d WHEN 'cross_polytope' THEN d * log2(d) ELSE 1 END, 6)::DOUBLE AS cost FROM (SELECT len(embedding)::INT AS d, count(*)::BIGINT AS objects FROM embeddings WHERE embedding IS NOT NULL GROUP BY d) CROSS JOIN (SELECT unnest(['random_projection', 'cross_polytope', 'bit_sampling']) AS family)",
    "toy": f"SELECT id, {RUN} AS run_len, ({SAME})::INT AS equal, ((a[1:4] = b[1:4])::INT + (a[5:8] = b[5:8])::INT)::INT AS tables FROM (SELECT id, a, [3,1,4,1,5,9,2,6] AS b FROM (VALUES ('a', [3,1,7,2,8,9,2,6]), ('b', [3,8,4,1,5,0,2,7]), ('c', [0,1,4,5,8,3,2,0])) t(id, a))",
    "pareto": f"WITH {MEASURED_ROWS} SELECT method, level, min(seconds) AS verified, arg_min(params, struct_pack(s := seconds, p := params)) AS params FROM res JOIN (SELECT unnest({LEVELS})::DOUBLE AS level) ON recall >= level GROUP BY method, level",
    "budget_curve": f"WITH {_measured(every=1)} SELECT DISTINCT method, index_bytes::BIGINT AS index_bytes, min(seconds) OVER (PARTITION BY method ORDER BY index_bytes RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS least_verified FROM res WHERE recall >= {LEVELS[0]}",
    "summarize": f"WITH {RESULT_ROWS} SELECT method, params, round(avg(recall), 6) AS recall, round(avg(ratio), 6) AS ratio, round(avg(seconds), 6) AS seconds, count(*)::BIGINT AS runs FROM res GROUP BY method, params",
    "acceleration": f"WITH {MEASURED_ROWS}, b AS (SELECT method, min(seconds) AS s FROM res WHERE recall >= {LEVELS[0]} GROUP BY method) SELECT b.method, round((b.s / o.s - 1) * 100, 6) AS percent FROM b JOIN b o ON o.method = 'ring'",
    "rollup_report": f"WITH {MEASURED_ROWS} SELECT method, params, round(avg(recall), 6) AS recall, min(seconds) AS verified, grouping(method, params)::INT AS level FROM res GROUP BY ROLLUP (method, params)",
    "doc_hash_vectors": _hashed(f"SELECT doc_id AS id, {LOWERED} AS t FROM documents", 16),
    "page_hash_vectors": _hashed(f"SELECT id, {LOWERED} AS t FROM (SELECT page_id AS id, {STRIPPED} AS text FROM pages)", 16),
    "line_vectors": _standard("SELECT * FROM lineitem", ["l_quantity", "l_extendedprice", "l_discount", "l_tax"], ""),
    "word_shingles": f"SELECT id AS obj_id, len(v)::INT AS n, coalesce(list_sum(v), 0)::BIGINT AS total FROM ({_shingles('benchmark', 'item_id')})",
    "part_profiles": _standard(PARTS, ["qty", "price", "disc", "tax", "n", "ret", "fin", "qty_sd", *MONTHS]),
    "customer_profiles": _standard(CUSTOMERS, ["bal", "n", "avg_price", "max_price"]),
    "event_profiles": "SELECT user_id, strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*)::BIGINT AS n, round(avg(value), 6) AS avg_value FROM events GROUP BY user_id, date_trunc('day', ts)",
    "session_profiles": """WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM g)
      SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, strftime(max(ts) + INTERVAL 2 HOUR, '%Y-%m-%d %H:%M:%S') AS "end", count(*)::BIGINT AS n, round(avg(value), 6) AS avg_value FROM s GROUP BY user_id, no""",
    "event_props": "SELECT event_type, sum(k)::BIGINT AS total, count(k)::BIGINT AS n, round(avg(value), 6) AS mean FROM (SELECT *, regexp_extract(props, '\"k\": ([0-9]+)', 1)::BIGINT AS k FROM events) GROUP BY event_type",
    "as_of_join": "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts",
    "band_join": "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON abs(c_acctbal - s_acctbal) <= 20",
    "sql_surface": f"WITH {_coded(RP)} SELECT qid, max(run_len)::INT AS longest, sum({SAME})::BIGINT AS equal, {M}::BIGINT AS rots FROM rl GROUP BY qid",
    "kth_distance": f"WITH {_data()} SELECT qid, dist AS kth FROM ({_knn(ALL, EUCLID)}) WHERE rnk = {K}",
}
# The guarantee's candidates for the (R, c) decision, with R = 0.8 and c = 1.5, as the formula gives them.
_G1, _G2 = theory.rp_collision_prob(0.8, W), theory.rp_collision_prob(1.2, W)
_RHO = f"(ln({_G2!r}) / ln({_G1!r}))"
ORACLES["near_neighbor_theory"] = f"""WITH {_coded(RP)}, lam AS (SELECT least(n, greatest(1, ceil(power({M}, 1 - {_RHO}) * n * power({1 - _G1!r}, -{_RHO}) * {1 - _G2!r} * power(ln(2), {_RHO}) / {_G2!r}))) AS lam FROM (SELECT count(*) AS n FROM embeddings)),
  cand AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY run_len DESC, obj_id) AS place FROM rl) CROSS JOIN lam WHERE place <= lam), found AS ({_knn('cand', EUCLID, 1)})
  SELECT q.id AS qid, coalesce(f.obj_id, -1) AS obj_id, coalesce(f.dist, -1) AS dist FROM q LEFT JOIN (SELECT * FROM found WHERE dist <= 1.2000001) f ON f.qid = q.id"""
