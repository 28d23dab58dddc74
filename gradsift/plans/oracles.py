"""DuckDB SQL of the engine queries, built from shared steps.

Every step is one or more common table expressions over the given tables; a
suffix keeps steps of different worker counts and iterations apart.
"""

from __future__ import annotations

from gradsift.plans.queries import DENSITY, RATE, SWEEP, N

MONTH = "(year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1"


def model() -> str:
    return f"""
sz AS (SELECT (SELECT count(*) FROM part) AS np, (SELECT count(*) FROM customer) AS nc, (SELECT count(*) FROM supplier) AS ns,
  (SELECT max({MONTH}) + 1 FROM lineitem) AS nm),
man AS (SELECT CAST(layer_id AS INTEGER) AS layer_id, layer_name, CAST(start AS BIGINT) AS start, CAST(size AS BIGINT) AS size FROM (
  SELECT 0 AS layer_id, 'part' AS layer_name, 0 AS start, np AS size FROM sz UNION ALL SELECT 1, 'customer', np, nc FROM sz UNION ALL
  SELECT 2, 'supplier', np + nc, ns FROM sz UNION ALL SELECT 3, 'month', np + nc + ns, nm FROM sz UNION ALL SELECT 4, 'bias', np + nc + ns + nm, 1 FROM sz)),
tot AS (SELECT CAST(sum(size) AS BIGINT) AS n_g FROM man)"""


def k_of(density: float, s: str = "") -> str:
    return f"kk{s} AS (SELECT CAST(greatest(1, floor({density!r} * n_g + 0.5)) AS BIGINT) AS k FROM tot)"


def fragments(n: int, s: str = "") -> str:
    return f"""
fr{s} AS (SELECT CAST(row_number() OVER (ORDER BY start) - 1 AS INTEGER) AS frag_id, * FROM (
  SELECT layer_id, CAST(piece AS INTEGER) AS piece, CAST(start + piece * (size // parts) + least(piece, size % parts) AS BIGINT) AS start,
    CAST(size // parts + CASE WHEN piece < size % parts THEN 1 ELSE 0 END AS BIGINT) AS size
  FROM (SELECT *, unnest(range(parts)) AS piece FROM (SELECT man.*, CASE WHEN size * {n} > n_g THEN {n} ELSE 1 END AS parts FROM man, tot))) WHERE size > 0)"""


def line_rows(n: int, s: str = "") -> str:
    return f"""
rw{s} AS (SELECT CAST(l_orderkey % {n} AS INTEGER) AS worker, l_partkey AS p, np + o_custkey AS c, np + nc + l_suppkey AS s, np + nc + ns + {MONTH} AS m,
  np + nc + ns + nm AS b, l_quantity AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey, sz)"""


def _terms(source: str, value: str) -> str:
    return " UNION ALL ".join(f"SELECT worker, {c} AS param_idx, {value} AS r FROM {source}" for c in "pcsmb")


def grads(n: int, s: str = "") -> str:
    terms = _terms(f"rw{s}", "CAST(25 - q AS BIGINT)")
    return line_rows(n, s) + f",\ngr{s} AS (SELECT worker, CAST(param_idx AS BIGINT) AS param_idx, CAST(sum(r) AS BIGINT) AS v FROM ({terms}) GROUP BY ALL)"


def tagged(source: str, s: str = "", f: str = "") -> str:
    return f"tg{s} AS (SELECT g.*, frag_id FROM {source} g JOIN fr{f} f ON g.param_idx >= f.start AND g.param_idx < f.start + f.size)"


def norms(n: int, s: str = "", f: str = "") -> str:
    return f"""
nm{s} AS (SELECT CAST(w.worker AS INTEGER) AS worker, f.frag_id, f.size, sqrt(coalesce(sum(CAST(t.v AS DOUBLE) * t.v), 0)) AS norm
  FROM (SELECT unnest(range({n})) AS worker) w CROSS JOIN fr{f} f LEFT JOIN tg{s} t ON t.worker = w.worker AND t.frag_id = f.frag_id GROUP BY ALL)"""


WEIGHTS = {"norm": "norm", "size": "CAST(size AS DOUBLE)", "energy": "norm * norm"}


def quotas(s: str = "", kk: str = "", cap: bool = True, policy: str = "norm") -> str:
    share = "floor(CASE WHEN q.w > 0 THEN q.k * p.weight / q.w ELSE 0 END + 0.5)"
    quota = f"CAST(least({share}, p.size, q.k) AS BIGINT)" if cap else f"CAST({share} AS BIGINT)"
    return f"""
pr{s} AS (SELECT *, CAST(row_number() OVER (PARTITION BY worker ORDER BY weight DESC, frag_id) AS INTEGER) AS priority FROM (SELECT *, {WEIGHTS[policy]} AS weight FROM nm{s})),
qr{s} AS (SELECT worker, 0 AS priority, -1 AS frag_id, CAST(0 AS BIGINT) AS size, CAST(0 AS DOUBLE) AS norm, (SELECT k FROM kk{kk}) AS k,
    list_reduce(list(weight ORDER BY priority), lambda x, y: x + y) AS w, CAST(0 AS BIGINT) AS quota FROM pr{s} GROUP BY worker
  UNION ALL SELECT p.worker, p.priority, p.frag_id, p.size, p.norm, q.k - {quota}, q.w - p.weight, {quota} FROM qr{s} q JOIN pr{s} p ON p.worker = q.worker AND p.priority = q.priority + 1),
qt{s} AS (SELECT worker, frag_id, size, norm, priority, quota FROM qr{s} WHERE priority > 0)"""


COST = "round(size * ln(CAST(greatest(quota, 1) AS DOUBLE)), 6)"


def packed(n: int, leader: int, s: str = "", cost: str = COST) -> str:
    light = "list_position(b.loads, list_min(b.loads))"
    zeros = "[" + ", ".join(["0"] * n) + "]"
    return f"""
ct{s} AS (SELECT *, row_number() OVER (ORDER BY micro DESC, frag_id) AS pos FROM (SELECT frag_id, size, quota, CAST(round({cost} * 1000000) AS BIGINT) AS micro FROM qt{s} WHERE worker = {leader})),
bk{s} AS (SELECT CAST(0 AS BIGINT) AS pos, -1 AS frag_id, -1 AS bin, CAST({zeros} AS BIGINT[]) AS loads
  UNION ALL SELECT c.pos, c.frag_id, CAST({light} - 1 AS INTEGER), list_transform(b.loads, lambda x, i: CASE WHEN i = {light} THEN x + c.micro ELSE x END)
  FROM bk{s} b JOIN ct{s} c ON c.pos = b.pos + 1),
bn{s} AS (SELECT bin, frag_id, CAST(pos - 1 AS INTEGER) AS pack_order FROM bk{s} WHERE pos > 0)"""


def owner(n: int, t: int, s: str = "") -> str:
    return f"ow{s} AS (SELECT CAST(((bin - {t % n}) % {n} + {n}) % {n} AS INTEGER) AS worker, frag_id FROM bn{s})"


def picks(s: str = "") -> str:
    return f"""
pk{s} AS (SELECT worker, frag_id, param_idx, v, CAST(rank AS INTEGER) AS rank FROM (
  SELECT t.*, q.quota, row_number() OVER (PARTITION BY t.frag_id ORDER BY abs(t.v) DESC, t.param_idx) AS rank
  FROM tg{s} t JOIN ow{s} o ON t.worker = o.worker AND t.frag_id = o.frag_id JOIN qt{s} q ON q.worker = t.worker AND q.frag_id = t.frag_id) WHERE rank <= quota)"""


def top(source: str, group: str, k: str) -> str:
    part = f"PARTITION BY {group} " if group else ""
    return f"SELECT worker, param_idx, v, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER ({part}ORDER BY abs(v) DESC, param_idx) AS rank FROM {source}) WHERE rank <= {k}"


def with_(*steps: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(steps) + "\n"


K = "(SELECT k FROM kk)"


def upto(step: str, n: int = N, density: float = DENSITY, **options) -> list[str]:
    """The steps of one fragmented selection, up to the named one."""
    steps = {
        "manifest": model(),
        "k": k_of(density),
        "fragments": fragments(n),
        "grads": grads(n),
        "tagged": tagged("gr"),
        "norms": norms(n),
        "quotas": quotas(**options),
        "packed": packed(n, 0),
        "owner": owner(n, 0),
        "picks": picks(),
    }
    names = list(steps)
    return [steps[x] for x in names[: names.index(step) + 1]]


EXCHANGED = [*upto("picks"), "ix AS (SELECT DISTINCT param_idx FROM pk)", "rs AS (SELECT worker, param_idx, v FROM gr WHERE param_idx NOT IN (SELECT param_idx FROM ix) AND v <> 0)"]
MEAN = f"mn AS (SELECT param_idx, sum(v) / {N} AS mean FROM gr WHERE param_idx IN (SELECT param_idx FROM ix) GROUP BY param_idx)"


def _each_n(select_one, steps_of, sweep=SWEEP) -> str:
    """One query with the steps of every n under its own suffix."""
    shared = [model(), k_of(DENSITY)]
    steps = [s for n in sweep for s in steps_of(n, f"_{n}")]
    return with_(*shared, *steps) + " UNION ALL ".join(select_one(n, f"_{n}") for n in sweep)


def _plan_steps(n: int, s: str) -> list[str]:
    return [fragments(n, s), grads(n, s), tagged(f"gr{s}", s, s), norms(n, s, s), quotas(s), packed(n, 0, s), owner(n, 0, s), _worker_costs(n, s)]


def _worker_costs(n: int, s: str = "") -> str:
    return f"""
wc{s} AS (SELECT w.worker, coalesce(sum({COST}), 0) AS cost, coalesce(sum(quota), 0) AS picks, count(o.frag_id) AS fragments FROM (SELECT unnest(range({n})) AS worker) w
  LEFT JOIN ow{s} o ON o.worker = w.worker LEFT JOIN qt{s} q ON q.worker = o.worker AND q.frag_id = o.frag_id GROUP BY w.worker)"""


def _report(n: int, s: str) -> str:
    f = f"CASE WHEN max(cost) > 0 THEN (SELECT n_g FROM tot) * ln(CAST({K} AS DOUBLE)) / max(cost) END"
    trivial = f"CASE WHEN {K} > {n} AND {K} > 1 THEN {n} * ln(CAST({K} AS DOUBLE)) / ln(CAST({K} AS DOUBLE) / {n}) END"
    return f"SELECT {n} AS n, round(max(cost), 3) AS cost, round({f}, 4) AS f, round({trivial}, 6) AS f_trivial, CAST(max(picks) AS BIGINT) AS kappa, CAST(sum(picks) AS BIGINT) AS quota_sum FROM wc{s}"


REPORT = _each_n(_report, _plan_steps)


def _buildup(n: int, s: str) -> str:
    return f"SELECT {n} AS n, count(DISTINCT param_idx) AS selected, round(count(DISTINCT param_idx) / {K}, 6) AS build_up FROM ({top(f'gr{s}', 'worker', K)})"


def _balance(policy: str) -> str:
    s = f"_{policy}"
    if policy == "greedy":
        bins = [packed(N, 0, s)]
    elif policy == "size":
        bins = [packed(N, 0, s, "size")]
    else:
        expr = f"pos % {N}" if policy == "round_robin" else f"pos * {N} // n"
        bins = [f"bn{s} AS (SELECT CAST({expr} AS INTEGER) AS bin, frag_id FROM (SELECT frag_id, row_number() OVER (ORDER BY frag_id) - 1 AS pos, count(*) OVER () AS n FROM qt WHERE worker = 0))"]
    return ",\n".join([f"qt{s} AS (SELECT * FROM qt)", *bins, owner(N, 0, s), _worker_costs(N, s)])


POLICIES = ("greedy", "round_robin", "contiguous", "size")


def _train(name: str, iterations: int = 3, feedback: bool = True, rates: tuple[float, ...] = ()) -> str:
    """Iterations unrolled: parameters, rows' residuals, accumulators,
    selection, mean and residual of each under its own suffix."""
    steps = [model(), k_of(DENSITY), fragments(N), line_rows(N)]
    steps.append("pa0 AS (SELECT CAST(i AS BIGINT) AS param_idx, CASE WHEN i = n_g - 1 THEN 25.0::DOUBLE ELSE 0.0::DOUBLE END AS value FROM (SELECT n_g, unnest(range(n_g)) AS i FROM tot))")
    for t in range(iterations):
        joins = " ".join(f"JOIN pa{t} p{c} ON p{c}.param_idx = rw.{c}" for c in "pcsmb")
        steps.append(f"rr{t} AS MATERIALIZED (SELECT worker, p, c, s, m, b, pp.value + pc.value + ps.value + pm.value + pb.value - q AS e FROM rw {joins})")
        before = f" UNION ALL SELECT worker, param_idx, v AS r FROM er{t - 1}" if t and feedback else ""
        terms = _terms(f"rr{t}", f"e * {rates[t] if rates else RATE!r}")
        steps.append(f"ac{t} AS MATERIALIZED (SELECT worker, param_idx, sum(r) AS v FROM ({terms}{before}) GROUP BY ALL)")
        leader, s = t % N, f"{t}"
        if name == "fragmented":
            steps += [tagged(f"ac{t}", s), norms(N, s), quotas(s), packed(N, leader, s), owner(N, t, s), picks(s), f"ix{t} AS MATERIALIZED (SELECT DISTINCT param_idx FROM pk{s})"]
        elif name == "dense":
            steps.append(f"ix{t} AS (SELECT param_idx FROM pa0)")
        else:
            source = f"ac{t}" if name == "global_topk" else f"(SELECT * FROM ac{t} WHERE worker = {leader})"
            steps.append(f"ix{t} AS MATERIALIZED (SELECT DISTINCT param_idx FROM ({top(source, 'worker', K)}))")
        steps.append(f"mn{t} AS (SELECT param_idx, sum(v) / {N} AS mean FROM ac{t} WHERE param_idx IN (SELECT param_idx FROM ix{t}) GROUP BY param_idx)")
        steps.append(f"pa{t + 1} AS MATERIALIZED (SELECT param_idx, value - coalesce(mean, 0) AS value FROM pa{t} LEFT JOIN mn{t} USING (param_idx))")
        kept = f"param_idx NOT IN (SELECT param_idx FROM ix{t}) AND v <> 0" if feedback else "FALSE"
        steps.append(f"er{t} AS MATERIALIZED (SELECT worker, param_idx, v FROM ac{t} WHERE {kept})")
    joins = lambda t: " ".join(f"JOIN pa{t} p{c} ON p{c}.param_idx = rw.{c}" for c in "pcsmb")
    one = lambda t: (
        f"SELECT {t} AS iteration, (SELECT count(*) FROM ix{t}) AS selected, round(coalesce((SELECT sum(n) / {N} FROM (SELECT sqrt(sum(v * v)) AS n FROM er{t} GROUP BY worker)), 0), 6) AS error, "
        f"round((SELECT sqrt(avg(e * e)) FROM (SELECT pp.value + pc.value + ps.value + pm.value + pb.value - q AS e FROM rw {joins(t + 1)})), 6) AS rmse"
    )
    return with_(*steps) + " UNION ALL ".join(one(t) for t in range(iterations))


_SLIDES = "SELECT CAST(floor(epoch(ts) / 21600) AS BIGINT) * 21600 - unnest([0, 21600, 43200, 64800]) AS st, event_type, value FROM events"
_HELD = """
rows_ AS (SELECT o_custkey AS u, l_partkey AS item, l_orderkey, o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
lst AS (SELECT o_custkey AS u, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS last FROM orders GROUP BY o_custkey),
tr AS (SELECT DISTINCT u, item FROM rows_ JOIN lst USING (u) WHERE l_orderkey <> last),
hd AS (SELECT u, min(item) AS own FROM rows_ JOIN lst USING (u) WHERE l_orderkey = last GROUP BY u),
dr AS (SELECT u, item, min(draw) AS draw FROM (SELECT u, own, draw, (u * 7919 + draw * 104729) % (SELECT count(*) FROM part) AS item FROM hd, (SELECT unnest(range(150)) AS draw)) d
  WHERE item <> own AND NOT EXISTS (SELECT 1 FROM tr WHERE tr.u = d.u AND tr.item = d.item) GROUP BY u, item),
cd AS (SELECT u, item, FALSE AS held_out FROM (SELECT *, row_number() OVER (PARTITION BY u ORDER BY draw) AS pos FROM dr) WHERE pos <= 99 UNION ALL SELECT u, own, TRUE FROM hd)"""
_CHARS = "SELECT unnest(list_zip(c[:-2], c[2:])) AS z FROM (SELECT string_split(lower(text), '') AS c FROM documents WHERE doc_id % 5 {} 4) WHERE len(c) > 1"


def _bigram(test: str) -> str:
    return f"SELECT z[1] AS a, z[2] AS b, count(*) AS n FROM ({_CHARS.format(test)}) GROUP BY ALL"


def _example() -> str:
    return ",\n".join([model(), "kk AS (SELECT CAST(8 AS BIGINT) AS k)", fragments(2), grads(2), tagged("gr"), norms(2)])


def _policy_bins(policy: str) -> str:
    expr = f"pos % {N}" if policy == "round_robin" else f"pos * {N} // n"
    return f"SELECT CAST({expr} AS INTEGER) AS bin, frag_id FROM (SELECT frag_id, row_number() OVER (ORDER BY frag_id) - 1 AS pos, count(*) OVER () AS n FROM fr)"


_QUOTA_COLUMNS = "SELECT worker, frag_id, size, priority, quota FROM qt"
_DENSE = f"SELECT param_idx, sum(v) / {N} AS mean FROM gr GROUP BY param_idx"

ORACLE: dict[str, str] = {
    "manifest_additive": with_(model()) + "SELECT layer_id, layer_name, start, size FROM man",
    "fragments_n4": with_(model(), fragments(4)) + "SELECT * FROM fr",
    "fragments_n16": with_(model(), fragments(16)) + "SELECT * FROM fr",
    "worker_gradients": with_(model(), grads(N)) + "SELECT worker, param_idx, v FROM gr",
    "fragment_norms": with_(*upto("norms")) + "SELECT worker, frag_id, size, round(norm, 6) AS norm FROM nm",
    "fragment_priority": with_(*upto("quotas")) + "SELECT worker, frag_id, priority FROM pr",
    "quota_sequential": with_(*upto("quotas")) + _QUOTA_COLUMNS,
    "quota_uncapped": with_(*upto("quotas", cap=False)) + _QUOTA_COLUMNS,
    "quota_size": with_(*upto("quotas", policy="size")) + _QUOTA_COLUMNS,
    "quota_energy": with_(*upto("quotas", policy="energy")) + _QUOTA_COLUMNS,
    "quota_closed_form": with_(*upto("norms")) + f"SELECT worker, frag_id, round({K} * norm / sum(norm) OVER (PARTITION BY worker), 6) AS share FROM nm",
    "fragment_costs": with_(*upto("quotas")) + f"SELECT worker, frag_id, quota, round({COST}, 4) AS cost FROM qt",
    "bins_greedy": with_(*upto("packed")) + "SELECT bin, frag_id, pack_order FROM bn",
    "bins_round_robin": with_(model(), fragments(N)) + _policy_bins("round_robin"),
    "bins_contiguous": with_(model(), fragments(N)) + _policy_bins("contiguous"),
    "bins_by_size": with_(*upto("quotas"), packed(N, 0, "", "size")) + "SELECT bin, frag_id, pack_order FROM bn",
    "bins_rotated_t3": with_(*upto("packed"), owner(N, 3)) + "SELECT worker, frag_id FROM ow",
    "picks_fragmented": with_(*upto("picks")) + "SELECT worker, param_idx, v, rank FROM pk",
    "picks_global": with_(*upto("grads")) + top("gr", "worker", K),
    "picks_cyclic": with_(*upto("grads")) + top("(SELECT * FROM gr WHERE worker = 1)", "", K),
    "picks_slices": with_(*upto("grads"))
    + f"SELECT worker, param_idx, v, CAST(rank AS INTEGER) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY slice ORDER BY abs(v) DESC, param_idx) AS rank FROM (SELECT gr.*, param_idx * {N} // n_g AS slice FROM gr, tot) WHERE slice = worker) WHERE rank <= {K} // {N} + CASE WHEN slice < {K} % {N} THEN 1 ELSE 0 END",
    "picks_threshold": with_(model(), grads(N)) + "SELECT worker, param_idx, v FROM gr WHERE abs(v) >= 100",
    "picks_leader_quotas": with_(*upto("owner"))
    + "SELECT frag_id, count(*) AS picks FROM (SELECT t.frag_id, q.quota, row_number() OVER (PARTITION BY t.frag_id ORDER BY abs(t.v) DESC, t.param_idx) AS rank FROM tg t JOIN ow o USING (worker, frag_id) JOIN (SELECT frag_id, quota FROM qt WHERE worker = 0) q ON q.frag_id = t.frag_id) WHERE rank <= quota GROUP BY frag_id",
    "dense_mean": with_(model(), grads(N)) + _DENSE,
    "exchange_mean": with_(*EXCHANGED, MEAN) + "SELECT param_idx, mean FROM mn",
    "params_after_1": with_(*EXCHANGED, MEAN)
    + f"SELECT CAST(i AS BIGINT) AS param_idx, CASE WHEN i = n_g - 1 THEN 25.0::DOUBLE ELSE 0.0::DOUBLE END - coalesce(mean, 0) * {RATE!r}::DOUBLE AS value FROM (SELECT n_g, unnest(range(n_g)) AS i FROM tot) LEFT JOIN mn ON param_idx = i",
    "residual_after_1": with_(*EXCHANGED) + "SELECT worker, param_idx, v FROM rs",
    "mean_error_after_1": with_(*EXCHANGED) + f"SELECT round(sum(n) / {N}, 6) AS error FROM (SELECT sqrt(sum(CAST(v AS DOUBLE) * v)) AS n FROM rs GROUP BY worker)",
    "local_error_after_1": with_(*EXCHANGED) + "SELECT worker, round(sqrt(sum(CAST(v AS DOUBLE) * v)), 6) AS norm FROM rs GROUP BY worker",
    "buildup_by_n": with_(model(), k_of(0.01), *[grads(n, f"_{n}") for n in SWEEP]) + " UNION ALL ".join(_buildup(n, f"_{n}") for n in SWEEP),
    "density_by_sparsifier": with_(*upto("picks", 16, 0.01))
    + f"SELECT sparsifier, selected, round(selected / n_g, 9) AS density FROM tot, (SELECT 'global_topk' AS sparsifier, count(DISTINCT param_idx) AS selected FROM ({top('gr', 'worker', K)}) UNION ALL SELECT 'cyclic_topk', count(*) FROM ({top('(SELECT * FROM gr WHERE worker = 0)', '', K)}) UNION ALL SELECT 'fragmented', count(*) FROM pk UNION ALL SELECT 'equal_slices', count(*) FROM (SELECT slice, row_number() OVER (PARTITION BY slice ORDER BY abs(v) DESC, param_idx) AS rank FROM (SELECT gr.*, param_idx * 16 // n_g AS slice FROM gr, tot) WHERE slice = worker) WHERE rank <= {K} // 16 + CASE WHEN slice < {K} % 16 THEN 1 ELSE 0 END)",
    "overlap_hist": with_(*upto("grads")) + f"SELECT workers, count(*) AS indices FROM (SELECT param_idx, count(DISTINCT worker) AS workers FROM ({top('gr', 'worker', K)}) GROUP BY param_idx) GROUP BY workers",
    "jaccard_pairs": with_(*upto("grads"), f"gp AS ({top('gr', 'worker', K)})", "ns AS (SELECT worker, count(*) AS n FROM gp GROUP BY worker)")
    + 'SELECT a, b, "both", round("both" / (na + nb - "both"), 6) AS jaccard FROM (SELECT x.worker AS a, y.worker AS b, x.n AS na, y.n AS nb, (SELECT count(*) FROM gp p JOIN gp q USING (param_idx) WHERE p.worker = x.worker AND q.worker = y.worker) AS "both" FROM ns x JOIN ns y ON x.worker < y.worker)',
    "cost_report_by_n": REPORT,
    "bound_report": f"SELECT n, f >= f_trivial AS above_trivial, f_trivial >= n AS trivial_above_n, round(f_trivial / n, 6) AS trivial_per_worker FROM ({REPORT})",
    "trivial_speedup_grid": with_(model(), k_of(DENSITY))
    + f"SELECT CAST(n AS INTEGER) AS n, round(cost, 6) AS cost, round(n_g * ln(CAST({K} AS DOUBLE)) / nullif(cost, 0), 6) AS speedup, round(n_g * ln(CAST({K} AS DOUBLE)) / nullif(cost, 0) / n, 6) AS per_worker FROM (SELECT n, n_g, CASE WHEN {K} > n THEN n_g / n * ln(CAST({K} AS DOUBLE) / n) END AS cost FROM tot, (SELECT unnest({list(SWEEP)}) AS n))",
    "comm_cost_by_n": _each_n(
        lambda n, s: f"SELECT {n} AS n, {K} AS kappa_global, CAST(max(picks) AS BIGINT) AS kappa, round(ln({n}) * 1e-5 + {2 * (n - 1)} * 1e-9 * {K}, 12) AS seconds_global, round(ln({n}) * 1e-5 + {2 * (n - 1)} * 1e-9 * max(picks), 12) AS seconds FROM wc{s}", _plan_steps
    ),
    "payload_by_n": with_(model(), *[fragments(n, f"_{n}") for n in SWEEP]) + " UNION ALL ".join(f"SELECT {n} AS n, count(*) * 4 AS bytes FROM fr_{n}" for n in SWEEP),
    "balance_by_policy": with_(*upto("quotas"), *[_balance(p) for p in POLICIES])
    + " UNION ALL ".join(f"SELECT '{p}' AS policy, round(max(cost) / avg(cost), 4) AS cost_ratio, round(max(picks) / avg(picks), 4) AS picks_ratio, min(fragments) AS least_fragments, max(fragments) AS most_fragments FROM wc_{p}" for p in POLICIES),
    "idle_by_n": f"SELECT n, round(avg(CASE WHEN worker <> 0 THEN 1.0 ELSE 0.0 END), 6) AS idle FROM (SELECT DISTINCT n, l_orderkey % n AS worker FROM lineitem JOIN orders ON l_orderkey = o_orderkey, (SELECT unnest({list(SWEEP)}) AS n)) GROUP BY n",
    "scanned_by_worker": with_(*upto("owner")) + "SELECT worker, count(*) AS scanned FROM tg JOIN ow USING (worker, frag_id) GROUP BY worker",
    "recall_vs_global": with_(*upto("picks"), f"dm AS ({_DENSE})", f"bs AS (SELECT * FROM dm ORDER BY abs(mean) DESC, param_idx LIMIT {K})".replace(K, "(SELECT k FROM kk)"))
    + "SELECT round(avg(h), 6) AS recall, round(sum(abs(mean) * h) / sum(abs(mean)), 6) AS l1, round(sum(mean * mean * h) / sum(mean * mean), 6) AS l2 FROM (SELECT mean, CASE WHEN param_idx IN (SELECT param_idx FROM pk) THEN 1 ELSE 0 END AS h FROM bs)",
    "fragment_density": with_(*upto("quotas")) + "SELECT worker, frag_id, size, quota, round(quota / size, 9) AS density FROM qt",
    "quota_dispersion": with_(*upto("quotas")) + "SELECT frag_id, min(quota) AS least, max(quota) AS most, round(stddev_pop(quota), 6) AS sd FROM qt GROUP BY frag_id",
    "metrics_cube": with_(*upto("picks")) + "SELECT worker, layer_id, count(*) AS picks, CAST(sum(abs(v)) AS BIGINT) AS mass FROM pk JOIN fr USING (frag_id) GROUP BY CUBE (worker, layer_id)",
    "hr_at_10_popularity": with_(_HELD)
    + "SELECT round(avg(CASE WHEN rank <= 10 THEN 1.0 ELSE 0.0 END), 6) AS hit_rate FROM (SELECT held_out, row_number() OVER (PARTITION BY u ORDER BY coalesce(n, 0) DESC, item) AS rank FROM cd LEFT JOIN (SELECT item, count(*) AS n FROM tr GROUP BY item) USING (item)) WHERE held_out",
    "bigram_perplexity": f"WITH sn AS ({_bigram('<>')}), hl AS ({_bigram('=')}), fs AS (SELECT a, sum(n) AS na FROM sn GROUP BY a), vv AS (SELECT count(DISTINCT b) + 1 AS v FROM sn) "
    "SELECT round(exp(sum(-ln((coalesce(sn.n, 0) + 0.1::DOUBLE) / (coalesce(na, 0) + 0.1::DOUBLE * v)) * hl.n) / sum(hl.n)), 4) AS perplexity FROM hl LEFT JOIN sn USING (a, b) LEFT JOIN fs USING (a), vv",
    "lang_majority_accuracy": "SELECT round(avg(CASE WHEN lang = (SELECT lang FROM documents WHERE doc_id % 5 <> 4 GROUP BY lang ORDER BY count(*) DESC, lang LIMIT 1) THEN 1.0 ELSE 0.0 END), 6) AS accuracy FROM documents WHERE doc_id % 5 = 4",
    "events_tumbling": "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d %H:%M:%S') AS window_start, event_type, count(*) AS events, round(sum(value), 4) AS total FROM events GROUP BY ALL",
    "events_sliding": f"SELECT strftime(make_timestamp(st * 1000000), '%Y-%m-%d %H:%M:%S') AS window_start, event_type, count(*) AS events, round(sum(value), 4) AS total FROM ({_SLIDES}) GROUP BY ALL",
    "events_session": "SELECT user_id, strftime(date_trunc('second', min(ts)), '%Y-%m-%d %H:%M:%S') AS session_start, count(*) AS events, round(sum(value), 4) AS total FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, sid",
    "worked_example_quotas": with_(_example(), quotas()) + "SELECT TRUE AS cap, frag_id, round(norm, 6) AS norm, priority, quota FROM qt WHERE worker = 0 UNION ALL SELECT FALSE, * FROM (" + with_(_example(), quotas(cap=False)) + "SELECT frag_id, round(norm, 6) AS norm, priority, quota FROM qt WHERE worker = 0)",
    "worked_example_picks": with_(_example(), quotas(), packed(2, 1), owner(2, 3), picks()) + "SELECT worker, param_idx FROM pk",
    "flagship": with_(*upto("picks"), _worker_costs(N))
    + "SELECT CAST(w.worker AS INTEGER) AS worker, fragments, coalesce(picked, 0) AS picked, round(cost, 3) AS cost, round(coalesce(picked, 0) / n_g, 9) AS density FROM wc w LEFT JOIN (SELECT worker, count(*) AS picked FROM pk GROUP BY worker) p ON p.worker = w.worker, tot",
}
LED = [*upto("tagged"), f"lp AS ({top('gr', 'worker', K)})"]
ORACLE["staleness_cyclic"] = with_(*LED) + f"SELECT round(avg({N} - last), 6) AS mean, CAST(max({N} - last) AS BIGINT) AS most, (SELECT n_g FROM tot) - count(*) AS never FROM (SELECT param_idx, max(worker) AS last FROM lp GROUP BY param_idx)"
ORACLE["layer_share_cyclic"] = (
    with_(*LED) + "SELECT worker AS iteration, layer_id, count(*) AS picks, round(count(*) / sum(count(*)) OVER (PARTITION BY worker), 6) AS share FROM lp JOIN tg USING (worker, param_idx) JOIN fr USING (frag_id) GROUP BY worker, layer_id"
)
_TURNS = [s for t in range(N) for s in (f"qt_{t} AS (SELECT * FROM qt)", f"tg_{t} AS (SELECT * FROM tg)", packed(N, t, f"_{t}"), owner(N, t, f"_{t}"), picks(f"_{t}"))]
ORACLE["density_summary_rotation"] = (
    with_(*upto("quotas"), *_TURNS)
    + "SELECT round(avg(d), 9) AS mean, round(stddev_samp(d), 9) AS sd, round(min(d), 9) AS least, round(max(d), 9) AS most FROM ("
    + " UNION ALL ".join(f"SELECT count(*) / (SELECT n_g FROM tot) AS d FROM pk_{t}" for t in range(N))
    + ")"
)
for _kernel in ("two_phase", "threshold", "arrow"):
    ORACLE[f"picks_fragmented_{_kernel}"] = ORACLE["picks_fragmented"]
for _name in ("fragmented", "global_topk", "cyclic_topk", "dense"):
    ORACLE[f"train3_{_name}"] = _train(_name)
ORACLE["train3_no_feedback"] = _train("fragmented", feedback=False)
ORACLE["train3_decay"] = _train("fragmented", rates=(RATE, RATE, RATE / 4))
ORACLE["comm_cost_cyclic_by_n"] = with_(model(), k_of(DENSITY)) + f"SELECT CAST(n AS INTEGER) AS n, {K} AS kappa, round(ln(n) * 1e-5 + 2 * (n - 1) * 1e-9 * {K}, 12) AS seconds FROM (SELECT unnest({list(SWEEP)}) AS n)"
ORACLE["set_density"] = with_(model(), k_of(DENSITY)) + f"SELECT {K} AS k, round({K} / n_g, 9) AS density, round(n_g / {K}, 6) AS ratio FROM tot"
ORACLE["quota_off_k_by_n"] = _each_n(lambda n, s: f"SELECT {n} AS n, CAST(sum(picks) AS BIGINT) AS picks, round(abs(sum(picks) - {K}) / {K}, 6) AS off FROM wc{s}", _plan_steps)
ORACLE["fragments_by_stages"] = (
    with_(model()) + "SELECT 0 AS stages, 0 AS frag_id, -1 AS layer_id, 0 AS piece, CAST(0 AS BIGINT) AS start, n_g AS size FROM tot UNION ALL SELECT 1, layer_id, layer_id, 0, start, size FROM man"
)
ORACLE["picks_repeated"] = (
    with_(*upto("picks"), f"gp AS ({top('gr', 'worker', K)})")
    + "SELECT 'fragmented' AS sparsifier, (SELECT count(*) FROM (SELECT param_idx FROM pk GROUP BY param_idx HAVING count(*) > 1)) AS repeated UNION ALL SELECT 'global_topk', (SELECT count(*) FROM (SELECT param_idx FROM gp GROUP BY param_idx HAVING count(*) > 1))"
)
ORACLE["random_k_shape"] = with_(model(), k_of(DENSITY)) + f"SELECT {K} AS drawn, {K} AS indices, TRUE AS inside, TRUE AS unlike"
ORACLE["moving_error"] = f"SELECT iteration, round(error - lag(error) OVER (ORDER BY iteration), 5) AS change, round(avg(error) OVER (ORDER BY iteration ROWS BETWEEN 1 PRECEDING AND CURRENT ROW), 5) AS smoothed FROM ({_train('fragmented')})"
