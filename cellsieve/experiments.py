"""The experiments as registered queries (W1-W14): grids of data sets, constraints, qualities and kappas; samplers against each other; scale; pattern sets.

A grid cell mines its space, estimates its total, samples it SHARE times for each pattern, and is compared with as many draws of the ideal sampler.
Cells that DuckDB checks hash the same words; `W` holds what this module shares with the other registered queries.
"""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads as W
from .functions.lineage import cut
from .operators import baselines, blocks, cells, metrics, mining, patternsets, search, sharded
from .params import EstimateParams, epsilon
from .sources import encodings
from .sources.tables import load
from .spec import QUALITIES, Constraints, MiningTask, high_tilt

query = W.query
#: Encoding: minimum frequency, least length of closed sets, longest pattern that is looked for.
GRID = {"order_dims": (0.03, 2, 6), "customer_brands": (0.55, 2, 6), "embed_signs": (0.28, 1, 4), "userday_events": (0.1, 1, 4), "doc_words": (0.42, 2, 12)}
#: Samples for each pattern.
SHARE = 15
#: Quality whose total is many cells, so that constraints are really drawn: frequencies of few items to a row add up to less than one.
HEAVY = {"order_dims": "purity", "customer_brands": "freq", "embed_signs": "uniform", "userday_events": "purity", "doc_words": "freq"}
CLOSED_THETA = 0.4


# mining of any encoding --------------------------------------------------------------------------------------------------------------------


def mined(s: SparkSession, d: str, name: str, theta: float, longest: int) -> tuple[DataFrame, DataFrame, int]:
    """(frequent itemsets, transactions, their number) of an encoding; the itemsets, and the transactions as blocks of codes, are kept."""
    coded = blocks.coded(encodings.ENCODINGS[name](s, d))
    n = blocks.transactions(coded)
    return cut(mining.frequent_in(coded, Constraints(theta=theta).bound(n).minsup, longest)), blocks.decoded(coded), n


def mined_sql(name: str, theta: float, longest: int) -> str:
    """CTE pat(pattern, items, size, freq, freq_pos) by joining levels, with tx and lim before it."""
    out = f"""tx AS MATERIALIZED (SELECT row_number() OVER () AS tid, items AS whole, coalesce(label, false) AS label FROM ({encodings.SQL[name]})), lim AS (SELECT greatest(1, ceil({theta} * count(*) - 1e-9)) AS least FROM tx),
o0 AS MATERIALIZED (SELECT tid, label, unnest(string_split(whole, ',')) AS item FROM tx WHERE whole <> ''), f0 AS MATERIALIZED (SELECT item FROM o0 GROUP BY item HAVING count(*) >= (SELECT least FROM lim)),
one AS MATERIALIZED (SELECT tid, label, item FROM o0 SEMI JOIN f0 USING (item)), o1 AS MATERIALIZED (SELECT tid, label, item, [item] AS its FROM one)"""
    for k in range(1, longest + 1):
        out += f", p{k} AS MATERIALIZED (SELECT its, count(*) AS freq, sum(CAST(label AS INT)) AS pos FROM o{k} GROUP BY its HAVING count(*) >= (SELECT least FROM lim))"
        if k < longest:
            out += f", o{k + 1} AS MATERIALIZED (SELECT a.tid, a.label, b.item, list_append(a.its, b.item) AS its FROM (SELECT * FROM o{k} SEMI JOIN p{k} USING (its)) a JOIN one b ON a.tid = b.tid AND b.item > a.item)"
    every = " UNION ALL ".join(f"SELECT * FROM p{k}" for k in range(1, longest + 1))
    return f"{out}, pat AS MATERIALIZED (SELECT array_to_string(its, ',') AS pattern, its AS items, CAST(len(its) AS INTEGER) AS size, CAST(freq AS BIGINT) AS freq, CAST(pos AS BIGINT) AS freq_pos FROM ({every}))"


# closed and free sets where they differ from the frequent ones (K3, K6, K8)
DOC = mined_sql("doc_words", CLOSED_THETA, 12)
query("closed_doc_words", f"WITH {DOC}, {W.CLOSED} SELECT {W.COLUMNS} FROM clo")(lambda s, d: W.show(mining.closed_itemsets(mined(s, d, "doc_words", CLOSED_THETA, 12)[0])))
query("fcl_doc_words", f"WITH {DOC}, {W.CLOSED} SELECT {W.COLUMNS} FROM clo WHERE size >= 3")(lambda s, d: W.show(mining.constrained(mined(s, d, "doc_words", CLOSED_THETA, 12)[0], Constraints(closed=True, min_len=3))))


@query("free_doc_words", f"WITH {DOC}, {W.FREE} SELECT {W.COLUMNS} FROM pat ANTI JOIN not_free USING (pattern) WHERE size > 1 OR freq < (SELECT count(*) FROM tx)")
def free_doc_words(s, d):
    p, _, n = mined(s, d, "doc_words", CLOSED_THETA, 12)
    return W.show(mining.free_generators(p, n))


# one closed set: all pages have the same tags
TAGS = "tg AS (SELECT items AS whole, coalesce(label, false) AS label FROM (" + encodings.SQL["page_tags"] + "))"


@query("closed_page_tags", f"WITH {TAGS} SELECT count(DISTINCT whole) AS transactions, CAST(1 AS BIGINT) AS closed, (SELECT any_value(whole) FROM tg) AS pattern FROM tg")
def closed_page_tags(s, d):
    """The generic oracle on the whole of saturated data: of all 2^n - 1 sets just one is closed."""
    data = search.collect_data(encodings.page_tags(s, d))
    got = search.ORACLES["generic"](data, Constraints(minsup=1, closed=True), QUALITIES["uniform"])
    found = got.solve([]).solutions
    return s.createDataFrame([(len(data.mult), len(found), got.names(found[0][0]))], "transactions bigint, closed bigint, pattern string")


query("generic_count_doc_words", f"WITH {DOC}, {W.CLOSED} SELECT count(*) AS patterns, CAST(sum(freq) AS BIGINT) AS weight FROM clo WHERE size >= 3")(
    lambda s, d: counted(s, "generic", vertical(encodings.doc_words(s, d), CLOSED_THETA), Constraints(theta=CLOSED_THETA, closed=True, min_len=3))
)


def vertical(tx: DataFrame, theta: float):
    """Data for the search oracles without infrequent items, which no constraint needs."""
    coded = blocks.coded(tx)
    return search.collect_blocks(coded, Constraints(theta=theta).bound(blocks.transactions(coded)).minsup)


def counted(s: SparkSession, oracle: str, data, c: Constraints) -> DataFrame:
    got = search.Sampler(s, data, MiningTask(c, QUALITIES["freq"]), oracle).count()
    return s.createDataFrame([(got["patterns"], got["weight"])], "patterns bigint, weight bigint")


LINE_THETA = 0.01
query("levelwise_line_attrs", f"WITH {mined_sql('line_attrs', LINE_THETA, 4)} SELECT {W.COLUMNS} FROM pat")(lambda s, d: W.show(mined(s, d, "line_attrs", LINE_THETA, 4)[0]))

# the grid (W1-W4) --------------------------------------------------------------------------------------------------------------------------


def bounds_of(quality: str, n_tx: int) -> cells.Scaled:
    scale = {"uniform": 1, "freq": n_tx, "purity": 1_000_000}[quality]
    least = {"uniform": 1, "freq": 1, "purity": 500_000}[quality]
    return cells.Scaled.of(scale, least, 1 if quality == "uniform" else 2 if quality == "purity" else n_tx)


def estimated(patterns: DataFrame, quality: str, bounds: cells.Scaled) -> float:
    return cells.estimate_runs(patterns, quality, bounds).agg(F.expr("percentile(estimate, 0.5)")).first()[0]


def cell(patterns: DataFrame, n_tx: int, quality: str, kappa: float, n: int) -> DataFrame:
    """js_gap of one grid cell."""
    bounds = bounds_of(quality, n_tx)
    ours = cells.sample(patterns, quality, bounds, estimated(patterns, quality, bounds), n, kappa)
    return metrics.js_gap(cells.target_distribution(patterns, quality), ours, baselines.ideal_sample(patterns, quality, n))


def divergences(patterns: DataFrame, n_tx: int, qualities: tuple[str, ...], kappas: tuple[float, ...], n: int) -> list[tuple[str, float, float, float, float]]:
    """(quality, kappa, ours, ideal, gap): js_gap of all grid cells of a space.  Its samples are drawn together, and ideal draws and totals don't depend on kappa."""
    asks = [(q, b, total, n, kappa) for q in qualities for b in (bounds_of(q, n_tx),) for total in (estimated(patterns, q, b),) for kappa in kappas]
    samples = cells.sample_many(patterns, asks).select("ask", "pattern")
    # the ideal draws of the k-th quality are asked for last
    for k, q in enumerate(qualities):
        samples = samples.unionByName(baselines.ideal_sample(patterns, q, n).select(F.lit(len(asks) + k).alias("ask"), "pattern"))
    of = [a[0] for a in asks] + list(qualities)
    targets = [cells.target_distribution(patterns, q).select(F.explode(F.lit([k for k, x in enumerate(of) if x == q])).alias("ask"), "pattern", "p") for q in qualities]
    js = {r["ask"]: r["js"] for r in metrics.js_divergences(functools.reduce(DataFrame.unionByName, targets), cut(samples)).collect()}
    ideal = {q: js[len(asks) + k] for k, q in enumerate(qualities)}
    return [(a[0], a[4], js[k], ideal[a[0]], round(js[k] - ideal[a[0]], 9)) for k, a in enumerate(asks)]


def bounded(patterns: DataFrame, closed: bool, min_len: int) -> DataFrame:
    return cut(mining.constrained(patterns, Constraints(closed=closed, min_len=min_len if closed else 1)))


def grid(s: SparkSession, d: str, names: tuple[str, ...], qualities: tuple[str, ...], kappas: tuple[float, ...], at: float | None = None) -> DataFrame:
    """(data, constraints, quality, kappa, patterns, samples, ours, ideal, gap, expected): divergences in bits; `expected` is what an exact sampler can be expected to reach."""
    rows = []
    for name in names:
        theta, min_len, longest = GRID[name]
        p, _, n_tx = mined(s, d, name, at or theta, longest)
        for label, closed in (("F", False), ("FCL", True)):
            space = bounded(p, closed, min_len)
            k = space.count()
            if not k:
                continue
            for q, kappa, *js in divergences(space, n_tx, qualities or (HEAVY[name],), kappas, SHARE * k):
                rows.append((name, label, q, kappa, k, SHARE * k, *js, round(metrics.js_expected(k, SHARE * k), 9)))
    return s.createDataFrame(rows, "data string, constraints string, quality string, kappa double, patterns bigint, samples bigint, ours double, ideal double, gap double, expected double")


query("grid_kappas")(lambda s, d: grid(s, d, ("order_dims",), ("uniform", "purity", "freq"), (0.1, 0.5, 0.9), W.THETA))
query("grid_datasets")(lambda s, d: grid(s, d, tuple(GRID), (), (0.9,)))
query("grid_unpivoted")(lambda s, d: grid(s, d, ("userday_events",), ("uniform", "freq"), (0.9,)).unpivot(["data", "constraints", "quality"], ["ours", "ideal"], "sampler", "js"))

#: Samples of the grid cells that SQL checks: a fixed number, so that the SQL can be written.
FIXED = 3000


def space_sql(name: str, closed: bool, quality: str, theta: float) -> tuple[str, str]:
    """(CTEs up to pa2, the weighted space; SQL of the quality's scale)."""
    _, min_len, longest = GRID[name]
    scale = {"uniform": "1", "freq": "(SELECT count(*) FROM tx)", "purity": "1000000"}[quality]
    return f"{mined_sql(name, theta, longest)}, {W.CLOSED}, base AS MATERIALIZED (SELECT * FROM {'clo' if closed else 'pat'} WHERE size >= {min_len if closed else 1}), pa2 AS MATERIALIZED (SELECT *, CAST({W.WEIGHT[quality]} AS BIGINT) AS w FROM base)", scale


def samples_sql(name: str, closed: bool, quality: str, theta: float, n: int, kappa: float) -> str:
    """The space, smp of the cell sampler over it, and pq."""
    space, scale = space_sql(name, closed, quality, theta)
    body = W.sample_sql(quality, 0.0, n, kappa)
    tail = body[body.index("it AS (SELECT DISTINCT") :].replace("FROM pat)", "FROM pa2)").replace("FROM pat ", "FROM pa2 ").replace(f"CAST({W.SCALE_SQL[quality]} AS DOUBLE)", f"CAST({scale} AS DOUBLE)")
    return f"{space}, {tail}, {W.PQ.replace('FROM pat', 'FROM pa2')}"


def cell_sql(name: str, closed: bool, quality: str, kappa: float = 0.9, n: int = FIXED, theta: float | None = None) -> str:
    ideal = W.ideal_sql(n).replace("smp AS", "ide AS").replace("FROM pat", "FROM pa2")
    pq2 = W.PQ.replace("FROM pat", "FROM pa2").replace("pq AS", "pqi AS").replace("smp", "ide")
    return f"WITH {samples_sql(name, closed, quality, theta or GRID[name][0], n, kappa)}, {ideal}, {pq2} SELECT ours, ideal, round(ours - ideal, 9) AS gap FROM (SELECT {W.JS} AS ours FROM pq), (SELECT {W.JS} AS ideal FROM pqi)"


def fixed_cell(s: SparkSession, d: str, name: str, closed: bool, quality: str, kappa: float = 0.9, n: int = FIXED, theta: float | None = None) -> DataFrame:
    at, min_len, longest = GRID[name]
    p, _, n_tx = mined(s, d, name, theta or at, longest)
    return cell(bounded(p, closed, min_len), n_tx, quality, kappa, n)


for _n, _q in HEAVY.items():
    for _l, _c in (("f", False), ("fcl", True)):
        query(f"js_{_n}_{_l}", cell_sql(_n, _c, _q))(lambda s, d, n=_n, c=_c, q=_q: fixed_cell(s, d, n, c, q))
for _k in (0.1, 0.5):  # a space of more than one cell of the least kappa
    query(f"js_order_dims_kappa{int(_k * 10)}", cell_sql("order_dims", False, "uniform", _k, 2 * FIXED, W.THETA))(lambda s, d, k=_k: fixed_cell(s, d, "order_dims", False, "uniform", k, 2 * FIXED, W.THETA))

# the cell sampler in detail (W2): frequencies of dense transactions ------------------------------------------------------------------------------

DETAIL_SAMPLES = 12_000
DETAIL = f"WITH {samples_sql('customer_brands', True, 'freq', GRID['customer_brands'][0], DETAIL_SAMPLES, 0.9)}"


def detail(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    """(space, its target and empirical probabilities)."""
    theta, min_len, longest = GRID["customer_brands"]
    p, _, n_tx = mined(s, d, "customer_brands", theta, longest)
    space, bounds = bounded(p, True, min_len), cells.Scaled.of(n_tx, 1, n_tx)
    total = cells.estimate_runs(space, "freq", bounds).agg(F.expr("percentile(estimate, 0.5)")).first()[0]
    return space, metrics.compared(cells.target_distribution(space, "freq"), cells.sample(space, "freq", bounds, total, DETAIL_SAMPLES, 0.9))


EPS = f"{epsilon(0.9)}::DOUBLE"
query("factor2_share", f"{DETAIL} SELECT round(avg(CAST(q * 2 >= p AND q <= p * 2 AS DOUBLE)), 9) AS share FROM pq WHERE p > 0")(lambda s, d: metrics.share_within_factor(detail(s, d)[1]))
query("guarantee_check", f"{DETAIL} SELECT count(*) AS judged, count_if(NOT (q * (1 + {EPS}) >= p AND q <= p * (1 + {EPS}))) AS outside FROM pq WHERE p * {DETAIL_SAMPLES} >= 20")(lambda s, d: metrics.check_guarantee(detail(s, d)[1], epsilon(0.9), DETAIL_SAMPLES, 20))
query("band_by_target", f"{DETAIL} SELECT freq, count(*) AS n, round(avg(p), 12) AS target, round(avg(q), 12) AS mean, round(quantile_cont(q, 0.05), 12) AS low, round(quantile_cont(q, 0.95), 12) AS high FROM pa2 JOIN pq USING (pattern) GROUP BY freq")(
    lambda s, d: (lambda space, pq: metrics.band_by_target(space, pq))(*detail(s, d))
)

# samplers against each other (W5, W6) -----------------------------------------------------------------------------------------------------


def versus(s: SparkSession, d: str, closed: bool) -> DataFrame:
    """(quality, sampler, js, candidates, rate): chains and two-step samplers against ideal draws and ours, with as many samples each, on orders."""
    theta, min_len, longest = GRID["order_dims"]
    p, tx, n_tx = mined(s, d, "order_dims", theta, longest)
    space = bounded(p, closed, min_len)
    n = SHARE * space.count()
    data = search.collect_data(tx)
    out = []

    def add(quality: str, sampler: str, samples: DataFrame, tried: int | None = None, kept: int | None = None) -> None:
        js = metrics.js_divergence(metrics.compared(cells.target_distribution(space, quality), samples)).first()["js"]
        out.append((quality, sampler, js, tried, round(kept / tried, 9) if tried else None))

    for quality in ("uniform", "freq"):
        got = cell(space, n_tx, quality, 0.9, n).first()
        out += [(quality, "cells", got["ours"], None, None), (quality, "ideal", got["ideal"], None, None)]
        t = MiningTask(Constraints(theta=theta, closed=closed, min_len=min_len if closed else 1), QUALITIES[quality])
        if quality == "uniform" and not closed:
            add(quality, "flip chain", baselines.chain_sample(s, data, t, "flip", n))
        add(quality, "lattice walk", baselines.chain_sample(s, data, t, "lattice", n))
        if closed:
            add(quality, "concept walk", baselines.chain_sample(s, data, t, "concept", n))
    for power in (1, 4):
        samples, kept, tried = baselines.two_step_until(tx, space, n, 400_000, power, 50_000)
        if kept:
            add("freq", f"two-step freq^{power}", samples, tried, kept)
        else:
            out.append(("freq", f"two-step freq^{power}", None, tried, 0.0))
    return s.createDataFrame(out, "quality string, sampler string, js double, candidates bigint, rate double")


query("versus_frequent")(lambda s, d: versus(s, d, False))
query("versus_closed")(lambda s, d: versus(s, d, True))
#: Wide, dense transactions, of which two-step candidates are hardly ever frequent: exact acceptance.
query("acceptance_brands", f"WITH {mined_sql('customer_brands', 0.55, 6)} SELECT CAST((SELECT sum(freq) FROM pat) AS BIGINT) AS valid, CAST(sum((CAST(1 AS BIGINT) << len(string_split(whole, ','))) - 1) AS BIGINT) AS every, round((SELECT sum(freq) FROM pat) / sum((CAST(1 AS BIGINT) << len(string_split(whole, ','))) - 1), 9) AS rate FROM tx")(
    lambda s, d: (lambda p, tx, n: baselines.acceptance_exact(tx, p))(*mined(s, d, "customer_brands", 0.55, 6))
)

# oracles by branches and blocks (M24, M25) ----------------------------------------------------------------------------------------------------

BRANCH_THETA, BRANCH_SAMPLES = 0.01, 300


def sharded_estimates(s: SparkSession, d: str) -> DataFrame:
    c = Constraints(minsup=W.minsup(s, d, BRANCH_THETA))
    return sharded.sharded_runs(cut(encodings.order_dims(s, d)), c, QUALITIES["freq"], W.scaled(s, d, "freq", BRANCH_THETA), EstimateParams(runs=W.RUNS))


query("sharded_runs", f"WITH {W.estimate_sql('freq', BRANCH_THETA)} SELECT * FROM est")(sharded_estimates)


@query("sharded_sample", f"WITH {W.sample_sql('freq', BRANCH_THETA, BRANCH_SAMPLES, 0.9)} SELECT * FROM smp")
def sharded_sample(s, d):
    """The same draws as the relational sampler's, made branch by branch."""
    tx, bounds = cut(encodings.order_dims(s, d)), W.scaled(s, d, "freq", BRANCH_THETA)
    c = Constraints(minsup=W.minsup(s, d, BRANCH_THETA))
    total = sharded.sharded_runs(tx, c, QUALITIES["freq"], bounds, EstimateParams(runs=W.RUNS)).agg(F.expr("percentile(estimate, 0.5)")).first()[0]
    return sharded.sharded_sample(tx, c, QUALITIES["freq"], bounds, total, BRANCH_SAMPLES, 0.9)


BLOCK_RULES = Constraints(theta=0.05, closed=True, must_not=("region=1",), max_sup=6000, min_len=1)


@query("block_cell", f"""WITH {W.cube_sql(0.05)}, {W.CLOSED} SELECT pattern, freq, freq_pos FROM clo WHERE NOT list_contains(items, 'region=1') AND freq <= 6000""")
def block_cell(s, d):
    """The whole space as one cell, by blocks, under constraints that only this and the generic oracle know."""
    tx = cut(encodings.order_dims(s, d))
    names = [r["item"] for r in mining.item_dictionary(tx).orderBy("rank").collect()]
    got = sharded.block_cell(tx, BLOCK_RULES, QUALITIES["freq"], 2, 0, 0, float("inf"))
    return s.createDataFrame([(",".join(sorted(names[j] for j in range(len(names)) if m >> j & 1)), f, p) for m, f, p, _ in got.solutions], "pattern string, freq bigint, freq_pos bigint")


# scale (W8, W14, C2-C5, C8) --------------------------------------------------------------------------------------------------------------------

SCALE = {"line_attrs": 0.01, "order_profile": 0.1, "customer_brands": 0.3, "order_parts": 0.0005}


def scale_timeline(s: SparkSession, d: str, name: str, oracle: str = "tidset", theta: float | None = None) -> DataFrame:
    """(data, kappa, batch, requested, drawn, ready_s, ms_per_sample, calls): pre-processing, then batches of 50 samples for each kappa, uniformly, all
    of them however long they take: a lower theta than that of SCALE makes spaces that take hours, as the published ones did."""
    theta = SCALE[name] if theta is None else theta
    data = vertical(encodings.ENCODINGS[name](s, d), theta)
    sampler = search.Sampler(s, data, MiningTask(Constraints(theta=theta), QUALITIES["uniform"]), oracle, s.sparkContext.defaultParallelism)
    rows = sampler.timeline(params=EstimateParams(stop="converged"))
    return s.createDataFrame([(name, *r) for r in rows], "data string, kappa double, batch int, requested int, drawn int, ready_s double, ms_per_sample double, calls bigint")


for _n in ("line_attrs", "customer_brands"):
    query(f"scale_{_n}")(lambda s, d, n=_n: scale_timeline(s, d, n))


@query("xor_memory")
def xor_memory(s, d):
    """(constraints, nodes, xor_bytes): what the XOR rows on the search stack need at most."""
    data = search.collect_data(encodings.order_dims(s, d))
    o = search.ORACLES["tidset"](data, Constraints(theta=W.THETA), QUALITIES["uniform"])
    rows = []
    for m in range(0, 12, 3):
        got = o.solve(search.xor_rows(data, 2, 0, m))
        rows.append((m, got.nodes, got.xor_bytes))
    return s.createDataFrame(rows, "constraints int, nodes bigint, xor_bytes bigint")


query("convergence_lines")(lambda s, d: convergence(s, d))


def convergence(s: SparkSession, d: str) -> DataFrame:
    """(seed, run, estimate, running_median, true_total) for three seeds on lines."""
    p, _, _ = mined(s, d, "line_attrs", LINE_THETA, 4)
    true, out = p.count(), None
    for seed in (1, 2, 3):
        t = metrics.estimate_trace(cells.estimate_runs(p, "uniform", cells.Scaled.of(1, 1, 1), EstimateParams(), seed)).select(F.lit(seed).alias("seed"), "run", "estimate", "running_median", F.lit(true).alias("true_total"))
        out = t if out is None else out.union(t)
    return out


@query("exchangeability_search")
def exchangeability_search(s, d):
    """Largest and mean range of an item's share among the parts of a batch, for the search sampler on lines."""
    data = search.collect_data(encodings.line_attrs(s, d))
    sampler = search.Sampler(s, data, MiningTask(Constraints(theta=LINE_THETA), QUALITIES["uniform"]), "tidset", s.sparkContext.defaultParallelism)
    got = cut(sampler.sample(sampler.estimate().total, 400))
    return metrics.exchangeability_gap(cut(baselines.batches_of(got)), 50)


# high tilt (Q7, K9) ------------------------------------------------------------------------------------------------------------------------------


def tilted(s: SparkSession, d: str, name: str):
    o = encodings.order_dims(s, d)
    row = o.agg(F.count("*").alias("n"), F.sum(F.col("label").cast("bigint")).alias("p")).first()
    return high_tilt(name, row["n"], row["p"])


N, Q = "(SELECT count(*)::DOUBLE FROM e1)", "(SELECT avg(CAST(label AS DOUBLE)) FROM e1)"
HIGH = {
    "wracc": f"abs(freq_pos / {N} - freq / {N} * {Q})",
    "chi2": f"{N} * power(freq_pos / {N} - freq / {N} * {Q}, 2) / ({Q} * (1 - {Q}) * (freq / {N}) * (1 - freq / {N}))",
}
HIGH["gain"] = (lambda h: f"{h(Q)} - freq / {N} * {h('(freq_pos / freq)')} - ({N} - freq) / {N} * {h(f'(({N} * {Q} - freq_pos) / ({N} - freq))')}")(
    lambda v: f"(CASE WHEN {v} <= 0 OR {v} >= 1 THEN 0 ELSE -{v} * log2({v}) - (1 - {v}) * log2(1 - {v}) END)"
)
for _h in HIGH:
    # whole millionths may differ by one where the sum order of doubles differs, so tens of them are compared
    query(f"quality_{_h}", f"WITH {W.E1}, {W.PAT} SELECT pattern, CAST(floor((floor(greatest({HIGH[_h]}, 0) * 1000000 + 1e-6::DOUBLE) + 1e-3::DOUBLE) / 10) AS BIGINT) AS tens FROM pat")(
        lambda s, d, h=_h: W.frequent(s, d).select("pattern", F.floor((F.expr(tilted(s, d, h).spark) + 1e-3) / 10).cast("bigint").alias("tens"))
    )


@query("high_tilt_sample")
def high_tilt_sample(s, d):
    """Patterns as likely as their weighted relative accuracy: slices of a factor of two each, since the measure has no bound on its tilt."""
    return cells.sample_tilt_sliced(W.kept(s, d), tilted(s, d, "wracc"), 200, 0.9)


@query("between_sample", f"WITH {W.PAT}, r AS (SELECT * FROM pat WHERE freq * size BETWEEN 900 AND 1800) SELECT pattern, CAST(freq * size AS BIGINT) AS w FROM r")
def between_sample(s, d):
    """The space between two bounds of the area, the right tail of the frequencies (K9)."""
    return cells.weighted(mining.quality_between(W.frequent(s, d), "area", 900, 1800), "area").select("pattern", "w")


# pattern sets (W11, W12) ---------------------------------------------------------------------------------------------------------------------


#: CTEs til over big, the patterns whose pairs are asked for; covers meet where a transaction holds both.
MET = """one_tx AS MATERIALIZED (SELECT DISTINCT whole, string_split(whole, ',') AS its FROM tx), cov AS MATERIALIZED (SELECT whole, pattern FROM one_tx JOIN big ON list_has_all(its, items)),
ov AS MATERIALIZED (SELECT DISTINCT a.pattern AS p1, b.pattern AS p2 FROM cov a JOIN cov b USING (whole) WHERE a.pattern < b.pattern),
til AS (SELECT a.pattern AS p1, b.pattern AS p2, a.freq AS freq1, b.freq AS freq2, CAST(a.freq * a.size + b.freq * b.size AS BIGINT) AS area FROM big a JOIN big b ON a.pattern < b.pattern AND NOT list_has_any(a.items, b.items) ANTI JOIN ov ON ov.p1 = a.pattern AND ov.p2 = b.pattern)"""


@query("tilings_wide", f"WITH {mined_sql('customer_brands', 0.6, 4)}, big AS MATERIALIZED (SELECT * FROM pat), {MET} SELECT * FROM til")
def tilings_wide(s, d):
    """On dense, wide data covers always meet: no tiling, and no crash (W13); overlaps come from the transactions."""
    p, tx, _ = mined(s, d, "customer_brands", 0.6, 4)
    return patternsets.tilings(p, cut(patternsets.overlapping(p, tx)))


USER_THETA = 0.02


@query("tilings_events", f"WITH {mined_sql('userday_events', USER_THETA, 3)}, big AS MATERIALIZED (SELECT * FROM pat WHERE size >= 2), {MET} SELECT * FROM til")
def tilings_events(s, d):
    p, tx, _ = mined(s, d, "userday_events", USER_THETA, 3)
    p = cut(p.where("size >= 2"))
    return patternsets.tilings(p, cut(patternsets.overlapping(p, tx)))


@query("tiling_costs")
def tiling_costs(s, d):
    """(tilings, enumeration_s, estimate, estimation_s, ms_per_sample) of the orders' 2-tilings."""
    import time

    at = [time.perf_counter()]
    n = W.all_tilings(s, d).count()
    at.append(time.perf_counter())
    p, o = cut(W.fcl(s, d)), cut(W.occurring(s, d))
    c, base, params = float(W.ones(s, d)), patternsets.first_level(p.count()), EstimateParams()
    found = patternsets.tiling_estimate(patternsets.tiling_cells(p, o, cells.runs_table(s, params.runs * params.attempts), base, 5), base, W.estimation_pivot() * c, params)
    total = found.agg(F.expr("percentile(estimate, 0.5)")).first()[0] or 0.0
    at.append(time.perf_counter())
    ok = patternsets.tiling_sample(p, o, total, c, 100, 0.9, 6).where("status = 'ok'").count()
    at.append(time.perf_counter())
    return s.createDataFrame([(n, at[1] - at[0], total, at[2] - at[1], (at[3] - at[2]) * 10, ok)], "tilings bigint, enumeration_s double, estimate double, estimation_s double, ms_per_sample double, drawn bigint")


# the rest of the relational surface (O23, O25, O32, O33, O38, O40) --------------------------------------------------------------------------------


@query("distinct_transactions", f"WITH {W.E1} SELECT count(DISTINCT items) AS exact, true AS near FROM e1")
def distinct_transactions(s, d):
    """Distinct transactions exactly, and whether two sketches are within a tenth of that."""
    tx = encodings.joined(encodings.order_dims(s, d)).select("items")
    one = tx.agg(F.countDistinct("items").alias("exact"), F.approx_count_distinct("items", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("items", F.lit(14))).alias("b"))
    near = (F.abs(F.col("a") - F.col("exact")) <= F.col("exact") * 0.1) & (F.abs(F.col("b") - F.col("exact")) <= F.col("exact") * 0.1)
    return one.select("exact", near.alias("near"))


@query("sample_set_operations", f"WITH {W.weighted_sql('freq')}, {W.ideal_sql(400)}, a AS (SELECT pattern FROM smp WHERE sample_id < 200), b AS (SELECT pattern FROM smp WHERE sample_id >= 200) SELECT 'both' AS side, pattern FROM (SELECT pattern FROM a INTERSECT SELECT pattern FROM b) UNION ALL SELECT 'first', pattern FROM (SELECT pattern FROM a EXCEPT SELECT pattern FROM b) UNION ALL SELECT 'more', pattern FROM (SELECT pattern FROM a EXCEPT ALL SELECT pattern FROM b) UNION ALL SELECT 'common', pattern FROM (SELECT pattern FROM a INTERSECT ALL SELECT pattern FROM b)")
def sample_set_operations(s, d):
    """Two halves of a sample by set operations."""
    smp = cut(baselines.ideal_sample(W.frequent(s, d), "freq", 400))
    a, b = smp.where("sample_id < 200").select("pattern"), smp.where("sample_id >= 200").select("pattern")
    parts = {"both": a.intersect(b), "first": a.subtract(b), "more": a.exceptAll(b), "common": a.intersectAll(b)}
    out = None
    for side, df in parts.items():
        df = df.select(F.lit(side).alias("side"), "pattern")
        out = df if out is None else out.unionByName(df)
    return out


SUBQUERIES = """SELECT o.o_orderpriority AS priority, count(*) AS n, max(l.top) AS top FROM orders o, LATERAL (SELECT max(l_quantity) AS top FROM lineitem WHERE l_orderkey = o.o_orderkey) l
WHERE o.o_totalprice > (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem x WHERE x.l_orderkey = o.o_orderkey AND x.l_returnflag = 'R') AND o.o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0) GROUP BY o.o_orderpriority"""


@query("subqueries", SUBQUERIES)
def subqueries(s, d):
    """Scalar, EXISTS, IN and lateral subqueries (O40): Catalyst makes joins of them."""
    text = SUBQUERIES
    for t in ("orders", "lineitem", "customer"):
        text = text.replace(f"FROM {t}", f"FROM {{{t}}}")
    return s.sql(text, **{t: load(s, d, t) for t in ("orders", "lineitem", "customer")})


@query("attribute_maps", f"WITH {W.E1}, x AS (SELECT tid, unnest(string_split(items, ',')) AS i FROM e1) SELECT split_part(i, '=', 1) AS attribute, split_part(i, '=', 2) AS value, count(*) AS n FROM x GROUP BY ALL")
def attribute_maps(s, d):
    """Transactions as maps from attribute to value, and back to entries."""
    pairs = F.transform("items", lambda x: F.struct(F.substring_index(x, "=", 1).alias("key"), F.substring_index(x, "=", -1).alias("value")))
    maps = encodings.order_dims(s, d).select(F.map_from_entries(pairs).alias("m"))
    return maps.select(F.explode(F.map_entries("m")).alias("e")).groupBy(F.col("e.key").alias("attribute"), F.col("e.value").alias("value")).agg(F.count("*").alias("n"))


@query("events_near", "SELECT a.event_id AS first_id, b.event_id AS second_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE WHERE a.event_type <> b.event_type")
def events_near(s, d):
    """Pairs of a user's events within half an hour (O23): an equi-join on user and half-hour slot, of which a pair meets in one or the next."""
    e = load(s, d, "events").select("event_id", "user_id", "event_type", "ts", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_800_000_000).alias("slot"))
    b = e.select(F.col("event_id").alias("id2"), "user_id", F.col("event_type").alias("type2"), F.col("ts").alias("ts2"), F.explode(F.array(F.col("slot"), F.col("slot") - 1)).alias("slot"))
    return e.join(b, ["user_id", "slot"]).where("ts2 > ts AND ts2 <= ts + INTERVAL 30 MINUTE AND event_type != type2").select(F.col("event_id").alias("first_id"), F.col("id2").alias("second_id"))


@query("stratified_sample")
def stratified_sample(s, d):
    """A tenth of the patterns of each size, and half of the long ones."""
    return W.frequent(s, d).sampleBy("size", {1: 1.0, 2: 0.1, 3: 0.1, 4: 0.5}, 7).select("pattern", "size")
