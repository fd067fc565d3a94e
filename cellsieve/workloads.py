"""The registered queries of the sampler, each with the SQL that DuckDB checks it by.

Unless a name says otherwise: encoding E1 (orders with six attributes), minimum frequency THETA, all frequent itemsets.  Draws are functions of MD5 hashes, so even
estimates and samples can be recomputed in SQL.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.hashing import draw_sql, share_sql, trailing_zeros_sql, unit_sql
from .functions.lineage import cut
from .operators import baselines, cells, metrics, mining, patternsets, search, sharded
from .params import EstimateParams, cell_range, epsilon, estimation_pivot, initial_xors
from .sources import encodings
from .sources.encodings import ORDER_ATTRIBUTES, ORDER_SQL
from .sources.tables import load
from .spec import QUALITIES, Constraints, MiningTask, high_tilt

THETA = 0.01
LOW_THETA = 0.002
KAPPA = 0.9
SAMPLES = 2000
RUNS = 17
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def minsup(spark: SparkSession, d: str, theta: float) -> int:
    return max(1, math.ceil(theta * load(spark, d, "orders").count() - 1e-9))


def frequent(spark: SparkSession, d: str, theta: float = THETA) -> DataFrame:
    return mining.frequent_cube(encodings.order_attributes(spark, d), ORDER_ATTRIBUTES, minsup(spark, d, theta))


def kept(spark: SparkSession, d: str, theta: float = THETA) -> DataFrame:
    """The same, mined once, for queries that read it several times."""
    return cut(frequent(spark, d, theta))


def occurring(spark: SparkSession, d: str) -> DataFrame:
    return mining.frequent_cube(encodings.order_attributes(spark, d), ORDER_ATTRIBUTES, 1)


ATTRS = ", ".join(ORDER_ATTRIBUTES)


def cube_sql(theta: float | None, name: str = "pat") -> str:
    least = f"(SELECT ceil({theta} * count(*) - 1e-9) FROM orders)" if theta else "1"
    return f"""{name} AS MATERIALIZED (SELECT concat_ws(',', {ATTRS}) AS pattern, list_filter([{ATTRS}], lambda x: x IS NOT NULL) AS items,
 CAST(len(list_filter([{ATTRS}], lambda x: x IS NOT NULL)) AS INTEGER) AS size, CAST(count(*) AS BIGINT) AS freq, CAST(sum(CAST(label AS INT)) AS BIGINT) AS freq_pos
 FROM ({ORDER_SQL}) GROUP BY CUBE ({ATTRS}) HAVING count(*) >= {least} AND concat_ws(',', {ATTRS}) <> '')"""


PAT = cube_sql(THETA)
#: pat without the patterns of which one with an item more has the same frequency.
CLOSED = """sub AS MATERIALIZED (SELECT DISTINCT array_to_string(list_filter(items, lambda x, i: i <> k), ',') AS pattern, freq FROM (SELECT items, freq, unnest(range(1, size + 1)) AS k FROM pat WHERE size > 1)),
clo AS MATERIALIZED (SELECT * FROM pat ANTI JOIN sub USING (pattern, freq))"""
COLUMNS = "pattern, size, freq, freq_pos"
WEIGHT = {"uniform": "1", "freq": "freq", "purity": "1000000 * greatest(freq_pos, freq - freq_pos) // freq", "area": "freq * size"}
SCALE_SQL = {"uniform": "1", "freq": "(SELECT count(*) FROM orders)", "purity": "1000000"}


def show(df: DataFrame) -> DataFrame:
    return df.select("pattern", "size", "freq", "freq_pos")


# encodings, dictionary, statistics ------------------------------------------------------------------------------------------------------

for _name in encodings.ENCODINGS:
    query(f"enc_{_name}", encodings.SQL[_name])(lambda s, d, n=_name: encodings.joined(encodings.ENCODINGS[n](s, d)))

E1 = f"e1 AS ({encodings.SQL['order_dims']})"
UNNEST = "SELECT unnest(string_split(items, ',')) AS item FROM e1"


@query("dataset_stats", f"""WITH {E1}, i AS ({UNNEST}) SELECT (SELECT count(*) FROM e1) AS transactions, (SELECT count(DISTINCT items) FROM e1) AS distinct_transactions,
 CAST((SELECT count(*) FROM i) AS BIGINT) AS ones, (SELECT count(DISTINCT item) FROM i) AS n_items, round((SELECT count(*) FROM i) / ((SELECT count(*) FROM e1) * (SELECT count(DISTINCT item) FROM i)), 6) AS density""")
def dataset_stats(s, d):
    return mining.dataset_stats(encodings.order_dims(s, d)).select("transactions", "distinct_transactions", "ones", "n_items", "density")


@query("item_dictionary", f"WITH {E1} SELECT item, count(*) AS freq, CAST(row_number() OVER (ORDER BY count(*), item) AS INTEGER) AS rank FROM ({UNNEST}) GROUP BY item")
def item_dictionary(s, d):
    return mining.item_dictionary(encodings.order_dims(s, d))


@query("condense", f"WITH {E1} SELECT items, count(*) AS mult, CAST(sum(CAST(label AS INT)) AS BIGINT) AS pos FROM e1 GROUP BY items")
def condense(s, d):
    return encodings.joined(mining.condense(encodings.order_dims(s, d)))


@query("one_hot_matrix", f"WITH r AS ({ORDER_SQL}) SELECT quart, {', '.join(f'CAST(count_if(region = {chr(39)}region={i}{chr(39)}) AS BIGINT) AS r{i}' for i in range(5))} FROM r GROUP BY quart")
def one_hot_matrix(s, d):
    p = encodings.order_attributes(s, d).groupBy("quart").pivot("region", [f"region={i}" for i in range(5)]).agg(F.count(F.lit(1)))
    return p.na.fill(0).select("quart", *[F.col(f"`region={i}`").alias(f"r{i}") for i in range(5)])


# mining -----------------------------------------------------------------------------------------------------------------------------------

query("frequent_cube", f"WITH {PAT} SELECT {COLUMNS} FROM pat")(lambda s, d: show(frequent(s, d)))
query("frequent_levelwise", f"WITH {PAT} SELECT {COLUMNS} FROM pat")(lambda s, d: show(mining.frequent_levelwise(encodings.order_dims(s, d), minsup(s, d, THETA), 6)))
query("frequent_fpgrowth", f"WITH {PAT} SELECT pattern, size, freq FROM pat")(lambda s, d: mining.frequent_fpgrowth(encodings.order_dims(s, d), minsup(s, d, THETA), load(s, d, "orders").count()))
query("closed_itemsets", f"WITH {PAT}, {CLOSED} SELECT {COLUMNS} FROM clo")(lambda s, d: show(mining.closed_itemsets(kept(s, d))))
query("maximal_itemsets", f"WITH {PAT} SELECT {COLUMNS} FROM pat p WHERE NOT EXISTS (SELECT 1 FROM pat q WHERE q.size = p.size + 1 AND list_has_all(q.items, p.items))")(lambda s, d: show(mining.maximal_itemsets(kept(s, d))))
FREE = """not_free AS MATERIALIZED (SELECT DISTINCT whole AS pattern FROM (SELECT pattern AS whole, freq, array_to_string(list_filter(items, lambda x, i: i <> k), ',') AS pattern FROM (SELECT pattern, items, freq, unnest(range(1, size + 1)) AS k FROM pat WHERE size > 1)) SEMI JOIN pat USING (pattern, freq))"""
query("free_generators", f"WITH {PAT}, {FREE} SELECT {COLUMNS} FROM pat ANTI JOIN not_free USING (pattern) WHERE size > 1 OR freq < (SELECT count(*) FROM orders)")(lambda s, d: show(mining.free_generators(kept(s, d), load(s, d, "orders").count())))
query("minlen_itemsets", f"WITH {PAT} SELECT {COLUMNS} FROM pat WHERE size >= 3")(lambda s, d: show(mining.constrained(frequent(s, d), Constraints(min_len=3))))
query("fcl_itemsets", f"WITH {PAT}, {CLOSED} SELECT {COLUMNS} FROM clo WHERE size >= 2")(lambda s, d: show(mining.constrained(kept(s, d), Constraints(closed=True, min_len=2))))
query("syntactic_itemsets", f"WITH {PAT} SELECT {COLUMNS} FROM pat WHERE list_contains(items, 'status=O') AND NOT list_contains(items, 'region=1') AND (NOT list_contains(items, 'seg=BUILDING') OR list_contains(items, 'quart=3')) AND size <= 4 AND freq <= 2000 AND freq_pos >= 50")(
    lambda s, d: show(mining.constrained(frequent(s, d), Constraints(must=("status=O",), must_not=("region=1",), implies=(("seg=BUILDING", "quart=3"),), max_len=4, max_sup=2000, min_pos=50, one_per_attribute=True)))
)
query("labelled_frequency", f"WITH {PAT} SELECT pattern, freq_pos, freq - freq_pos AS freq_neg FROM pat")(lambda s, d: frequent(s, d).select("pattern", "freq_pos", (F.col("freq") - F.col("freq_pos")).alias("freq_neg")))
query("support_lookup", f"WITH {PAT}, b AS (SELECT doc_id, list_distinct(list_filter(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}_]+'), lambda w: w <> '')) AS w FROM documents), k AS (SELECT unnest(['the', 'and', 'is', 'of']) AS a), p AS (SELECT x.a || ',' || y.a AS pattern, [x.a, y.a] AS items FROM k x, k y WHERE x.a < y.a) SELECT pattern, count_if(list_has_all(w, items)) AS support FROM p, b GROUP BY pattern")(
    lambda s, d: mining.support(
        s.createDataFrame([("and,is", ["and", "is"], 2), ("and,of", ["and", "of"], 2), ("and,the", ["and", "the"], 2), ("is,of", ["is", "of"], 2), ("is,the", ["is", "the"], 2), ("of,the", ["of", "the"], 2)], "pattern string, items array<string>, size int"),
        load(s, d, "documents").select(F.array_distinct(F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}_]+"), lambda w: w != "")).alias("items")),
    )
)
query("tidset_bitmaps", f"WITH {E1} SELECT item, CAST(count(*) AS BIGINT) AS ones FROM (SELECT tid, unnest(string_split(items, ',')) AS item FROM e1) GROUP BY item")(
    lambda s, d: mining.tidsets(encodings.order_dims(s, d)).groupBy("item").agg(F.sum(F.bitmap_count("bits")).alias("ones"))
)
query("topk_patterns", f"WITH {PAT} SELECT {COLUMNS}, CAST(freq * size AS BIGINT) AS quality FROM pat ORDER BY quality DESC, pattern LIMIT 50")(lambda s, d: mining.top_k(frequent(s, d), 50, "freq * size").select("pattern", "size", "freq", "freq_pos", "quality"))

# qualities --------------------------------------------------------------------------------------------------------------------------------

for _q in ("uniform", "freq", "purity", "area"):
    query(f"quality_{_q}", f"WITH {PAT} SELECT pattern, CAST({WEIGHT[_q]} AS BIGINT) AS w FROM pat")(lambda s, d, q=_q: cells.weighted(frequent(s, d), q).select("pattern", "w"))
query("tilt_observed", f"WITH {PAT} SELECT min(freq) AS w_min, max(freq) AS w_max, round(max(freq) / min(freq), 6) AS tilt FROM pat")(lambda s, d: cells.observed_tilt(frequent(s, d), "freq"))
query("target_distribution", f"WITH {PAT} SELECT pattern, round(freq / (SELECT sum(freq) FROM pat), 12) AS p FROM pat")(lambda s, d: cells.target_distribution(frequent(s, d), "freq").select("pattern", F.round("p", 12).alias("p")))
query("quality_between", f"WITH {PAT} SELECT pattern, freq FROM pat WHERE freq BETWEEN 200 AND 400")(lambda s, d: frequent(s, d).where(F.col("freq").between(200, 400)).select("pattern", "freq"))

# cells ------------------------------------------------------------------------------------------------------------------------------------


def depth_sql(seed: int, runs: int, source: str = "pat") -> str:
    """CTE dep(run, pattern, w, depth) of all runs and patterns."""
    return f"""it AS (SELECT DISTINCT unnest(items) AS item FROM {source}), wd AS (SELECT run, item, {draw_sql(seed, 'run', 'item')} AS word FROM range({runs}) t(run), it),
px AS MATERIALIZED (SELECT run, pattern, any_value(w) AS w, bit_xor(word) AS v FROM (SELECT pattern, w, unnest(items) AS item FROM {source}) x JOIN wd USING (item) GROUP BY run, pattern),
dep AS (SELECT run, pattern, w, least({trailing_zeros_sql(f"xor(v, {draw_sql(seed, 'run', chr(39) + 'parity' + chr(39))})")}, {cells.DEEPEST}) AS depth FROM px)"""


def weighted_sql(quality: str, theta: float = THETA) -> str:
    return f"{cube_sql(theta, 'base')}, pat AS (SELECT *, CAST({WEIGHT[quality]} AS BIGINT) AS w FROM base)"


query("xor_cells", f"WITH {weighted_sql('freq')}, {depth_sql(1, 4)} SELECT pattern, run, depth FROM dep")(lambda s, d: cells.with_depth(cells.weighted(frequent(s, d), "freq").select("pattern", "items", "w"), 4, 1).select("pattern", "run", "depth"))
query("nested_cells", f"""WITH {weighted_sql('freq')}, {depth_sql(1, 51)}, g AS (SELECT run, depth AS m, sum(w) AS w, count(*) AS n FROM dep GROUP BY 1, 2)
SELECT run, m, CAST(sum(w) OVER d AS BIGINT) AS cell_weight, CAST(sum(n) OVER d AS BIGINT) AS n_patterns FROM g WINDOW d AS (PARTITION BY run ORDER BY m DESC)""")(
    lambda s, d: cells.nested_cells(cells.weighted(frequent(s, d), "freq"), 51, 1)
)


def scaled(s: SparkSession, d: str, quality: str, theta: float = THETA) -> cells.Scaled:
    """Scale, tilt bound and least weight, from two counts; the least weight by the constraint's bound."""
    n, least = load(s, d, "orders").count(), minsup(s, d, theta)
    scale = {"uniform": 1, "freq": n, "purity": 1_000_000}[quality]
    tilt = {"uniform": 1, "freq": n / least, "purity": 2}[quality]
    return cells.Scaled.of(scale, {"uniform": 1, "freq": least, "purity": 500_000}[quality], tilt)


def estimate_sql(quality: str, theta: float) -> str:
    """CTE est(run, m, cell_weight, attempt, estimate)."""
    bound = f"{estimation_pivot()} * CAST({SCALE_SQL[quality]} AS DOUBLE)"
    return f"""{weighted_sql(quality, theta)}, {depth_sql(cells.ESTIMATE_SEED, RUNS * 3)}, g AS (SELECT run, depth AS m, sum(w) AS w FROM dep GROUP BY 1, 2),
cl AS (SELECT run, m, CAST(sum(w) OVER (PARTITION BY run ORDER BY m DESC) AS BIGINT) AS cw FROM g),
fr AS (SELECT *, lead(m) OVER (PARTITION BY run ORDER BY m DESC) AS bm, lead(cw) OVER (PARTITION BY run ORDER BY m DESC) AS bw FROM cl),
tr AS (SELECT run // 3 AS run, CAST(run % 3 AS INTEGER) AS attempt, CAST(coalesce(bm + 1, 0) AS INTEGER) AS m, cw AS cell_weight FROM fr WHERE cw <= {bound} AND (bw IS NULL OR bw > {bound})),
est AS (SELECT run, m, cell_weight, attempt, CAST(cell_weight AS DOUBLE) * power(2.0::DOUBLE, m) AS estimate FROM tr QUALIFY row_number() OVER (PARTITION BY run ORDER BY attempt) = 1)"""


def estimates(s: SparkSession, d: str, quality: str, theta: float) -> DataFrame:
    return cells.estimate_runs(frequent(s, d, theta), quality, scaled(s, d, quality, theta), EstimateParams(runs=RUNS))


query("estimate_runs", f"WITH {estimate_sql('freq', LOW_THETA)} SELECT * FROM est")(lambda s, d: estimates(s, d, "freq", LOW_THETA))
for _q, _t in (("uniform", THETA), ("freq", LOW_THETA), ("purity", THETA)):
    query(f"estimate_total_{_q}", f"WITH {estimate_sql(_q, _t)} SELECT quantile_cont(estimate, 0.5) AS median_estimate, min(m) AS least_xors, CAST((SELECT sum(w) FROM pat) AS BIGINT) AS true_total, round(abs(quantile_cont(estimate, 0.5) - (SELECT sum(w) FROM pat)) / (SELECT sum(w) FROM pat), 9) AS error FROM est")(
        lambda s, d, q=_q, t=_t: cells.estimate_total(estimates(s, d, q, t), frequent(s, d, t), q)
    )
query("estimate_trace", f"WITH {estimate_sql('uniform', LOW_THETA)} SELECT run, estimate, quantile_cont(estimate, 0.5) OVER (ORDER BY run ROWS UNBOUNDED PRECEDING) AS running_median FROM est")(lambda s, d: metrics.estimate_trace(estimates(s, d, "uniform", LOW_THETA)))


def pivots(kappa: float) -> str:
    return f"ceil(4.03 * power(1 + 1 / {kappa}::DOUBLE, 2))"


@query("cell_parameters", " UNION ALL ".join(f"SELECT {k}::DOUBLE AS kappa, CAST({pivots(k)} AS INTEGER) AS pivot, round({pivots(k)} / (sqrt(2) * (1 + {k}::DOUBLE)), 6) AS lo, round(1 + sqrt(2) * (1 + {k}::DOUBLE) * {pivots(k)}, 6) AS hi, round((1 + {k}::DOUBLE) * (2.36 + 0.51 / power(1 - {k}::DOUBLE, 2)) - 1, 6) AS epsilon" for k in (0.1, 0.5, 0.9)))
def cell_parameters(s, d):
    from .params import sampling_pivot

    return s.createDataFrame([(k, sampling_pivot(k), *(round(x, 6) for x in cell_range(k)), round(epsilon(k), 6)) for k in (0.1, 0.5, 0.9)], "kappa double, pivot int, lo double, hi double, epsilon double")


def xors_sql(kappa: float, total: str, scale: str) -> str:
    hi = cell_range(kappa)[1]
    return f"CASE WHEN {total} <= {hi} * {scale} THEN 0 ELSE greatest(0, CAST(ceil(log2({total} / {scale}) + log2(1.8::DOUBLE) - log2({pivots(kappa)})) AS INTEGER) - 3) END"


@query("initial_xor_count", f"WITH {estimate_sql('uniform', LOW_THETA)}, t AS (SELECT quantile_cont(estimate, 0.5) AS total FROM est) " + " UNION ALL ".join(f"SELECT {k}::DOUBLE AS kappa, CAST({xors_sql(k, 'total', '1')} AS INTEGER) AS n_xor FROM t" for k in (0.1, 0.5, 0.9)))
def initial_xor_count(s, d):
    total = estimates(s, d, "uniform", LOW_THETA).agg(F.expr("percentile(estimate, 0.5)")).first()[0]
    return s.createDataFrame([(k, initial_xors(total, k)) for k in (0.1, 0.5, 0.9)], "kappa double, n_xor int")


def sample_sql(quality: str, theta: float, n: int, kappa: float) -> str:
    """CTE smp(sample_id, status, pattern, n_xor, cell_weight, oracle_calls)."""
    scale = f"CAST({SCALE_SQL[quality]} AS DOUBLE)"
    lo, hi = cell_range(kappa)
    est = estimate_sql(quality, theta)
    deep = depth_sql(cells.SAMPLE_SEED, n).replace("it AS", "it2 AS").replace(", it)", ", it2)").replace("wd AS", "wd2 AS").replace("JOIN wd ", "JOIN wd2 ").replace("px AS MATERIALIZED", "px2 AS MATERIALIZED").replace("FROM px)", "FROM px2)").replace("dep AS", "dep2 AS")
    key = f"round(ln({unit_sql(draw_sql(cells.SAMPLE_SEED, chr(39) + 'pick' + chr(39), 'run', 'pattern'))}) / w, 12)"
    return f"""{est}, par AS (SELECT CAST({xors_sql(kappa, 'quantile_cont(estimate, 0.5)', scale)} AS INTEGER) AS start FROM est), {deep},
ea AS (SELECT run, least(depth - start, 3) AS level, sum(w) AS w, max({{'key': {key}, 'pattern': pattern}}) AS best FROM dep2, par WHERE depth >= start GROUP BY 1, 2),
ev AS (SELECT r.run, l.level, coalesce(w, 0) AS w, best FROM range({n}) r(run), range(4) l(level) LEFT JOIN ea ON ea.run = r.run AND ea.level = l.level),
ce AS (SELECT run, level, sum(w) OVER d AS cw, max(best) OVER d AS best FROM ev WINDOW d AS (PARTITION BY run ORDER BY level DESC)),
fi AS (SELECT * FROM ce WHERE cw <= {hi} * {scale} QUALIFY row_number() OVER (PARTITION BY run ORDER BY level) = 1),
smp AS (SELECT r.run AS sample_id, CASE WHEN level IS NULL THEN 'too_large' WHEN cw > 0 AND (cw >= {lo} * {scale} OR level + start = 0) THEN 'ok' ELSE 'too_small' END AS status,
 CASE WHEN cw > 0 AND (cw >= {lo} * {scale} OR level + start = 0) THEN best.pattern END AS pattern, CAST(start + coalesce(level, 3) AS INTEGER) AS n_xor, CAST(coalesce(cw, 0) AS BIGINT) AS cell_weight, CAST(coalesce(level, 3) + 1 AS INTEGER) AS oracle_calls
 FROM range({n}) r(run) CROSS JOIN par LEFT JOIN fi ON fi.run = r.run)"""


def drawn(s: SparkSession, d: str, quality: str, theta: float, n: int = SAMPLES, kappa: float = KAPPA) -> DataFrame:
    patterns = kept(s, d, theta)
    bounds = scaled(s, d, quality, theta)
    total = cells.estimate_runs(patterns, quality, bounds, EstimateParams(runs=RUNS)).agg(F.expr("percentile(estimate, 0.5)")).first()[0]
    return cells.sample(patterns, quality, bounds, total, n, kappa)


for _q, _t in (("uniform", THETA), ("freq", LOW_THETA), ("purity", THETA)):
    query(f"cell_sample_{_q}", f"WITH {sample_sql(_q, _t, SAMPLES, KAPPA)} SELECT * FROM smp")(lambda s, d, q=_q, t=_t: drawn(s, d, q, t))
query("success_rate", f"WITH {sample_sql('freq', LOW_THETA, SAMPLES, KAPPA)} SELECT status, count(*) AS n, round(count(*) / (SELECT count(*) FROM smp), 9) AS share FROM smp GROUP BY status")(lambda s, d: metrics.success_rate(drawn(s, d, "freq", LOW_THETA)))
query("sliced_sample")(lambda s, d: cells.sample_tilt_sliced(kept(s, d), "area", 200, KAPPA))

# baselines --------------------------------------------------------------------------------------------------------------------------------


def draw_from_sql(source: str, key: str, weight: str, draws: str, r: str, keep: str) -> str:
    return f"SELECT {keep} FROM (SELECT *, {share_sql(r, f"(SELECT CAST(sum({weight}) AS HUGEINT) FROM {source})")} AS r FROM {draws}) q JOIN (SELECT *, CAST(sum({weight}) OVER (ORDER BY md5({key}), {key}) AS BIGINT) AS stop FROM {source}) c ON q.r >= c.stop - c.{weight} AND q.r < c.stop"


def ideal_sql(n: int) -> str:
    return f"smp AS ({draw_from_sql('pat', 'pattern', 'w', f'(SELECT unnest(range({n})) AS sample_id)', draw_sql('2', chr(39) + 'ideal' + chr(39), 'sample_id'), 'sample_id, pattern')})"


query("ideal_sample", f"WITH {weighted_sql('freq')}, {ideal_sql(SAMPLES)} SELECT * FROM smp")(lambda s, d: baselines.ideal_sample(frequent(s, d), "freq", SAMPLES))

CON = "con AS (SELECT items AS t, string_split(items, ',') AS items, len(string_split(items, ',')) AS n, count(*) AS mult, CAST(count(*) * ((CAST(1 AS BIGINT) << len(string_split(items, ','))) - 1) AS BIGINT) AS w FROM e1 GROUP BY items)"
CANDIDATES = 20_000
TWO_STEP = f"""{E1}, {CON}, cd AS ({draw_from_sql('con', 't', 'w', f'(SELECT unnest(range({CANDIDATES})) AS candidate)', draw_sql('2', "'tx'", 'candidate'), f"candidate, items, {draw_sql('2', chr(39) + 'subset' + chr(39), 'candidate')} % ((CAST(1 AS BIGINT) << n) - 1) + 1 AS bits")}),
ts AS (SELECT candidate, array_to_string(list_filter(items, lambda x, i: ((bits >> CAST(i - 1 AS BIGINT)) & 1) = 1), ',') AS pattern FROM cd), tsa AS (SELECT candidate, pattern, pattern IN (SELECT pattern FROM pat) AS accepted FROM ts)"""
query("two_step_sample", f"WITH {PAT}, {TWO_STEP} SELECT * FROM tsa")(lambda s, d: baselines.two_step_sample(encodings.order_dims(s, d), frequent(s, d), CANDIDATES))
query("acceptance_rate", f"WITH {PAT}, {TWO_STEP} SELECT count(*) AS candidates, count_if(accepted) AS accepted, round(avg(CAST(accepted AS DOUBLE)), 9) AS rate FROM tsa")(lambda s, d: baselines.acceptance_rate(baselines.two_step_sample(encodings.order_dims(s, d), frequent(s, d), CANDIDATES)))
query("acceptance_exact", f"WITH {PAT}, {E1} SELECT CAST((SELECT sum(freq) FROM pat) AS BIGINT) AS valid, CAST(sum((CAST(1 AS BIGINT) << len(string_split(items, ','))) - 1) AS BIGINT) AS every, round((SELECT sum(freq) FROM pat) / sum((CAST(1 AS BIGINT) << len(string_split(items, ','))) - 1), 9) AS rate FROM e1")(
    lambda s, d: baselines.acceptance_exact(encodings.order_dims(s, d), frequent(s, d))
)
query("two_step_freq4")(lambda s, d: baselines.two_step_sample(encodings.order_dims(s, d), frequent(s, d), CANDIDATES, power=4))


def task(quality: str = "uniform", theta: float = THETA, closed: bool = False, min_len: int = 1) -> MiningTask:
    return MiningTask(Constraints(theta=theta, closed=closed, min_len=min_len), QUALITIES[quality], KAPPA)


def held(s: SparkSession, d: str):
    return search.collect_data(encodings.order_dims(s, d))


query("flip_chain")(lambda s, d: baselines.chain_sample(s, held(s, d), task(), "flip", 400))
query("lattice_walk")(lambda s, d: baselines.chain_sample(s, held(s, d), task("freq"), "lattice", 400))
query("concept_walk")(lambda s, d: baselines.chain_sample(s, held(s, d), task("freq", closed=True), "concept", 400))
SCAN = f"""ln AS (SELECT pattern, items, row_number() OVER (ORDER BY pattern) - 1 AS line FROM pat), dr AS (SELECT batch, k, {share_sql(draw_sql('2', "'scan'", 'batch', 'k'), '(SELECT count(*) FROM pat)')} AS line FROM range(20) b(batch), range(50) kk(k)),
ps AS (SELECT batch, CAST(row_number() OVER (PARTITION BY batch ORDER BY line, k) AS INTEGER) AS pos, line FROM dr), scn AS (SELECT batch, pos, CAST(line AS BIGINT) AS line, pattern, items FROM ps JOIN ln USING (line))"""
query("scan_sample", f"WITH {PAT}, {SCAN} SELECT batch, pos, line, pattern FROM scn")(lambda s, d: baselines.scan_sample(frequent(s, d), 20).select("batch", "pos", "line", "pattern"))
query("capabilities", "SELECT * FROM (VALUES ('flip chain','minimal','no','no','yes','no'),('lattice walk','yes','yes','no','depends','no'),('concept walk','monotone','yes','no','yes','no'),('two-step','no','no','yes','yes','no'),('cell sampler','generic oracle','yes','yes','tidset oracle','yes')) t(sampler, constraints, distributions, guarantees, efficiency, pattern_sets)")(
    lambda s, d: baselines.capabilities(s)
)

# measures ---------------------------------------------------------------------------------------------------------------------------------

PQ = "pq AS (SELECT coalesce(a.pattern, b.pattern) AS pattern, coalesce(p, 0) AS p, coalesce(q, 0) AS q FROM (SELECT pattern, w / (SELECT sum(w) FROM pat) AS p FROM pat) a FULL JOIN (SELECT pattern, count(*) / (SELECT count(*) FROM smp WHERE pattern IS NOT NULL) AS q FROM smp WHERE pattern IS NOT NULL GROUP BY pattern) b ON a.pattern = b.pattern)"
JS = "round((sum(CASE WHEN p > 0 THEN p * log2(p / ((p + q) / 2)) ELSE 0 END + CASE WHEN q > 0 THEN q * log2(q / ((p + q) / 2)) ELSE 0 END)) / 2, 9)"
KL = "round(sum(CASE WHEN q > 0 THEN q * log2(q / p) ELSE 0 END), 9)"
MEASURED = f"WITH {sample_sql('uniform', THETA, SAMPLES, KAPPA)}, {PQ}"
IDEAL = f"WITH {weighted_sql('freq')}, {ideal_sql(SAMPLES)}, {PQ}"


def measured(s: SparkSession, d: str) -> DataFrame:
    return metrics.compared(cells.target_distribution(frequent(s, d), "uniform"), drawn(s, d, "uniform", THETA))


def ideally(s: SparkSession, d: str) -> DataFrame:
    p = kept(s, d)
    return metrics.compared(cells.target_distribution(p, "freq"), baselines.ideal_sample(p, "freq", SAMPLES))


query("js_divergence", f"{MEASURED} SELECT {JS} AS js FROM pq")(lambda s, d: metrics.js_divergence(measured(s, d)))
query("js_divergence_ideal", f"{IDEAL} SELECT {JS} AS js FROM pq")(lambda s, d: metrics.js_divergence(ideally(s, d)))
query("kl_divergence", f"{MEASURED} SELECT {KL} AS kl FROM pq")(lambda s, d: metrics.kl_divergence(measured(s, d)))
BAT = "bat AS (SELECT sample_id // 50 AS batch, CAST(sample_id % 50 + 1 AS INTEGER) AS pos, string_split(pattern, ',') AS items FROM smp WHERE pattern IS NOT NULL)"


def gap_sql(source: str) -> str:
    return f"""n AS (SELECT (pos - 1) * 5 // 50 AS part, count(*) AS n_all FROM {source} GROUP BY 1), x AS (SELECT (pos - 1) * 5 // 50 AS part, unnest(items) AS item FROM {source}), h AS (SELECT part, item, count(*) AS c FROM x GROUP BY 1, 2),
sh AS (SELECT i.item, n.part, coalesce(c, 0) / n_all AS share FROM (SELECT DISTINCT item FROM x) i CROSS JOIN n LEFT JOIN h ON h.item = i.item AND h.part = n.part), gp AS (SELECT item, max(share) - min(share) AS gap FROM sh GROUP BY item)"""


query("exchangeability", f"WITH {PAT}, {SCAN} SELECT item, pos, round(count(*) / 20, 9) AS share FROM (SELECT batch, pos, unnest(items) AS item FROM scn) GROUP BY item, pos")(lambda s, d: metrics.exchangeability(baselines.scan_sample(frequent(s, d), 20)))
query("exchangeability_gap_scan", f"WITH {PAT}, {SCAN}, {gap_sql('scn')} SELECT round(max(gap), 9) AS largest_gap, round(avg(gap), 9) AS mean_gap FROM gp")(lambda s, d: metrics.exchangeability_gap(baselines.scan_sample(frequent(s, d), 20), 50))
query("exchangeability_gap_cells", f"WITH {sample_sql('uniform', THETA, 1000, KAPPA)}, {BAT}, {gap_sql('bat')} SELECT round(max(gap), 9) AS largest_gap, round(avg(gap), 9) AS mean_gap FROM gp")(
    lambda s, d: metrics.exchangeability_gap(baselines.batches_of(drawn(s, d, "uniform", THETA, 1000)), 50)
)
query("diversity", f"""WITH {sample_sql('purity', THETA, 300, KAPPA)}, c AS (SELECT pattern, string_split(pattern, ',') AS items, count(*) AS n FROM smp WHERE pattern IS NOT NULL GROUP BY pattern),
j AS (SELECT sum(CASE WHEN a.pattern = b.pattern THEN a.n * (a.n - 1) ELSE a.n * b.n END * len(list_intersect(a.items, b.items)) / (len(a.items) + len(b.items) - len(list_intersect(a.items, b.items)))) / sum(CASE WHEN a.pattern = b.pattern THEN a.n * (a.n - 1) ELSE a.n * b.n END) AS j FROM c a, c b)
SELECT CAST(sum(n) AS BIGINT) AS samples, round(count(*) / sum(n), 9) AS distinct_share, (SELECT count(DISTINCT i) FROM (SELECT unnest(items) AS i FROM c)) AS items_touched, (SELECT round(j, 9) FROM j) AS mean_jaccard FROM c""")(
    lambda s, d: metrics.diversity(cut(drawn(s, d, "purity", THETA, 300).where("pattern is not null").select("pattern", F.split("pattern", ",").alias("items"))))
)

# pattern sets -----------------------------------------------------------------------------------------------------------------------------

TILING_THETA = 0.02
FCL2 = f"{cube_sql(TILING_THETA)}, {CLOSED}, {cube_sql(None, 'occ')}, fcl AS (SELECT * FROM clo WHERE size >= 2)"
PAIR = "array_to_string(list_sort(list_distinct(list_concat(a.items, b.items))), ',')"
TILE = f"til AS (SELECT a.pattern AS p1, b.pattern AS p2, a.freq AS freq1, b.freq AS freq2, a.freq * a.size + b.freq * b.size AS area FROM fcl a JOIN fcl b ON a.pattern < b.pattern AND NOT list_has_any(a.items, b.items) ANTI JOIN occ ON {PAIR} = occ.pattern)"


def fcl(s: SparkSession, d: str, theta: float = TILING_THETA) -> DataFrame:
    return mining.constrained(frequent(s, d, theta), Constraints(closed=True, min_len=2))


def all_tilings(s: SparkSession, d: str) -> DataFrame:
    return patternsets.tilings(cut(fcl(s, d)), cut(occurring(s, d)))


query("tilings_enumerated", f"WITH {FCL2}, {TILE} SELECT * FROM til")(all_tilings)
query("area_percentiles", f"WITH {FCL2}, {TILE} SELECT count(*) AS n, min(area) AS least, {', '.join(f'round(quantile_cont(area, {q}), 6) AS {n}' for n, q in (('p01', 0.01), ('p25', 0.25), ('p50', 0.5), ('p75', 0.75), ('p99', 0.99)))}, max(area) AS most FROM til")(lambda s, d: metrics.value_percentiles(all_tilings(s, d), "area"))
TSIG = f"""run AS (SELECT unnest(range(6)) AS run), ti AS (SELECT DISTINCT unnest(items) AS item FROM fcl), tw AS (SELECT run, item, {draw_sql('3', 'run', '1', 'item')} AS w1, {draw_sql('3', 'run', '2', 'item')} AS w2 FROM run, ti),
sg AS (SELECT run, pattern, bit_xor(w1) AS s1, bit_xor(w2) AS s2 FROM (SELECT pattern, unnest(items) AS item FROM fcl) x JOIN tw USING (item) GROUP BY 1, 2),
tc AS (SELECT a.run, p1, p2, area, least({trailing_zeros_sql(f"xor(xor(a.s1, b.s2), {draw_sql('3', 'a.run', chr(39) + 'parity' + chr(39))})")}, {cells.DEEPEST}) AS depth FROM til JOIN sg a ON a.pattern = p1 JOIN sg b ON b.pattern = p2 AND a.run = b.run)"""
query("tiling_cells", f"WITH {FCL2}, {TILE}, {TSIG} SELECT run, p1, p2, area, depth FROM tc WHERE depth >= 8")(lambda s, d: patternsets.tiling_cells(fcl(s, d), occurring(s, d), cells.runs_table(s, 6), 8, 3).select("run", "p1", "p2", "area", "depth"))


def ones(s: SparkSession, d: str) -> int:
    return len(ORDER_ATTRIBUTES) * load(s, d, "orders").count()


@query("tiling_sample")
def tiling_sample(s, d, n: int = 200):
    """Tilings, as likely as their areas; the total by the median of 17 runs."""
    p, o = cut(fcl(s, d)), cut(occurring(s, d))
    c, base, params = float(ones(s, d)), patternsets.first_level(p.count()), EstimateParams(runs=RUNS)
    found = patternsets.tiling_estimate(patternsets.tiling_cells(p, o, cells.runs_table(s, params.runs * params.attempts), base, 5), base, estimation_pivot() * c, params)
    total = found.agg(F.expr("percentile(estimate, 0.5)")).first()[0] or 0.0
    return patternsets.tiling_sample(p, o, total, c, n, KAPPA, 6)


query("tiling_six")(lambda s, d: metrics.value_ranks(cut(all_tilings(s, d)), tiling_sample(s, d, 6).where("status = 'ok'"), "area"))
K3_THETA = 0.06
query("tilings_three", f"""WITH {cube_sql(K3_THETA)}, {CLOSED}, {cube_sql(None, 'occ')}, fcl AS MATERIALIZED (SELECT * FROM clo), til AS MATERIALIZED (SELECT a.pattern AS p1, b.pattern AS p2, a.freq * a.size AS a1, b.freq * b.size AS a2 FROM fcl a JOIN fcl b ON a.pattern < b.pattern AND NOT list_has_any(a.items, b.items) ANTI JOIN occ ON {PAIR} = occ.pattern)
SELECT x.p1, x.p2, y.p2 AS p3, CAST(x.a1 + x.a2 + y.a2 AS BIGINT) AS area FROM til x JOIN til y ON y.p1 = x.p2 JOIN til z ON z.p1 = x.p1 AND z.p2 = y.p2""")(
    lambda s, d: patternsets.k_tilings(cut(mining.constrained(frequent(s, d, K3_THETA), Constraints(closed=True))), cut(occurring(s, d)), 3)
)
# of lines: flag and status part them in a few ways
LINE_TX = "tx AS (SELECT row_number() OVER () AS tid, ['flag=' || l_returnflag, 'line=' || l_linestatus] AS its, false AS label FROM lineitem)"
query("conceptual_clusterings", f"""WITH {LINE_TX}, pat AS MATERIALIZED (SELECT array_to_string(items, ',') AS pattern, items, len(items) AS size, count(*) AS freq FROM (SELECT unnest([its, its[1:1], its[2:2]]) AS items FROM tx) GROUP BY items)
SELECT a.pattern AS p1, b.pattern AS p2, a.freq AS freq1, b.freq AS freq2, CAST(a.freq * a.size + b.freq * b.size AS BIGINT) AS area FROM pat a JOIN pat b ON a.pattern < b.pattern AND NOT list_has_any(a.items, b.items)
WHERE a.freq + b.freq = (SELECT count(*) FROM tx) AND NOT EXISTS (SELECT 1 FROM tx WHERE list_has_all(its, a.items) AND list_has_all(its, b.items))""")(lambda s, d: clusterings(s, d))


def clusterings(s: SparkSession, d: str) -> DataFrame:
    line = load(s, d, "lineitem").select(F.array(F.concat(F.lit("flag="), "l_returnflag"), F.concat(F.lit("line="), "l_linestatus")).alias("items"), F.lit(False).alias("label"))
    p = cut(mining.frequent_levelwise(line, 1, 2))
    return patternsets.conceptual_clusterings(patternsets.tilings(p, patternsets.overlapping(p, line)), line.count())


query("redescriptions", f"""WITH {cube_sql(0.05)}, {cube_sql(None, 'occ')} SELECT a.pattern AS p1, b.pattern AS p2, round(o.freq / (a.freq + b.freq - o.freq), 9) AS jaccard FROM pat a, pat b JOIN occ o ON o.pattern = {PAIR}
WHERE len(list_filter(a.items, lambda x: split_part(x, '=', 1) NOT IN ('pri', 'quart', 'status'))) = 0 AND len(list_filter(b.items, lambda x: split_part(x, '=', 1) IN ('pri', 'quart', 'status'))) = 0 AND o.freq / (a.freq + b.freq - o.freq) >= 0.12""")(
    lambda s, d: patternsets.redescriptions(kept(s, d, 0.05), occurring(s, d), ("pri", "quart", "status"), 0.12)
)
query("association_rules", f"""WITH {PAT}, h AS MATERIALIZED (SELECT freq, items[k] AS head, array_to_string(list_filter(items, lambda x, i: i <> k), ',') AS body FROM (SELECT items, freq, unnest(range(1, size + 1)) AS k FROM pat WHERE size > 1))
SELECT body, head, h.freq, round(h.freq / b.freq, 9) AS confidence FROM h JOIN pat b ON b.pattern = body WHERE h.freq >= 0.3 * b.freq""")(lambda s, d: patternsets.association_rules(kept(s, d), 0.3))
query("two_term_dnf", f"""WITH {cube_sql(0.05)}, {cube_sql(None, 'occ')}, x AS (SELECT a.pattern AS p1, b.pattern AS p2, a.freq + b.freq - coalesce(o.freq, 0) AS freq, a.freq_pos + b.freq_pos - coalesce(o.freq_pos, 0) AS freq_pos FROM pat a JOIN pat b ON a.pattern < b.pattern LEFT JOIN occ o ON o.pattern = {PAIR})
SELECT p1, p2, freq, freq_pos, round(greatest(freq_pos, freq - freq_pos) / freq, 9) AS purity FROM x""")(lambda s, d: patternsets.two_term_dnf(kept(s, d, 0.05), occurring(s, d)))

# search oracles ---------------------------------------------------------------------------------------------------------------------------


@query("tidset_count", f"WITH {PAT} SELECT count(*) AS patterns, CAST(sum(freq) AS BIGINT) AS weight FROM pat")
def tidset_count(s, d):
    got = search.Sampler(s, held(s, d), task("freq")).count()
    return s.createDataFrame([(got["patterns"], got["weight"])], "patterns bigint, weight bigint")


@query("generic_count_fcl", f"WITH {PAT}, {CLOSED} SELECT count(*) AS patterns, CAST(sum(freq) AS BIGINT) AS weight FROM clo WHERE size >= 2")
def generic_count_fcl(s, d):
    got = search.Sampler(s, held(s, d), task("freq", closed=True, min_len=2), "generic").count()
    return s.createDataFrame([(got["patterns"], got["weight"])], "patterns bigint, weight bigint")


def searched(s, d, quality: str, theta: float, oracle: str, n: int, **constraints) -> DataFrame:
    sampler = search.Sampler(s, held(s, d), task(quality, theta, **constraints), oracle)
    return sampler.sample(sampler.estimate(EstimateParams(runs=RUNS)).total, n)


query("tidset_sample")(lambda s, d: searched(s, d, "uniform", THETA, "tidset", 100))
query("generic_sample_fcl")(lambda s, d: searched(s, d, "purity", 0.02, "generic", 40, closed=True, min_len=2))


@query("search_cells", f"WITH {weighted_sql('freq')}, {depth_sql(2, 12)} SELECT run, pattern FROM dep WHERE depth >= 5")
def search_cells(s, d):
    """The cells of five constraints by the tidset oracle: the same as the relational sampler's."""
    import pandas as pd

    from .operators.oracles import TidsetOracle, xor_rows

    data, t = s.sparkContext.broadcast(held(s, d)), task("freq")

    def work(batches):
        o = TidsetOracle(data.value, t.constraints, t.quality)
        for b in batches:
            for r in b["id"]:
                got = [o.names(x[0]) for x in o.solve(xor_rows(o.data, 2, int(r), 5)).solutions]
                yield pd.DataFrame({"run": int(r), "pattern": got}).astype({"run": "int64", "pattern": "object"})

    return s.range(0, 12, 1, 12).mapInPandas(work, "run bigint, pattern string")


def window_rank(s: SparkSession, d: str) -> DataFrame:
    """Rank, quantile and neighbours of patterns by frequency inside their size."""
    w = Window.partitionBy("size").orderBy(F.desc("freq"), "pattern")
    return frequent(s, d).select(
        "pattern", F.row_number().over(w).alias("nth"), F.rank().over(Window.partitionBy("size").orderBy(F.desc("freq"))).alias("rank"), F.round(F.percent_rank().over(Window.partitionBy("size").orderBy("freq")), 9).alias("pr"),
        F.ntile(4).over(w).alias("quarter"), F.lag("freq").over(w).alias("before"), F.sum("freq").over(w.rowsBetween(-2, 0)).alias("last_three"),
    )


query("pattern_ranks", f"""WITH {PAT} SELECT pattern, CAST(row_number() OVER w AS INTEGER) AS nth, CAST(rank() OVER (PARTITION BY size ORDER BY freq DESC) AS INTEGER) AS rank, round(percent_rank() OVER (PARTITION BY size ORDER BY freq), 9) AS pr,
CAST(ntile(4) OVER w AS INTEGER) AS quarter, lag(freq) OVER w AS before, CAST(sum(freq) OVER (PARTITION BY size ORDER BY freq DESC, pattern ROWS 2 PRECEDING) AS BIGINT) AS last_three FROM pat WINDOW w AS (PARTITION BY size ORDER BY freq DESC, pattern)""")(window_rank)
query("patterns_by_size", f"WITH {PAT} SELECT size, CAST(count(*) AS BIGINT) AS n, CAST(sum(freq) AS BIGINT) AS freq FROM pat GROUP BY ROLLUP (size)")(lambda s, d: frequent(s, d).rollup("size").agg(F.count("*").alias("n"), F.sum("freq").alias("freq")))
query("sample_sets_compared", f"WITH {weighted_sql('freq')}, {ideal_sql(SAMPLES)}, a AS (SELECT DISTINCT pattern FROM smp) SELECT pattern, pattern IN (SELECT pattern FROM a) AS drawn FROM pat")(
    lambda s, d: frequent(s, d).select("pattern").join(baselines.ideal_sample(frequent(s, d), "freq", SAMPLES).select("pattern").distinct().withColumn("drawn", F.lit(True)), "pattern", "left").na.fill(False)
)
