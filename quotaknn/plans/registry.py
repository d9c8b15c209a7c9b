"""Named queries for checks and benchmarks: (spark, sf_dir) -> DataFrame, most with SQL for another engine."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from quotaknn.functions import cells as C
from quotaknn.functions import lsh, quota
from quotaknn.functions.distance import distance
from quotaknn.operators import baselines, graph, measures, retrieve
from quotaknn.operators import select as S
from quotaknn.operators.search import pool_of, search
from quotaknn.plans import oracle as O
from quotaknn.plans import workloads as W
from quotaknn.plans.index import build_index
from quotaknn.plans.lineage import cut
from quotaknn.sources.catalog import ATTRS, table, vector_relation

QUERIES: dict = {}
SQL: dict[str, str] = {}

N, K = 6, 6
#: Queries of a batch in the experiments.
BATCH = 20


def register(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _emb(spark: SparkSession, sf_dir: str, relation: str = "V_EMB") -> DataFrame:
    return cut(vector_relation(spark, sf_dir, relation), "vectors")


def _setup(spark: SparkSession, sf_dir: str, relation: str = "V_EMB", m: int = 3, n: int = N, k: int = K, **kw):
    vectors = _emb(spark, sf_dir, relation)
    attrs = ATTRS[relation][:m]
    index = build_index(vectors, attrs, **({"tables": 2} | kw))
    return index, *W.feasible_queries(vectors, attrs, n, k)


def _report(result) -> DataFrame:
    """query_id, status, total_dist, ids: an answer in one row."""
    ids = result.answer.groupBy("query_id").agg(F.concat_ws(",", F.transform(F.sort_array(F.collect_list("rec_id")), lambda x: x.cast("string"))).alias("ids"))
    return result.status.join(ids, "query_id", "left").select("query_id", "status", F.round("total_dist", 6).alias("total_dist"), "ids")


# distances -----------------------------------------------------------------------------------------------------------


def _pairs(metric: str, p: float = 2.0):
    def f(spark, sf_dir):
        v = _emb(spark, sf_dir).select("rec_id", "vec")
        one = v.where("rec_id = 7").select(F.col("vec").alias("q"))
        return v.join(F.broadcast(one)).select("rec_id", F.round(distance(metric, "vec", "q", p), 6).alias("dist"))

    return f


_ONE = f"with v as ({O.RELATION_SQL['V_EMB']}), one as (select vec as q from v where rec_id = 7) select rec_id, round({{}}, 6) as dist from v, one"
_ZIP = "list_sum(list_transform(list_zip(vec, q), lambda z: {}))"
register("dist_l2", _ONE.format("list_distance(vec, q)"))(_pairs("l2"))
register("dist_l1", _ONE.format(_ZIP.format("abs(z[1] - z[2])")))(_pairs("l1"))
register("dist_cosine", _ONE.format("1 - list_cosine_similarity(vec, q)"))(_pairs("cosine"))
register("dist_lp3", _ONE.format("pow(" + _ZIP.format("pow(abs(z[1] - z[2]), 3)") + ", 1.0 / 3)"))(_pairs("lp", 3))

# plain neighbours ----------------------------------------------------------------------------------------------------


def _knn(metric: str, predicate=None):
    def f(spark, sf_dir):
        index, q, _, x = _setup(spark, sf_dir, metric=metric)
        found = retrieve.knn(index, q, 10, predicate=predicate, exclude=x)
        return found.select("query_id", "rec_id", F.round("dist", 6).alias("dist"))

    return f


def _knn_sql(metric: str, where: str = "true") -> str:
    d = O.DISTANCE[metric].format(a="v.vec", b="q.qvec")
    return f"""with {O.base('V_EMB', ATTRS['V_EMB'], N, K)}
select query_id, rec_id, round(dist, 6) as dist from (select query_id, rec_id, dist, row_number() over (partition by query_id order by dist, rec_id) as rn
from (select q.query_id, v.rec_id, {d} as dist from q join v on v.rec_id <> q.src where {where})) where rn <= 10"""


register("knn_plain_l2", _knn_sql("l2"))(_knn("l2"))
register("knn_plain_cosine", _knn_sql("cosine"))(_knn("cosine"))


@register("knn_filtered", _knn_sql("l2", "v.status = 'F' and v.lang in ('en', 'de')"))
def knn_filtered(spark, sf_dir):
    return _knn("l2", (F.col("status") == "F") & F.col("lang").isin("en", "de"))(spark, sf_dir)


@register("knn_blocks", _knn_sql("l2"))
def knn_blocks(spark, sf_dir):
    """Plain neighbours by matrix products, each task keeping its own nearest."""
    index, q, _, x = _setup(spark, sf_dir)
    return retrieve.knn(index, q, 10, retrieve.exhaustive_blocks, exclude=x).select("query_id", "rec_id", F.round("dist", 6).alias("dist"))


# cells ---------------------------------------------------------------------------------------------------------------

_A5 = ATTRS["V_EMB5"]
_CODES = f"with v as ({O.RELATION_SQL['V_EMB5']}), {O.codes(_A5)} "
_Q3 = f"with {O.base('V_EMB', ATTRS['V_EMB'], N, K)}, {O.codes(ATTRS['V_EMB'])}, {O.query_codes(ATTRS['V_EMB'])} "
_CELLS = ", cells as (select cell_code, count(*) as n_cell from coded group by 1) "


@register("cell_dictionary", _CODES + "select attr, value, code, cast(width as integer) as width, cast(shift as integer) as shift, cast(mask as bigint) as mask from fields")
def cell_dictionary(spark, sf_dir):
    d = C.build_dictionary(vector_relation(spark, sf_dir, "V_EMB5"), _A5)
    return d.frame(spark).select("attr", "value", "code", "width", "shift", "mask")


@register("cell_codes", _CODES + "select rec_id, cell_code from coded")
def cell_codes(spark, sf_dir):
    v = vector_relation(spark, sf_dir, "V_EMB5")
    return v.select("rec_id", C.build_dictionary(v, _A5).cell_code().alias("cell_code"))


@register("cell_decode", f"select rec_id, {', '.join(_A5)} from ({O.RELATION_SQL['V_EMB5']})")
def cell_decode(spark, sf_dir):
    """Codes taken apart again: the identity."""
    v = vector_relation(spark, sf_dir, "V_EMB5")
    d = C.build_dictionary(v, _A5)
    return v.select("rec_id", d.decode(d.cell_code()).alias("x")).select("rec_id", "x.*")


@register("cell_sizes", _CODES + "select cell_code, count(*) as n_cell from coded group by 1")
def cell_sizes(spark, sf_dir):
    v = vector_relation(spark, sf_dir, "V_EMB5")
    return C.cell_stats(v, C.build_dictionary(v, _A5))


@register("cell_cube", f"select status, priority, lang, grouping(status, priority, lang) as level, count(*) as n from ({O.RELATION_SQL['V_EMB']}) group by cube (status, priority, lang)")
def cell_cube(spark, sf_dir):
    """Sizes of the cells of every subset of attributes, in one pass."""
    return vector_relation(spark, sf_dir, "V_EMB").cube("status", "priority", "lang").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"))


@register("query_codes", _Q3 + "select query_id, mask, qcode, k_cell from asked")
def query_codes(spark, sf_dir):
    index, _, u, _ = _setup(spark, sf_dir)
    return C.query_cells(u, index.dictionary)


@register("query_masks", _Q3 + "select distinct query_id, mask from asked")
def query_masks(spark, sf_dir):
    index, _, u, _ = _setup(spark, sf_dir)
    return C.query_mask(u, index.dictionary)


_MATCH = _Q3 + _CELLS + "select query_id, cell_code, n_cell, qcode, k_cell from cells, asked where xor(cell_code & mask, qcode) = 0"


@register("cell_match_equi", _MATCH)
def cell_match_equi(spark, sf_dir):
    index, _, u, _ = _setup(spark, sf_dir)
    return C.match_cells(index.cells, C.query_cells(u, index.dictionary)).drop("mask")


@register("cell_match_xor", _MATCH)
def cell_match_xor(spark, sf_dir):
    index, _, u, _ = _setup(spark, sf_dir)
    return C.match_cells_xor(index.cells, C.query_cells(u, index.dictionary)).drop("mask")


@register("cell_bitmaps", f"with v as ({O.RELATION_SQL['V_EMB']}), cells as (select distinct status, priority, lang from v), l as (select 'status' as attr, status as value from cells union all select 'priority', priority from cells union all select 'lang', lang from cells) select attr, value, count(*) as n_cells from l where value is not null group by all")
def cell_bitmaps(spark, sf_dir):
    """How many cells each value has, from the bitmaps of cells by value."""
    v = vector_relation(spark, sf_dir, "V_EMB")
    d = C.build_dictionary(v, ATTRS["V_EMB"])
    return C.value_bitmaps(C.cell_stats(v, d), d).groupBy("attr", "value").agg(F.sum(F.bitmap_count("bits")).alias("n_cells"))


# quotas --------------------------------------------------------------------------------------------------------------


@register("quota_validate", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, K)} select query_id, {K} as k, 3 as m, case when query_id % 3 = 1 then 'sums differ' when query_id % 3 = 2 then 'unknown value' end as reason from q")
def quota_validate(spark, sf_dir):
    """Every third query is broken in one way or another."""
    index, _, u, _ = _setup(spark, sf_dir)
    first = F.row_number().over(Window.partitionBy("query_id", "attr").orderBy("value")) == 1
    broken = u.withColumn("need", F.when(first & (F.col("query_id") % 3 == 1) & (F.col("attr") == "lang"), F.col("need") - 1).otherwise(F.col("need")))
    broken = broken.withColumn("value", F.when(first & (F.col("query_id") % 3 == 2) & (F.col("attr") == "lang"), "nowhere").otherwise(F.col("value")))
    return quota.validate(broken, index.dictionary)


@register("quota_route", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, K)} select query_id, 3 as m, 'multi' as variant from q")
def quota_route(spark, sf_dir):
    _, _, u, _ = _setup(spark, sf_dir)
    return quota.route(u)


@register("quota_from_population", f"""with v as ({O.RELATION_SQL['V_EMB']}), l as (select 'status' as attr, status as value from v union all select 'priority', priority from v), s as (select attr, value, count(*) as n from l group by all),
t as (select *, sum(n) over (partition by attr) as a from s), f as (select *, (n * 12) // a as low, (n * 12) % a as rest from t),
r as (select *, row_number() over (partition by attr order by rest desc, value) as rn, sum(low) over (partition by attr) as lows from f)
select attr, value, n, cast(low + case when rn <= 12 - lows then 1 else 0 end as integer) as need from r""")
def quota_from_population(spark, sf_dir):
    return quota.from_population(vector_relation(spark, sf_dir, "V_EMB"), ["status", "priority"], 12)


@register("feasible_queries", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, K)} select query_id, attr, value, need from quotas")
def feasible_queries(spark, sf_dir):
    return _setup(spark, sf_dir)[2]


@register("quick_feasibility", f"""with recursive {O.base('V_EMB', ATTRS['V_EMB'], N, K)}, {O.pool(ATTRS['V_EMB'])}, have as (select x.query_id, x.attr, x.value, x.need, count(r.rec_id) as n from nd x left join pool r on r.query_id = x.query_id and (r.p0 = x.pos or r.p1 = x.pos or r.p2 = x.pos) group by all)
select query_id, cast(count(*) filter (n < need) as integer) as short_values from have group by 1""")
def quick_feasibility(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir)
    found, _ = retrieve.exhaustive(index, q, cut(retrieve.cell_requests(index, u), "requests"), x)
    return quota.quick_infeasible(pool_of(index, found), u)


# hashing -------------------------------------------------------------------------------------------------------------

_FAMILY = {"pstable": lsh.Family("pstable", 64, 3, 2, 1.0), "sign": lsh.Family("sign", 64, 3, 3)}


def _keys(kind: str):
    def f(spark, sf_dir):
        v = _emb(spark, sf_dir).select("rec_id", "vec")
        return v.select("rec_id", F.posexplode(lsh.lsh_keys(_FAMILY[kind])(F.col("vec"))).alias("table_no", "bucket"))

    return f


def _keys_sql(kind: str, tail: str) -> str:
    return f"with v as ({O.RELATION_SQL['V_EMB']}), {O.projections(_FAMILY[kind])}, {O.keys(_FAMILY[kind], 'v', 'rec_id', 'vec')} {tail}"


register("lsh_keys_pstable", _keys_sql("pstable", "select rec_id, table_no, bucket from keys"))(_keys("pstable"))
register("lsh_keys_sign", _keys_sql("sign", "select rec_id, table_no, bucket from keys"))(_keys("sign"))


@register("lsh_bucket_stats", _keys_sql("pstable", ", b as (select table_no, bucket, count(*) as n from keys group by all) select table_no, count(*) as buckets, max(n) as largest, sum(n)::bigint as records from b group by 1"))
def lsh_bucket_stats(spark, sf_dir):
    b = _keys("pstable")(spark, sf_dir).groupBy("table_no", "bucket").agg(F.count(F.lit(1)).alias("n"))
    return b.groupBy("table_no").agg(F.count(F.lit(1)).alias("buckets"), F.max("n").alias("largest"), F.sum("n").alias("records"))


def _probe_cte(tables: int, cap: int | None) -> str:
    """CTEs up to `met`: what a query shares a bucket with in its cells, coarse groups, at most quota + extra of each."""
    family = lsh.Family("pstable", 64, tables, 2, 1.0)
    keep = f"where rn <= quota + {cap}" if cap is not None else ""
    return f"""{_Q3}{_CELLS.rstrip()}, {O.projections(family)}, {O.keys(family, 'v', 'rec_id', 'vec')}, {O.keys(family, 'q', 'query_id', 'qvec', 'qkeys')},
req as (select query_id, qcode as group_id, cell_code, k_cell as quota from cells, asked where xor(cell_code & mask, qcode) = 0),
met0 as (select r.query_id, r.group_id, k.rec_id, min(k.table_no) as first_, any_value(r.quota) as quota from req r join qkeys x using (query_id) join coded c using (cell_code) join keys k on k.rec_id = c.rec_id and k.table_no = x.table_no and k.bucket = x.bucket
  join q on q.query_id = r.query_id and q.src <> k.rec_id group by 1, 2, 3),
met as (select * from (select *, row_number() over (partition by query_id, group_id order by first_, rec_id) as rn from met0) {keep})"""


@register("lsh_probe", _probe_cte(4, 2) + " select query_id, group_id, rec_id from met")
def lsh_probe(spark, sf_dir):
    """delta is set so that few more than k_cell are inspected, which makes the bound bite."""
    index, q, u, x = _setup(spark, sf_dir, tables=4)
    requests = cut(retrieve.cell_requests(index, u), "requests")
    return retrieve.probe(index, q, requests, delta=4.0, exclude=x).select("query_id", "group_id", "rec_id")


_POOL_SQL = _probe_cte(4, 80) + f""", far as (select met.*, list_distance(v.vec, q.qvec) as dist from met join v using (rec_id) join q using (query_id)),
near as (select *, row_number() over (partition by query_id, group_id order by dist, rec_id) as r2 from far)"""


@register("lsh_pool", _POOL_SQL + " select query_id, rec_id, round(dist, 6) as dist from near where r2 <= quota")
def lsh_pool(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, tables=4)
    found, _ = retrieve.cell_lsh(index, q, cut(retrieve.cell_requests(index, u), "requests"), exclude=x)
    return found.select("query_id", "rec_id", F.round("dist", 6).alias("dist"))


@register("scanned_report", _POOL_SQL + " select q.query_id, count(distinct far.rec_id) as scanned, round(count(distinct far.rec_id) / (select count(*) from v), 6) as scanned_share from q left join far using (query_id) group by 1")
def scanned_report(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, tables=4)
    got = search(index, q, u, exclude=x)
    share = measures.scanned_share(got.status, index.vectors.count())
    return got.status.select("query_id", "scanned").join(share, "query_id").withColumn("scanned_share", F.round("scanned_share", 6))


_P1, _P2 = 0.34, 0.27
_RHO = math.log(1 / _P1) / math.log(1 / _P2)


@register("lsh_plan_cells", _CODES + f", cells as (select cell_code, count(*) as n from coded group by 1) select cell_code, greatest(1, cast(ceil(ln(n) / {math.log(1 / _P2)!r}) as integer)) as hashes, case when n <= 1 then 1 else cast(ceil(pow(n, {_RHO!r}) * {math.log(2 * 10 / 0.1)!r}) as integer) end as tables from cells")
def lsh_plan_cells(spark, sf_dir):
    v = vector_relation(spark, sf_dir, "V_EMB5")
    stats = C.cell_stats(v, C.build_dictionary(v, _A5))
    return stats.select("cell_code", lsh.plan_cells(F.col("n_cell"), _P1, _P2, 10, 0.1).alias("p")).select("cell_code", "p.*")


@register("inspect_budget", "select l_linenumber as k, cast(count(distinct l_quantity) as integer) as l, cast(l_linenumber + ceil(2 * count(distinct l_quantity) / 0.1::double) as integer) as budget from lineitem group by 1")
def inspect_budget(spark, sf_dir):
    """For each line number as many results as it says, in as many tables as its lines have quantities."""
    asked = table(spark, sf_dir, "lineitem").groupBy(F.col("l_linenumber").alias("k")).agg(F.count_distinct("l_quantity").cast("int").alias("l"))
    return asked.select("k", "l", lsh.inspect_budgets(F.col("k"), F.col("l"), 0.1).alias("budget"))


@register("success_bound", "select o_orderpriority as priority, cast(count(distinct (o_orderstatus, o_custkey % 25)) as integer) as n, least(1.0::double, greatest(0.0::double, 1 - count(distinct (o_orderstatus, o_custkey % 25)) * 0.01::double / 2)) as success from orders group by 1")
def success_bound(spark, sf_dir):
    """For each priority the bound over its cells of status and customer group."""
    cells = table(spark, sf_dir, "orders").groupBy(F.col("o_orderpriority").alias("priority")).agg(F.count_distinct("o_orderstatus", F.col("o_custkey") % 25).cast("int").alias("n"))
    return cells.select("priority", "n", lsh.overall_successes(F.col("n"), 0.01).alias("success"))


@register("collision_curve")
def collision_curve(spark, sf_dir):
    return measures.collision_curve(_emb(spark, sf_dir), lsh.Family("pstable", 64, 32, 4, 1.0))


@register("index_rows", f"select t.table_no, count(*) as rows_ from ({O.RELATION_SQL['V_EMB']}) v, (select unnest(range(16)) as table_no) t group by 1")
def index_rows(spark, sf_dir):
    """Each record once in each table, no more."""
    index = _setup(spark, sf_dir, tables=16)[0]
    return index.postings.groupBy(F.col("table_no").cast("long").alias("table_no")).agg(F.count(F.lit(1)).alias("rows_"))


# selection and whole methods -----------------------------------------------------------------------------------------


def _exact(m: int, k: int = K, relation: str = "V_EMB", **kw):
    def f(spark, sf_dir):
        index, q, u, x = _setup(spark, sf_dir, relation, m, k=k, compact=False)  # exact search reads no postings
        return _report(search(index, q, u, exclude=x, **({"retriever": "exact"} | kw)))

    return f


register("exhaustive_quota", O.truth("V_EMB", 3, N, 10))(_exact(3, 10))
register("select_single", O.truth("V_EMB", 1, N, K))(_exact(1))
register("select_pair", O.truth("V_EMB", 2, N, K))(_exact(2))
register("select_multi", O.truth("V_EMB", 3, N, K))(_exact(3, selector="multi", select_options={"method": "bnb"}))
register("select_multi_m1", O.truth("V_EMB", 1, N, K))(_exact(1, selector="multi", select_options={"method": "bnb"}))
register("select_multi_m2", O.truth("V_EMB", 2, N, K))(_exact(2, selector="multi", select_options={"method": "bnb"}))
register("select_cell_dp", O.truth("V_EMB", 3, N, K))(_exact(3, selector="multi", select_options={"method": "dp"}))
register("select_fine_pool", O.truth("V_EMB", 2, N, K))(_exact(2, scope="fine"))
register("exhaustive_blocks", O.truth("V_EMB", 3, N, K))(_exact(3, retriever="blocks"))
register("exhaustive_correlated", O.truth("V_COR", 3, N, K))(_exact(3, relation="V_COR"))


@register("exhaustive_four", O.truth("V_EMB5", 4, 4, 4))
def exhaustive_four(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, "V_EMB5", 4, 4, 4)
    return _report(search(index, q, u, exclude=x, retriever="exact"))


TABLES, DELTA = 16, 0.1
EXTRA = lsh.inspect_budget(0, TABLES, DELTA)


def _lsh_answer(m: int, tables: int = TABLES, extra: int | None = EXTRA, met: str | None = None) -> str:
    """SQL of the whole hash-based method: its own pool (at most need + extra met first, by table and record, of a coarse
    cell), then the same program over cells. `met` replaces which records are met, and in which table first."""
    attrs = ATTRS["V_EMB"][:m]
    family = lsh.Family("pstable", 64, tables, 2, 1.0)
    p = ", ".join(f"p{i}" for i in range(m))
    met = met or "select r.query_id, r.rec_id, min(k.table_no) as first_ from rel r join qkeys x using (query_id) join keys k on k.rec_id = r.rec_id and k.table_no = x.table_no and k.bucket = x.bucket group by 1, 2"
    bound = f"where rn <= kc + {extra}" if extra is not None else ""
    return f"""with recursive {O.base('V_EMB', attrs, N, K)}, {O.projections(family)}, {O.keys(family, 'v', 'rec_id', 'vec')}, {O.keys(family, 'q', 'query_id', 'qvec', 'qkeys')},
{O.pool(attrs).split('ranked as')[0]}
met0 as ({met}),
met as (select * from (select r.*, row_number() over (partition by query_id, {p} order by first_, rec_id) as rn from rel r join met0 using (query_id, rec_id)) {bound}),
ranked as (select *, row_number() over (partition by query_id, {p} order by dist, rec_id) as rk from met),
pool as (select *, dense_rank() over (partition by query_id order by {p}) as cell from ranked where rk <= kc),
{O.solve(attrs)} {O.ANSWERS}"""


def _lsh(m: int, tables: int = TABLES, options: dict | None = None, **kw):
    def f(spark, sf_dir):
        index, q, u, x = _setup(spark, sf_dir, m=m, tables=tables)
        return _report(search(index, q, u, exclude=x, options={"delta": DELTA} | (options or {}), **kw))

    return f


register("quota_knn_1", _lsh_answer(1))(_lsh(1))
register("quota_knn_2", _lsh_answer(2))(_lsh(2))
register("quota_knn_m", _lsh_answer(3))(_lsh(3, selector="multi", select_options={"method": "bnb"}))
register("quota_knn_few_tables", _lsh_answer(2, 4, 4))(_lsh(2, 4, {"delta": 2.0}))

_BESIDE = "select r.query_id, r.rec_id, min(k.table_no) as first_ from rel r join qkeys x using (query_id) join keys k on k.rec_id = r.rec_id and k.table_no = x.table_no and k.bucket between x.bucket - 1 and x.bucket + 1 group by 1, 2"
register("quota_knn_multi_probe", _lsh_answer(2, 4, None, _BESIDE))(_lsh(2, 4, {"cap": False, "probes": 2}))


_SMALL, _MET = 8, _probe_cte(4, None)
_SIZED = _MET + ", sized as (select cell_code, count(*) as n_cell from coded group by 1)"
_FAR = ", far as (select b.*, list_distance(v.vec, q.qvec) as dist from both_ b join v using (rec_id) join q using (query_id)), near as (select *, row_number() over (partition by query_id, group_id order by dist, rec_id) as r2 from far) select query_id, rec_id, round(dist, 6) as dist from near where r2 <= quota"


def _scans(**options):
    def f(spark, sf_dir):
        index, q, u, x = _setup(spark, sf_dir, tables=4)
        found, _ = retrieve.cell_lsh(index, q, cut(retrieve.cell_requests(index, u), "requests"), cap=False, exclude=x, **options)
        return found.select("query_id", "rec_id", F.round("dist", 6).alias("dist"))

    return f


register("lsh_scan_small_cells", _SIZED + f", both_ as (select query_id, group_id, rec_id, quota from met union select r.query_id, r.group_id, c.rec_id, r.quota from req r join sized s using (cell_code) join coded c using (cell_code) join q on q.query_id = r.query_id and q.src <> c.rec_id where s.n_cell <= {_SMALL})" + _FAR)(_scans(scan_below=_SMALL))
register("lsh_scan_short_groups", _SIZED + """, held as (select query_id, group_id, count(*) as h from met group by 1, 2), asked_ as (select query_id, group_id, sum(n_cell) as n, max(quota) as quota from req join sized using (cell_code) group by 1, 2),
short as (select query_id, group_id from asked_ left join held using (query_id, group_id) where coalesce(h, 0) < least(n, quota)),
both_ as (select query_id, group_id, rec_id, quota from met union select r.query_id, r.group_id, c.rec_id, r.quota from req r join short using (query_id, group_id) join coded c using (cell_code) join q on q.query_id = r.query_id and q.src <> c.rec_id)""" + _FAR)(_scans(on_short="scan"))

_PLAN = {"p1": 0.9, "p2": 0.3, "near": 2, "delta": 0.5}


def _planned_sql(m: int, tables: int, hashes: int) -> str:
    """Keys as long as each cell plans, in as many tables; the answer from what is met so."""
    attrs = ATTRS["V_EMB"][:m]
    names = ", ".join(attrs)
    family = lsh.Family("pstable", 64, tables, hashes, 1.0)
    power = " ".join(f"when {i} then {lsh.BASE ** i}" for i in range(hashes))
    lengths = ", ".join(f"({n})" for n in range(1, hashes + 1))
    rho = lsh.rho(_PLAN["p1"], _PLAN["p2"])
    one = lambda rows, key, vec, name: f"""{name} as (select {key}, table_no, hashes, cast(sum(h * case hashes - 1 - hash_no {power} end) as bigint) as bucket
  from (select x.{key}, p.table_no, p.hash_no, cast(floor((list_dot_product(x.{vec}, p.a::double[]) + p.b) / {family.width!r}) as bigint) as h from {rows} x, proj p), (values {lengths}) l(hashes) where hash_no < hashes group by all)"""  # noqa: E731
    planned = f"""planned as (select {names}, least({hashes}, greatest(1, cast(ceil(ln(count(*)) / {math.log(1 / _PLAN['p2'])!r}) as integer))) as hashes,
  least({tables}, case when count(*) <= 1 then 1 else greatest(1, cast(ceil(pow(count(*), {rho!r}) * {math.log(2 * _PLAN['near'] / _PLAN['delta'])!r}) as integer)) end) as tables from v group by all)"""
    met = f"""select r.query_id, r.rec_id, min(k.table_no) as first_ from rel r join v using (rec_id) join planned n using ({names}) join keys_ k on k.rec_id = r.rec_id and k.hashes = n.hashes and k.table_no < n.tables
  join qkeys_ x on x.query_id = r.query_id and x.hashes = k.hashes and x.table_no = k.table_no and x.bucket = k.bucket group by 1, 2"""
    text = _lsh_answer(m, 1, None, met)
    head, tail = text.split("met0 as (", 1)
    return f"{head.replace(O.projections(lsh.Family('pstable', 64, 1, 2, 1.0)), O.projections(family))}{one('v', 'rec_id', 'vec', 'keys_')}, {one('q', 'query_id', 'qvec', 'qkeys_')}, {planned},\nmet0 as ({tail}"


@register("quota_knn_planned_cells", _planned_sql(2, 6, 3))
def quota_knn_planned_cells(spark, sf_dir):
    """Hashes and tables planned for each cell by its size."""
    index, q, u, x = _setup(spark, sf_dir, m=2, tables=6, hashes=3, per_cell=_PLAN)
    return _report(search(index, q, u, exclude=x, options={"cap": False}))


def _mixed_sql() -> str:
    attrs, parts = ATTRS["V_EMB"], []
    for m in (1, 2, 3):
        own = ", ".join(f"'{a}'" for a in attrs[:m])
        base = O.base("V_EMB", attrs, N, K).replace("quotas as (", "quotas0 as (") + f", quotas as (select * from quotas0 where attr in ({own}) and query_id % 3 = {m - 1})"
        parts.append(f"(with recursive {base}, {O.pool(attrs[:m])}, {O.solve(attrs[:m])} {O.ANSWERS} where q.query_id % 3 = {m - 1})")
    return "select * from (" + " union all ".join(parts) + ")"


@register("select_mixed_batch", _mixed_sql())
def select_mixed_batch(spark, sf_dir):
    """One batch whose queries constrain one, two or three attributes, each by its own selector."""
    index, q, u, x = _setup(spark, sf_dir)
    number = F.element_at(F.create_map(*[F.lit(v) for i, a in enumerate(index.attrs) for v in (a, i)]), F.col("attr"))
    own = cut(u.where(number <= F.col("query_id") % 3), "quotas")
    return _report(search(index, q, own, exclude=x, retriever="exact"))


@register("pair_feasible", f"with {O.base('V_EMB', ATTRS['V_EMB'][:2], N, K)} select query_id, query_id % 2 = 0 as feasible from q")
def pair_feasible(spark, sf_dir):
    """Every other query asks for more than there is."""
    index, q, u, x = _setup(spark, sf_dir, m=2)
    supply = baselines.marginals(index).select("attr", "value", "n")
    hard = W.infeasible(u.where("query_id % 2 = 1"), supply)
    both = cut(u.where("query_id % 2 = 0").unionByName(hard.select(u.columns)), "quotas")
    found, _ = retrieve.exhaustive(index, q, cut(retrieve.cell_requests(index, both), "requests"), x)
    return S.feasible_pair(cut(pool_of(index, found), "pool"), both, index.attrs)


@register("gadget_3dm", "select * from (values (0, true), (1, false)) t(case_no, feasible)")
def gadget_3dm(spark, sf_dir):
    """Three-dimensional matching as counts: one instance with a perfect matching, one without."""
    out = None
    for i, triples in enumerate([[(1, 1, 1), (2, 2, 2)], [(1, 1, 1), (2, 1, 2), (1, 2, 2)]]):
        v, q, u = quota.gadget_from_triples(spark, triples)
        index = build_index(v, ["x", "y", "z"], tables=1, compact=False)
        got = search(index, q, u, retriever="exact", selector="multi", select_options={"method": "bnb"}).status.select(F.lit(i).alias("case_no"), (F.col("status") == "ok").alias("feasible"))
        out = got if out is None else out.unionByName(got)
    return out


# rivals --------------------------------------------------------------------------------------------------------------


def _policy(policy: str, m: int = 2, relation: str = "V_EMB", **kw):
    def f(spark, sf_dir):
        index, q, u, x = _setup(spark, sf_dir, relation, m)
        return _report(search(index, q, u, exclude=x, retriever="exact", policy=policy, **kw))

    return f


def _marginal_join(attrs: list[str]) -> str:
    parts = " union all ".join(f"select '{a}' as attr, {a} as value, count(*) / (select count(*) from v) as prop from v where {a} is not null group by 2" for a in attrs)
    return f"marg as ({parts})"


def _independence_sql(relation: str, m: int, finish: str) -> str:
    attrs = ATTRS[relation][:m]
    names, p = ", ".join(attrs), ", ".join(f"p{i}" for i in range(m))
    joins = " ".join(f"join marg g{i} on g{i}.attr = '{a}' and g{i}.value = v.{a} join nd n{i} on n{i}.query_id = q.query_id and n{i}.attr = '{a}' and n{i}.value = v.{a}" for i, a in enumerate(attrs))
    prop = " * ".join(f"g{i}.prop" for i in range(m))
    ps = ", ".join(f"n{i}.pos as p{i}" for i in range(m))
    head = f"""with recursive {O.base(relation, attrs, N, K)}, nd as (select *, row_number() over (partition by query_id order by attr, value) - 1 as pos from quotas where need > 0), {_marginal_join(attrs)},
rel as (select q.query_id, v.rec_id, {', '.join('v.' + a for a in attrs)}, list_distance(v.vec, q.qvec) as dist, {ps}, cast(ceil(round({K} * {prop}, 9)) as integer) as budget from q join v on v.rec_id <> q.src {joins}),
got as (select * from (select *, row_number() over (partition by query_id, {names} order by dist, rec_id) as rn from rel) where rn <= budget),
pool as (select *, row_number() over (partition by query_id, {p} order by dist, rec_id) as rk, dense_rank() over (partition by query_id order by {p}) as cell from got)"""
    if finish == "select":
        return f"{head}, {O.solve(attrs)} {O.ANSWERS}"
    checks = " and ".join(f"(select bool_and(coalesce(h.n, 0) = x.need) from nd x left join (select query_id, p{i} as pos, count(*) as n from top group by 1, 2) h on h.query_id = x.query_id and h.pos = x.pos where x.query_id = q.query_id and x.attr = '{a}')" for i, a in enumerate(attrs))
    return f"""{head}, top as (select * from (select *, row_number() over (partition by query_id order by dist, rec_id) as rt from pool) where rt <= {K}),
res as (select query_id, sum(dist) as cost, list(rec_id) as ids, count(*) as n from top group by 1), ok as (select q.query_id, res.n = {K} and {checks} as good from q left join res using (query_id))
select q.query_id, case when ok.good then 'ok' else 'failed' end as status, case when ok.good then round(res.cost, 6) end as total_dist, case when ok.good then array_to_string(list_sort(res.ids), ',') end as ids
from q join ok using (query_id) left join res using (query_id)"""


def _per_attribute_sql(relation: str, m: int) -> str:
    attrs = ATTRS[relation][:m]
    p = ", ".join(f"p{i}" for i in range(m))
    got = " union all ".join(f"select query_id, rec_id, dist, {i} as a from (select q.query_id, v.rec_id, list_distance(v.vec, q.qvec) as dist, row_number() over (partition by q.query_id, v.{a} order by list_distance(v.vec, q.qvec), v.rec_id) as rn from q join v on v.rec_id <> q.src join nd on nd.query_id = q.query_id and nd.attr = '{a}' and nd.value = v.{a}) where rn <= {K}" for i, a in enumerate(attrs))
    joins = " ".join(f"join nd n{i} on n{i}.query_id = b.query_id and n{i}.attr = '{a}' and n{i}.value = v.{a}" for i, a in enumerate(attrs))
    ps = ", ".join(f"n{i}.pos as p{i}" for i in range(m))
    return f"""with recursive {O.base(relation, attrs, N, K)}, nd as (select *, row_number() over (partition by query_id order by attr, value) - 1 as pos from quotas where need > 0),
shared as (select query_id, rec_id, min(dist) as dist from ({got}) group by 1, 2 having count(distinct a) = {m}),
pool0 as (select b.query_id, b.rec_id, b.dist, {ps} from shared b join v using (rec_id) {joins}),
pool as (select *, row_number() over (partition by query_id, {p} order by dist, rec_id) as rk, dense_rank() over (partition by query_id order by {p}) as cell from pool0), {O.solve(attrs)} {O.ANSWERS}"""


register("per_attribute", _per_attribute_sql("V_EMB", 2))(_policy("per_attribute"))
register("per_attribute_correlated", _per_attribute_sql("V_COR", 3))(_policy("per_attribute", 3, "V_COR"))
register("independence_budget", _independence_sql("V_EMB", 2, "select"))(_policy("independence"))
register("independence_correlated", _independence_sql("V_COR", 3, "select"))(_policy("independence", 3, "V_COR"))
register("independence_direct", _independence_sql("V_EMB", 2, "direct"))(_policy("independence", finish="direct"))


@register("marginal_shares", f"with v as ({O.RELATION_SQL['V_EMB']}), {_marginal_join(ATTRS['V_EMB'])} select attr, value, round(prop, 6) as prop from marg")
def marginal_shares(spark, sf_dir):
    return baselines.marginals(_setup(spark, sf_dir)[0]).select("attr", "value", F.round("prop", 6).alias("prop"))


@register("post_filter", f"""with recursive {O.base('V_EMB', ATTRS['V_EMB'][:2], N, K)}, nd as (select *, row_number() over (partition by query_id order by attr, value) - 1 as pos from quotas where need > 0),
near as (select * from (select q.query_id, v.rec_id, v.status, v.priority, list_distance(v.vec, q.qvec) as dist, row_number() over (partition by q.query_id order by list_distance(v.vec, q.qvec), v.rec_id) as rn from q join v on v.rec_id <> q.src) where rn <= 60),
pool0 as (select near.*, n0.pos as p0, n1.pos as p1 from near join nd n0 on n0.query_id = near.query_id and n0.attr = 'status' and n0.value = near.status join nd n1 on n1.query_id = near.query_id and n1.attr = 'priority' and n1.value = near.priority),
pool as (select *, row_number() over (partition by query_id, p0, p1 order by dist, rec_id) as rk, dense_rank() over (partition by query_id order by p0, p1) as cell from pool0),
{O.solve(['a', 'b'])} select q.query_id, round(best.cost, 6) as total_dist from q left join best using (query_id)""")
def post_filter(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, m=2)
    picked = S.select(cut(baselines.post_filter(index, q, u, 60, exclude=x), "pool"), u, index.attrs)
    return q.select("query_id").join(picked.groupBy("query_id").agg(F.round(F.sum("dist"), 6).alias("total_dist")), "query_id", "left")


@register("unconstrained_counts", _knn_sql("l2").replace("select query_id, rec_id, round(dist, 6) as dist from", "select k.query_id, v.status as value, count(*) as n from", 1).replace(") where rn <= 10", ") k join v using (rec_id) where rn <= 10 group by 1, 2"))
def unconstrained_counts(spark, sf_dir):
    index, q, _, x = _setup(spark, sf_dir)
    return baselines.unconstrained_counts(index, retrieve.knn(index, q, 10, exclude=x), "status")


@register("graph_edges", f"with v as ({O.RELATION_SQL['V_EMB']}) select src, dst, round(dist, 6) as dist from (select a.rec_id as src, b.rec_id as dst, list_distance(a.vec, b.vec) as dist, row_number() over (partition by a.rec_id order by list_distance(a.vec, b.vec), b.rec_id) as rn from v a join v b on a.rec_id <> b.rec_id) where rn <= 8")
def graph_edges(spark, sf_dir):
    return graph.knn_edges(_setup(spark, sf_dir)[0], 8).select("src", "dst", F.round("dist", 6).alias("dist"))


def _graph(kind: str):
    def f(spark, sf_dir):
        index, q, u, x = _setup(spark, sf_dir, m=2, n=4)
        g = graph.build(index, 8, per_cell=kind == "graph_collection")
        return _report(search(index, q, u, exclude=x, retriever=kind, graph=g))

    return f


register("graph_filtered_quota")(_graph("graph_filtered"))
register("graph_collection_fair")(_graph("graph_collection"))

# measures ------------------------------------------------------------------------------------------------------------


def _judged(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, "V_COR", 3)
    truth = search(index, q, u, exclude=x, retriever="exact")
    got = search(index, q, u, exclude=x, retriever="exact", policy="independence")
    return truth, got


_BOTH = f"""truth as ({O.truth('V_COR', 3, N, K)}), got as ({_independence_sql('V_COR', 3, 'select')})"""


@register("success_report", f"with {_BOTH} select count(*) as queries, round(100 * avg(case when status = 'ok' then 1.0 else 0.0 end), 6) as success_pct from got")
def success_report(spark, sf_dir):
    return measures.success_pct(_judged(spark, sf_dir)[1].status)


@register("recall_report", f"with {_BOTH} select query_id, round(coalesce(len(list_intersect(string_split(t.ids, ','), string_split(g.ids, ','))), 0) / {K}, 6) as recall from truth t join got g using (query_id)")
def recall_report(spark, sf_dir):
    truth, got = _judged(spark, sf_dir)
    return measures.recall_at_k(got.answer, truth.answer).withColumn("recall", F.round("recall", 6))


@register("daf_report", f"with {_BOTH} select round(avg(g.total_dist / t.total_dist), 4) as daf_answered, round(avg(coalesce(g.total_dist / t.total_dist, 0)), 4) as daf_zeroed from truth t join got g using (query_id)")
def daf_report(spark, sf_dir):
    truth, got = _judged(spark, sf_dir)
    r = measures.daf_report(got.status, truth.status)
    return r.select(F.round("daf_answered", 4).alias("daf_answered"), F.round("daf_zeroed", 4).alias("daf_zeroed"))


# experiments ---------------------------------------------------------------------------------------------------------

SIX = {
    f"{policy}_{name}": {"retriever": retriever, "policy": policy}
    for policy in ("per_attribute", "independence") for name, retriever in (("lsh", "lsh"), ("filtered", "graph_filtered"), ("collection", "graph_collection"))
}
register("exp_plain_retrieval")(lambda s, d: W.plain_retrieval(s, 6_000, 10))
register("exp_plain_retrieval_swept")(lambda s, d: W.plain_swept(s, 2_000, 5))
register("exp_quality_by_k")(lambda s, d: W.by_k(s, d, "V_EMB", (5, 10, 20), BATCH, 64))
register("exp_ratio_by_k")(lambda s, d: W.by_k(s, d, "V_LINE", (5, 20), 10, 16, policies={"cell_lsh": {"retriever": "lsh"}, **W.GRAPHS}, sample=1_500))
register("exp_quality_by_m")(lambda s, d: W.by_m(s, d, ms=(1, 3, 5), n=BATCH, k=5, tables=128, with_graphs=False))
register("exp_graphs_by_m")(lambda s, d: W.by_m(s, d, ms=(2, 4, 5), n=4, k=5, tables=32, with_graphs=True, policies={"cell_lsh": {"retriever": "lsh"}}))
register("exp_policy_grid")(lambda s, d: W.by_m(s, d, "V_COR", (2,), 4, 6, 32, with_graphs=True, policies={"cell_lsh": {"retriever": "lsh"}, **SIX}))
register("exp_quality_by_tables")(lambda s, d: W.by_parameter(s, d, "V_COR", (4, 32, 128), n=BATCH, policies=W.POLICIES))
register("exp_quality_by_width")(lambda s, d: W.by_parameter(s, d, "V_COR", (16,), (0.5, 2.0), n=BATCH, policies=W.POLICIES))
register("exp_query_times")(lambda s, d: W.query_times(s, d, ks=(5, 20), n=BATCH))
register("exp_selection_times")(lambda s, d: W.selection_times(s, d, (1, 2, 3), 20, BATCH))
register("exp_flow_or_integer")(lambda s, d: W.flow_or_integer(s, d, (5, 10, 20, 40), BATCH))
register("exp_scanned_share")(lambda s, d: W.scanned_by(s, 10_000, (1, 3), (5, 20), 10))
register("exp_index_costs")(lambda s, d: W.index_costs(s, d, ("V_EMB", "V_DOC"), ((4, 2), (16, 2), (16, 4))))
