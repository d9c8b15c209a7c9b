"""More named queries: relational surround, SQL surface and streams."""

from __future__ import annotations

import time

from pyspark.sql import Window
from pyspark.sql import functions as F

from quotaknn.functions import sql as surface
from quotaknn.functions.cells import build_dictionary, match_counts_by_bitmap, value_bitmaps
from quotaknn.functions.lsh import Family
from quotaknn.operators import relational as R
from quotaknn.operators.baselines import mllib_lsh_candidates
from quotaknn.plans import oracle as O
from quotaknn.plans import workloads as W
from quotaknn.plans.index import append_index, build_index, delete_from_index, load_index
from quotaknn.plans.lineage import cut, shared_path
from quotaknn.plans.registry import N, _exact, _report, _setup, register
from quotaknn.operators.search import search
from quotaknn.sources.catalog import ATTRS, bad_vectors, latest_attributes, read_vectors, table, vector_relation, write_vectors
from quotaknn.streaming import events as E

# relational ----------------------------------------------------------------------------------------------------------


@register("rel_inner_join", "select o_orderstatus, count(*) as n, round(sum(l_quantity), 2) as quantity from lineitem join orders on l_orderkey = o_orderkey where l_discount between 0.02 and 0.05 group by 1")
def rel_inner_join(spark, sf_dir):
    li, o = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    rows = li.where(F.col("l_discount").between(0.02, 0.05)).join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    return rows.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@register("rel_semi_join", "select c_custkey, c_mktsegment from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderpriority = '1-URGENT')")
def rel_semi_join(spark, sf_dir):
    urgent = table(spark, sf_dir, "orders").where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return table(spark, sf_dir, "customer").join(urgent, "c_custkey", "left_semi").select("c_custkey", "c_mktsegment")


@register("rel_anti_join", "select doc_id from documents where doc_id not in (select doc_id from labels)")
def rel_anti_join(spark, sf_dir):
    return table(spark, sf_dir, "documents").join(table(spark, sf_dir, "labels"), "doc_id", "left_anti").select("doc_id")


@register("rel_full_join", "select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as customers, coalesce(b.n, 0) as suppliers from (select c_nationkey as k, count(*) as n from customer group by 1) a full join (select s_nationkey as k, count(*) as n from supplier group by 1) b on a.k = b.k")
def rel_full_join(spark, sf_dir):
    a = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("a_"))
    b = table(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("b_"))
    return a.join(b, "k", "full").select("k", F.coalesce("a_", F.lit(0)).alias("customers"), F.coalesce("b_", F.lit(0)).alias("suppliers"))


@register("rel_range_join", "select p_partkey, low, high from part join (select s_suppkey, s_acctbal / 10 as low, s_acctbal / 10 + 20 as high from supplier) on p_retailprice between low and high where p_partkey < 200")
def rel_range_join(spark, sf_dir):
    p = table(spark, sf_dir, "part").where("p_partkey < 200").select("p_partkey", "p_retailprice")
    s = table(spark, sf_dir, "supplier").select((F.col("s_acctbal") / 10).alias("low"), (F.col("s_acctbal") / 10 + 20).alias("high"))
    return R.range_join(p, "p_retailprice", s, "low", "high", 50.0).select("p_partkey", "low", "high")


@register("rel_asof_join", "select e.event_id as id, s.value as seen from (select event_id, user_id, ts from events where event_type = 'error') e asof left join (select user_id, ts, cast(event_id as varchar) as value from events where event_type = 'click') s on e.user_id = s.user_id and e.ts >= s.ts")
def rel_asof_join(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    left = e.where("event_type = 'error'").select(F.col("user_id").alias("rec_id"), F.col("ts").alias("at"), F.col("event_id").alias("id"))
    right = e.where("event_type = 'click'").select(F.col("user_id").alias("rec_id"), F.col("ts").alias("at"), F.col("event_id").cast("string").alias("seen"))
    return latest_attributes(left, right, ["seen"]).select("id", "seen")


@register("rel_lateral_top", "select c_custkey, o_orderkey from (select c_custkey, o_orderkey, row_number() over (partition by c_custkey order by o_totalprice desc, o_orderkey) as rn from customer join orders on o_custkey = c_custkey) where rn <= 2")
def rel_lateral_top(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey", (-F.col("o_totalprice")).alias("price"))
    top = R.salted_top_k(o, ["o_custkey"], ["price", "o_orderkey"], 2)
    return table(spark, sf_dir, "customer").join(top, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


@register("rel_rollup", "select r_name, n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)")
def rel_rollup(spark, sf_dir):
    return vector_relation(spark, sf_dir, "V_CUST").rollup(F.col("region").alias("r_name"), F.col("nation").alias("n_name")).agg(F.count(F.lit(1)).alias("n"))


@register("rel_pivot", f"select priority, count(*) filter (status = 'F') as f, count(*) filter (status = 'O') as o, count(*) filter (status = 'P') as p from ({O.RELATION_SQL['V_EMB']}) group by 1")
def rel_pivot(spark, sf_dir):
    rows = vector_relation(spark, sf_dir, "V_EMB").groupBy("priority").pivot("status", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return rows.select("priority", *[F.coalesce(F.col(c), F.lit(0)).alias(c.lower()) for c in "FOP"])


@register("rel_set_operations", "(select o_custkey as k from orders where o_orderstatus = 'F' intersect select o_custkey from orders where o_orderstatus = 'O') except select o_custkey from orders where o_orderstatus = 'P'")
def rel_set_operations(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    keys = lambda s: o.where(F.col("o_orderstatus") == s).select(F.col("o_custkey").alias("k"))
    return keys("F").intersect(keys("O")).subtract(keys("P"))


@register("rel_prefix_costs", "select o_orderpriority, rec_id, take, round(cost, 4) as cost, round(step, 4) as step from (select o_orderpriority, o_orderkey as rec_id, row_number() over w as take, sum(o_totalprice) over (w rows between unbounded preceding and current row) as cost, o_totalprice - coalesce(lag(o_totalprice) over w, 0) as step from orders where o_orderkey < 400 window w as (partition by o_orderpriority order by o_totalprice, o_orderkey))")
def rel_prefix_costs(spark, sf_dir):
    o = table(spark, sf_dir, "orders").where("o_orderkey < 400").select("o_orderpriority", F.col("o_orderkey").alias("rec_id"), F.col("o_totalprice").alias("dist"))
    return R.prefix_costs(o, ["o_orderpriority"]).select("o_orderpriority", "rec_id", "take", F.round("cost", 4).alias("cost"), F.round("step", 4).alias("step"))


@register("rel_page_hosts", "select regexp_extract(url, '^https?://([^/:?#]+)', 1) as host, count(*) as n from pages group by 1")
def rel_page_hosts(spark, sf_dir):
    return table(spark, sf_dir, "pages").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count(F.lit(1)).alias("n"))


@register("rel_json_events", "select event_type, cast(json_extract_string(props, '$.k') as integer) // 10 as bucket, count(*) as n from events group by 1, 2")
def rel_json_events(spark, sf_dir):
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf_dir, "events").groupBy("event_type", F.floor(k / 10).cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@register("rel_dates", "select cast(dayofweek(ts) + 1 as integer) as weekday, cast(hour(ts) as integer) as hour, count(*) as n from events group by 1, 2")
def rel_dates(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.dayofweek("ts").alias("weekday"), F.hour("ts").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@register("rel_stratified_sample", "select o_orderkey, o_orderstatus from (select *, percent_rank() over (partition by o_orderstatus order by (o_orderkey * 2654435761 + 3) % 4294967291, o_orderkey) as r from orders) where r < 0.1")
def rel_stratified_sample(spark, sf_dir):
    return R.stratified(table(spark, sf_dir, "orders"), "o_orderstatus", "o_orderkey", 0.1).select("o_orderkey", "o_orderstatus")


@register("rel_subqueries", "select o_orderkey from orders o where o_totalprice > (select avg(o_totalprice) * 1.5 from orders i where i.o_orderpriority = o.o_orderpriority)")
def rel_subqueries(spark, sf_dir):
    return spark.sql("select o_orderkey from {o} o where o_totalprice > (select avg(o_totalprice) * 1.5 from {o} i where i.o_orderpriority = o.o_orderpriority)", o=table(spark, sf_dir, "orders"))


@register("rel_rank_windows", "select c_custkey, rank() over w as r, dense_rank() over w as d, ntile(4) over w as q from customer window w as (partition by c_mktsegment order by c_nationkey, c_custkey)")
def rel_rank_windows(spark, sf_dir):
    w = Window.partitionBy("c_mktsegment").orderBy("c_nationkey", "c_custkey")
    return table(spark, sf_dir, "customer").select("c_custkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(w).alias("q"))


@register("rel_width_quantiles")
def rel_width_quantiles(spark, sf_dir):
    from quotaknn.plans.registry import QUERIES

    return R.choose_width(QUERIES["dist_l2"](spark, sf_dir))


@register("use_part_diversity")
def use_part_diversity(spark, sf_dir):
    """Parts close to a wanted one, a count for each brand and size band (brand diversity)."""
    return _exact(2, 6, "V_PART")(spark, sf_dir)


@register("use_speech_like")
def use_speech_like(spark, sf_dir):
    return _exact(2, 6, "V_LINE", retriever="blocks")(spark, sf_dir)


@register("use_text_cosine")
def use_text_cosine(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, "V_DOC", 2, n=4, k=5, metric="cosine", tables=16, hashes=8)
    return _report(search(index, q, u, exclude=x))


@register("cell_match_bitmaps", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, 6)}, cells as (select distinct status, priority, lang from v) select q.query_id, cast(count(*) as bigint) as n_cells from q, cells c where exists (select 1 from quotas u where u.query_id = q.query_id and u.attr = 'status' and u.value = c.status) and exists (select 1 from quotas u where u.query_id = q.query_id and u.attr = 'priority' and u.value = c.priority) and exists (select 1 from quotas u where u.query_id = q.query_id and u.attr = 'lang' and u.value = c.lang) group by 1")
def cell_match_bitmaps(spark, sf_dir):
    index, _, u, _ = _setup(spark, sf_dir)
    return match_counts_by_bitmap(value_bitmaps(index.cells, index.dictionary), u)


@register("lsh_mllib", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, 6)} select q.query_id, count(*) filter (list_distance(v.vec, q.qvec) < 0.5) as n from q, v group by 1")
def lsh_mllib(spark, sf_dir):
    """Spark ML's hashing as a contrast; with these tables it finds each query's own record."""
    index, q, _, _ = _setup(spark, sf_dir, tables=8, width=2.0)
    return mllib_lsh_candidates(index, q, 0.5).groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))


@register("rel_sketches")
def rel_sketches(spark, sf_dir):
    """Approximate domain sizes, quantiles and heavy values, all mergeable."""
    o = table(spark, sf_dir, "orders")
    return o.agg(F.approx_count_distinct("o_custkey").alias("customers"), F.percentile_approx("o_totalprice", 0.5).alias("median"), F.to_json(F.expr("approx_top_k(o_orderpriority, 2)")).alias("heavy"))


@register("rel_unpivot", "select o_orderkey, 'status' as attr, o_orderstatus as value from orders union all select o_orderkey, 'priority', o_orderpriority from orders")
def rel_unpivot(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority"))
    return o.unpivot("o_orderkey", ["status", "priority"], "attr", "value")


register("exp_times_by_relation")(lambda s, d: W.times_by_relation(s, d, ("V_EMB", "V_LINE", "V_DOC"), 20, 3, 20))
register("exp_metrics")(lambda s, d: W.by_metric(s, d, 20))
register("exp_passages_as_queries")(lambda s, d: W.passages_as_queries(s, d))
register("exp_near_recall")(lambda s, d: W.near_recall(s, d))


# index life ----------------------------------------------------------------------------------------------------------


def _kept(where: str) -> str:
    return f"select count(*) as postings, count(distinct rec_id) as records from ({O.RELATION_SQL['V_EMB']}), (select unnest(range(4)) as t) where {where}"


@register("index_append", _kept("true"))
def index_append(spark, sf_dir):
    v = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors")
    index = build_index(v.where("rec_id < 300"), ATTRS["V_EMB"], tables=4)
    more = append_index(index, v.where("rec_id >= 300"))
    return load_index(spark, more.path).postings.agg(F.count(F.lit(1)).alias("postings"), F.count_distinct("rec_id").alias("records"))


@register("index_delete", _kept("rec_id % 10 <> 0"))
def index_delete(spark, sf_dir):
    index = _setup(spark, sf_dir, tables=4)[0]
    left = delete_from_index(index, index.vectors.where("rec_id % 10 = 0").select("rec_id"))
    return left.postings.agg(F.count(F.lit(1)).alias("postings"), F.count_distinct("rec_id").alias("records"))


@register("source_round_trip", f"select k.kind, v.rec_id, round(list_sum(v.vec), 6) as total, v.status from ({O.RELATION_SQL['V_EMB']}) v, (values ('csv'), ('json'), ('orc'), ('parquet')) k(kind)")
def source_round_trip(spark, sf_dir):
    v = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors").select("rec_id", "vec", "status")
    out = None
    for kind in ("csv", "json", "orc", "parquet"):
        path = shared_path(spark, kind)
        write_vectors(v, path, kind, 2)
        back = read_vectors(spark, path, kind, attrs=["status"]).select(F.lit(kind).alias("kind"), "rec_id", F.round(F.aggregate("vec", F.lit(0.0), lambda a, x: a + x), 6).alias("total"), "status")
        out = back if out is None else out.unionByName(back)
    return out


@register("source_bad_vectors", "select vec_id as rec_id from embeddings where vec_id % 5 = 0")
def source_bad_vectors(spark, sf_dir):
    v = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("rec_id"), F.col("embedding").cast("array<double>").alias("vec"))
    broken = F.when(F.col("rec_id") % 15 == 0, F.lit(None)).when(F.col("rec_id") % 15 == 5, F.slice("vec", 1, 3)).when(F.col("rec_id") % 15 == 10, F.transform("vec", lambda x: F.lit(float("nan")))).otherwise(F.col("vec"))
    return bad_vectors(v.withColumn("vec", broken), 64).select("rec_id")


# SQL surface ---------------------------------------------------------------------------------------------------------


@register("sql_expand_quota", f"with {O.base('V_EMB', ATTRS['V_EMB'], N, 6)}, {O.codes(ATTRS['V_EMB'])}, {O.query_codes(ATTRS['V_EMB'])} select query_id, mask, qcode, k_cell from asked")
def sql_expand_quota(spark, sf_dir):
    """The product of needs by a table function in SQL, laterally for each query."""
    index, _, u, _ = _setup(spark, sf_dir)
    surface.register_sql(spark, index.family, index.dictionary)
    own = u.groupBy("query_id", "attr").agg(F.map_from_entries(F.collect_list(F.struct("value", "need"))).alias("own"))
    needs = own.groupBy("query_id").agg(F.to_json(F.map_from_entries(F.collect_list(F.struct("attr", "own")))).alias("needs"))
    return spark.sql("select n.query_id, x.mask, x.qcode, x.k_cell from {n} n, lateral expand_quota(n.needs) x", n=needs)


@register("sql_functions", f"with v as ({O.RELATION_SQL['V_EMB']}) select rec_id, round(list_distance(vec, (select vec from v where rec_id = 7)), 6) as dist, xor(rec_id & 6, 4) = 0 as matched, 10 + cast(ceil(2 * 16 / 0.1) as integer) as budget from v")
def sql_functions(spark, sf_dir):
    v = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors")
    surface.register_sql(spark, Family("pstable", 64), build_dictionary(v, ["status"]))
    return spark.sql("select rec_id, round(vec_l2(vec, (select max(vec) from {v} where rec_id = 7)), 6) as dist, cell_match(rec_id, 6L, 4L) as matched, inspect_budget(10, 16, 0.1D) as budget from {v}", v=v)


@register("sql_centroids", f"select status, round(avg(vec[1]), 6) as first, round(avg(vec[64]), 6) as last from ({O.RELATION_SQL['V_EMB']}) group by 1")
def sql_centroids(spark, sf_dir):
    v = vector_relation(spark, sf_dir, "V_EMB").groupBy("status").agg(surface.centroid()("vec").alias("c"))
    return v.select("status", F.round(F.get("c", F.lit(0)), 6).alias("first"), F.round(F.get("c", F.lit(63)), 6).alias("last"))


# streams -------------------------------------------------------------------------------------------------------------


def _plain_time(rows):
    """Watermarks need instants: a wall clock is read as UTC."""
    return rows.withColumn("ts", F.expr("cast(convert_timezone('UTC', current_timezone(), ts) as timestamp)")) if dict(rows.dtypes)["ts"] == "timestamp_ntz" else rows


def _events(spark, sf_dir):
    rows = E.read_stream(spark, f"{sf_dir.rstrip('/')}/events.parquet*", table(spark, sf_dir, "events").schema)
    if dict(rows.dtypes)["ts"] == "timestamp_ntz":  # watermarks need instants: the wall clock is read as UTC
        rows = rows.withColumn("ts", F.expr("cast(convert_timezone('UTC', current_timezone(), ts) as timestamp)"))
    return rows


def _plain(rows):
    """Window starts as UTC's wall clock, without a zone, as other engines have them."""
    return rows.withColumn("start", F.expr("convert_timezone(current_timezone(), 'UTC', cast(start as timestamp_ntz))"))


@register("stream_tumbling", "select date_trunc('hour', ts) as start, event_type, count(*) as n from events group by 1, 2")
def stream_tumbling(spark, sf_dir):
    return _plain(E.run_to_end(E.tumbling(_events(spark, sf_dir)), "tumbling", "complete"))


@register("stream_sliding", "select w as start, event_type, count(*) as n from (select event_type, unnest([time_bucket(interval '3 hours', ts), time_bucket(interval '3 hours', ts) - interval '3 hours']) as w from events) group by 1, 2")
def stream_sliding(spark, sf_dir):
    return _plain(E.run_to_end(E.sliding(_events(spark, sf_dir)), "sliding", "complete"))


@register("stream_sessions", "with g as (select user_id, ts, sum(case when ts > prev + interval '30 minutes' or prev is null then 1 else 0 end) over (partition by user_id order by ts) as s from (select user_id, ts, lag(ts) over (partition by user_id order by ts) as prev from events)) select user_id, min(ts) as start, count(*) as n from g group by user_id, s")
def stream_sessions(spark, sf_dir):
    return _plain(E.run_to_end(E.sessions(_events(spark, sf_dir)), "sessions", "complete"))


@register("stream_quota_monitor", "select date_trunc('day', ts) as start, event_type, count(*) as n, case event_type when 'click' then 60 when 'view' then 60 else 0 end as need, count(*) - case event_type when 'click' then 60 when 'view' then 60 else 0 end as gap from events group by 1, 2")
def stream_quota_monitor(spark, sf_dir):
    counts = E.run_to_end(E.tumbling(_events(spark, sf_dir), "1 day"), "monitor", "complete")
    return _plain(E.quota_monitor(counts, {"click": 60, "view": 60}))


@register("stream_dedup", "select event_id, user_id from events")
def stream_dedup(spark, sf_dir):
    """Each event sent twice; once in the result."""
    e = _events(spark, sf_dir).select("event_id", "user_id", "ts")
    return E.run_to_end(E.deduplicated(e.unionAll(e), ["event_id"]), "dedup").select("event_id", "user_id")


@register("stream_interval_join", "select a.event_id as first_id, b.event_id as second_id, a.user_id from events a join events b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval '10 minutes' where a.event_type = 'click' and b.event_type = 'purchase'")
def stream_interval_join(spark, sf_dir):
    e = _events(spark, sf_dir)
    return E.run_to_end(E.followed(e.where("event_type = 'click'"), e.where("event_type = 'purchase'")), "join")


@register("stream_late_rows", """with cut as (select epoch_us(min(ts)) + (epoch_us(max(ts)) - epoch_us(min(ts))) // 2 as mid from events),
part as (select case when epoch_us(ts) < mid then 2 else event_id % 2 end as batch, ts from events, cut), first_ as (select max(ts) as last from part where batch = 0)
select cast(batch as bigint) as batch, count(*) as rows, count(*) filter (batch = 2 and ts <= date_trunc('millisecond', last) - interval '2 hours') as late_rows from part, first_ group by 1""")
def stream_late_rows(spark, sf_dir):
    """The later half of the events arrives first, in two batches: most of the other half is behind the watermark, which
    counts from the batch after the next."""
    e = _plain_time(table(spark, sf_dir, "events")).select("event_id", "ts")
    mid = e.agg(F.expr("unix_micros(min(ts)) + (unix_micros(max(ts)) - unix_micros(min(ts))) div 2")).head()[0]
    path = shared_path(spark, "halves")
    for part in (f"unix_micros(ts) >= {mid} and event_id % 2 = 0", f"unix_micros(ts) >= {mid} and event_id % 2 = 1", f"unix_micros(ts) < {mid}"):
        e.where(part).coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)  # files are taken in the order of their times
    return E.late_rows(E.read_stream(spark, path, e.schema), ["event_id"])


@register("stream_running_best", "select start, event_type, value, event_id from (select date_trunc('day', ts) as start, event_type, value, event_id, row_number() over (partition by date_trunc('day', ts), event_type order by value, event_id) as rn from events) where rn <= 3")
def stream_running_best(spark, sf_dir):
    return _plain(E.running_best(spark, _events(spark, sf_dir), 3))


@register("stream_ingest", _kept("true"))
def stream_ingest(spark, sf_dir):
    """Vectors that arrive in three files, some of them twice: the index is the same as one built at once."""
    v = cut(vector_relation(spark, sf_dir, "V_EMB"), "vectors")
    index = build_index(v.where("rec_id < 100"), ATTRS["V_EMB"], tables=4)
    path = shared_path(spark, "arrivals")
    v.where("rec_id >= 50").repartition(3).write.parquet(path)
    after = E.ingest(E.read_stream(spark, path, v.schema), index)
    return after.postings.agg(F.count(F.lit(1)).alias("postings"), F.count_distinct("rec_id").alias("records"))


@register("stream_answers", O.truth("V_EMB", 2, N, 6, tail="select q.query_id, round(best.cost, 6) as total_dist from q join best using (query_id)"))
def stream_answers(spark, sf_dir):
    index, q, u, x = _setup(spark, sf_dir, m=2)
    own = u.groupBy("query_id", "attr").agg(F.map_from_entries(F.collect_list(F.struct("value", "need"))).alias("own"))
    needs = own.groupBy("query_id").agg(F.to_json(F.map_from_entries(F.collect_list(F.struct("attr", "own")))).alias("needs"))
    path = shared_path(spark, "queries")
    rows = q.join(needs, "query_id").select("query_id", "qvec", "needs")
    rows.repartition(2).write.parquet(path)
    answers = E.answer_stream(E.read_stream(spark, path, rows.schema), index, retriever="exact", exclude=x)
    return answers.groupBy("query_id").agg(F.round(F.sum("dist"), 6).alias("total_dist"))
