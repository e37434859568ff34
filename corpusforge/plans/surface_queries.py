"""Relational surface around the methods: joins, sets, aggregates, windows and functions, with SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import relational
from ..sources.tables import read_files, shared_folder, table, write_files
from .registry import query


@query("rel_semi_anti", "select 'with' kind, count(*) n from customer where c_custkey in (select o_custkey from orders) union all select 'without', count(*) from customer where c_custkey not in (select o_custkey from orders)")
def rel_semi_anti(spark, d):
    c, o = table(spark, d, "customer").select("c_custkey"), table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"))
    count = lambda how, name: c.join(o, "c_custkey", how).agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "n")
    return count("left_semi", "with").unionByName(count("left_anti", "without"))


@query("rel_full_outer", "select (c.k is null) no_customer, (o.k is null) no_order, count(*) n from (select c_custkey::bigint k from customer) c full join (select o_custkey::bigint k, count(*) n from orders group by all) o on c.k = o.k group by all")
def rel_full_outer(spark, d):
    c = table(spark, d, "customer").select(F.col("c_custkey").cast("bigint").alias("k"), F.lit(1).alias("c"))
    o = table(spark, d, "orders").groupBy(F.col("o_custkey").cast("bigint").alias("k")).agg(F.lit(1).alias("o"))
    return c.join(o, "k", "full").groupBy(F.isnull("c").alias("no_customer"), F.isnull("o").alias("no_order")).agg(F.count(F.lit(1)).alias("n"))


BANDS = ((0, 20_000), (20_000, 80_000), (80_000, 10**9))


@query("rel_range_join", "select b band, count(*) n from orders, (values (0, 0, 20000), (1, 20000, 80000), (2, 80000, 1000000000)) v(b, lo, hi) where o_totalprice >= lo and o_totalprice < hi group by b")
def rel_range_join(spark, d):
    """Rows to the interval that holds them: bounds are a literal of a few rows."""
    bands = spark.createDataFrame([(i, *b) for i, b in enumerate(BANDS)], "band int, lo bigint, hi bigint")
    o = table(spark, d, "orders").select("o_totalprice")
    return o.join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("lo")) & (F.col("o_totalprice") < F.col("hi"))).groupBy("band").agg(F.count(F.lit(1)).alias("n"))


@query("rel_sets", "select 'intersect' kind, count(*) n from (select c_nationkey from customer intersect select s_nationkey from supplier) union all select 'except', count(*) from (select c_custkey from customer except select o_custkey from orders) union all select 'union', count(*) from (select c_nationkey from customer union select s_nationkey from supplier)")
def rel_sets(spark, d):
    c, s = table(spark, d, "customer"), table(spark, d, "supplier").select("s_nationkey")
    keys = table(spark, d, "orders").select(F.col("o_custkey").cast("bigint")), c.select(F.col("c_custkey").cast("bigint"))
    parts = {"intersect": c.select("c_nationkey").intersect(s), "except": keys[1].subtract(keys[0]), "union": c.select("c_nationkey").union(s).distinct()}
    out = None
    for name, part in parts.items():
        part = part.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "n")
        out = part if out is None else out.unionByName(part)
    return out


@query("rel_pivot", "select user_id % 10 as slot, count(*) filter (where event_type = 'click') click, count(*) filter (where event_type = 'view') as view, count(*) filter (where event_type = 'purchase') purchase from events group by all")
def rel_pivot(spark, d):
    x = table(spark, d, "events").select((F.col("user_id") % 10).alias("slot"), "event_type")
    return x.groupBy("slot").pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1))).fillna(0)


@query("rel_unpivot", "select flag, measure, round(sum(v), 2) total from (select l_returnflag flag, unnest([{'measure': 'qty', 'v': l_quantity::double}, {'measure': 'price', 'v': l_extendedprice::double}], recursive := true) from lineitem) group by all")
def rel_unpivot(spark, d):
    x = table(spark, d, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_quantity").cast("double").alias("qty"), F.col("l_extendedprice").cast("double").alias("price"))
    sums = x.groupBy("flag").agg(F.sum("qty").alias("qty"), F.sum("price").alias("price"))
    return sums.unpivot("flag", ["qty", "price"], "measure", "v").select("flag", "measure", F.round("v", 2).alias("total"))


@query("rel_rollup", "select coalesce(lang, '(all)') lang, coalesce(source, '(all)') source, count(*) n, sum(n_chars)::bigint chars from documents group by rollup (lang, source)")
def rel_rollup(spark, d):
    x = table(spark, d, "documents").select("lang", "source", "n_chars").rollup("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))
    return x.select(F.coalesce("lang", F.lit("(all)")).alias("lang"), F.coalesce("source", F.lit("(all)")).alias("source"), "n", "chars")


@query("rel_statistics", "select event_type, round(stddev_samp(value), 5) sd, round(quantile_cont(value, 0.5), 5) median, round(corr(value, user_id), 5) r, round(regr_slope(value, user_id), 6) slope from events group by event_type")
def rel_statistics(spark, d):
    x = table(spark, d, "events").select("event_type", "value", "user_id")
    return x.groupBy("event_type").agg(F.round(F.stddev_samp("value"), 5).alias("sd"), F.round(F.percentile("value", F.lit(0.5)), 5).alias("median"), F.round(F.corr("value", "user_id"), 5).alias("r"), F.round(F.regr_slope("value", "user_id"), 6).alias("slope"))


@query("rel_running", "select o_orderkey::bigint orderkey, round(sum(o_totalprice) over w, 2) running, coalesce(lag(o_orderkey::bigint) over w, -1) prev, ntile(4) over w as quartile, dense_rank() over w dr from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def rel_running(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    k = F.col("o_orderkey").cast("bigint")
    return table(spark, d, "orders").select(k.alias("orderkey"), F.round(F.sum("o_totalprice").over(w), 2).alias("running"), F.coalesce(F.lag(k).over(w), F.lit(-1)).alias("prev"), F.ntile(4).over(w).cast("bigint").alias("quartile"), F.dense_rank().over(w).cast("bigint").alias("dr"))


@query("rel_max_by", "select o_custkey::bigint cust, arg_max(o_orderkey::bigint, (o_totalprice, o_orderkey)) dearest, count(distinct o_orderdate) as n_days from orders group by o_custkey")
def rel_max_by(spark, d):
    return table(spark, d, "orders").groupBy(F.col("o_custkey").cast("bigint").alias("cust")).agg(F.max_by(F.col("o_orderkey").cast("bigint"), F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.countDistinct("o_orderdate").alias("n_days"))


@query("rel_arrays", "select vec_id, round(list_dot_product(embedding::double[], embedding::double[]), 4) norm2, len(list_filter(embedding, lambda x: x > 0)) positive from embeddings")
def rel_arrays(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.round(F.aggregate(e, F.lit(0.0), lambda s, x: s + x * x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("positive"))


@query("rel_strings", "select page_id, lower(regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)) host, length(html) chars, strlen(html)::bigint bytes, md5(html) digest from pages")
def rel_strings(spark, d):
    return table(spark, d, "pages").select("page_id", F.lower(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)).alias("host"), F.length("html").cast("bigint").alias("chars"), F.octet_length("html").cast("bigint").alias("bytes"), F.md5("html").alias("digest"))


@query("rel_dates", "select extract(year from o_orderdate)::int y, extract(month from o_orderdate)::int m, count(*) n, max(date_diff('day', '1990-01-01'::date, o_orderdate::date)) last_day from orders group by all")
def rel_dates(spark, d):
    o = table(spark, d, "orders").select(F.to_date("o_orderdate").alias("t"))
    return o.groupBy(F.year("t").alias("y"), F.month("t").alias("m")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("t", F.lit("1990-01-01").cast("date"))).cast("bigint").alias("last_day"))


@query("rel_star", "select r_name region, n_name nation, count(*) n, round(sum(o_totalprice), 2) total from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by all")
def rel_star(spark, d):
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").alias("n_nationkey"))
    n = table(spark, d, "nation").select("n_nationkey", F.col("n_name").alias("nation"), F.col("n_regionkey").alias("r_regionkey"))
    r = table(spark, d, "region").select("r_regionkey", F.col("r_name").alias("region"))
    by = table(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("o_totalprice").alias("t"))
    return by.join(c, "o_custkey").join(n, "n_nationkey").join(r, "r_regionkey").groupBy("region", "nation").agg(F.sum("n").alias("n"), F.round(F.sum("t"), 2).alias("total"))


@query("rel_sketch")
def rel_sketch(spark, d):
    """Distinct users by type from mergeable sketches of each hour."""
    x = table(spark, d, "events").groupBy("event_type", F.window("ts", "1 hour").alias("w")).agg(F.hll_sketch_agg("user_id").alias("s"))
    return x.groupBy("event_type").agg(F.hll_sketch_estimate(F.hll_union_agg("s")).alias("users"))


@query("rel_reservoir", f"select event_type, event_id from events qualify row_number() over (partition by event_type order by {T.uniform_sql('event_id', '0')}, event_id) <= 50")
def rel_reservoir(spark, d):
    return relational.reservoir(table(spark, d, "events").select("event_type", "event_id"), 50, ["event_type"], "event_id")


@query("rel_stratified", f"select event_id from events where {T.uniform_sql('event_id', '0')} < case event_type when 'click' then 0.5 when 'view' then 0.1 else 0 end")
def rel_stratified(spark, d):
    return relational.stratified(table(spark, d, "events"), "event_type", {"click": 0.5, "view": 0.1}, "event_id").select("event_id")


@query("rel_count_min")
def rel_count_min(spark, d):
    return relational.count_min(table(spark, d, "events"), "event_type").select(F.length("sketch").alias("bytes"))


@query("rel_maps", "with m as (select event_type, map_from_entries(list(row(k, n) order by k)) as slots from (select event_type, (user_id % 4)::varchar k, count(*)::bigint n from events group by all) group by event_type) select event_type, cardinality(slots)::bigint n_slots, slots['1'] as first_slot, array_to_string(map_keys(slots), ',') keys from m")
def rel_maps(spark, d):
    by = table(spark, d, "events").groupBy("event_type", (F.col("user_id") % 4).cast("string").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    m = by.groupBy("event_type").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("k", "n")))).alias("slots"))
    return m.select("event_type", F.size("slots").cast("bigint").alias("n_slots"), F.col("slots")["1"].alias("first_slot"), F.array_join(F.map_keys("slots"), ",").alias("keys"))


@query("rel_variant", "select event_type, count(json_extract_string(props, '$.k')) n, sum(json_extract_string(props, '$.k')::bigint)::bigint total from events group by event_type")
def rel_variant(spark, d):
    """The same field through the variant type: parsed once, read by path and type."""
    k = F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint")
    return table(spark, d, "events").groupBy("event_type").agg(F.count(k).alias("n"), F.sum(k).alias("total"))


@query("rel_percent_rank", "select event_id, round(percent_rank() over (partition by event_type order by value), 9) pr, round(cume_dist() over (partition by event_type order by value), 9) cd from events")
def rel_percent_rank(spark, d):
    w = Window.partitionBy("event_type").orderBy("value")
    return table(spark, d, "events").select("event_id", F.round(F.percent_rank().over(w), 9).alias("pr"), F.round(F.cume_dist().over(w), 9).alias("cd"))


@query("rel_range_between", "select event_id, count(*) over (partition by user_id order by epoch(date_trunc('second', ts::timestamp))::bigint range between 3600 preceding and current row) n from events")
def rel_range_between(spark, d):
    t = F.unix_seconds(F.col("ts").cast("timestamp"))
    return table(spark, d, "events").withColumn("t", t).select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("t").rangeBetween(-3600, 0)).alias("n"))


@query("rel_null_handling", "select count(*) n, count(nullif(event_type, 'click')) others, sum(coalesce(json_extract_string(props, '$.k')::bigint, -1))::bigint filled, count(*) filter (where nullif(event_type, 'click') is not distinct from null) same from events")
def rel_null_handling(spark, d):
    e = table(spark, d, "events").withColumn("other", F.nullif("event_type", F.lit("click")))
    k = F.get_json_object("props", "$.k").cast("bigint")
    return e.agg(F.count(F.lit(1)).alias("n"), F.count("other").alias("others"), F.sum(F.coalesce(k, F.lit(-1))).alias("filled"), F.count_if(F.col("other").eqNullSafe(F.lit(None))).alias("same"))


@query("rel_sql_surface", "select n_name, count(*) n from customer join nation on c_nationkey = n_nationkey where c_custkey % 2 = 0 group by n_name having count(*) > 1")
def rel_sql_surface(spark, d):
    """Parameterised SQL over frames: no text is pasted into the statement and no name is left in the session."""
    return spark.sql(
        "select n_name, count(*) n from {customers} join {nations} on c_nationkey = n_nationkey where c_custkey % :by = 0 group by n_name having count(*) > :least",
        args={"by": 2, "least": 1},
        customers=table(spark, d, "customer"),
        nations=table(spark, d, "nation"),
    )


@query("rel_table_function", "select page_id, i pos, part from (select page_id, string_split(regexp_replace(url, '^[a-z]+://', ''), '/') ps from pages), unnest(range(1, len(ps) + 1)) t(i), unnest([ps[i]]) u(part)")
def rel_table_function(spark, d):
    """A table function in Arrow-free Python, called laterally; registered under a name of its own."""
    spark.udtf.register("corpusforge_url_parts", relational.UrlParts)
    return spark.sql("select page_id, p.pos, p.part from {pages}, lateral corpusforge_url_parts(url) p", pages=table(spark, d, "pages").select("page_id", "url"))


@query("rel_grouped_aggregate", "select event_type, round(quantile_cont(value, 0.9) - quantile_cont(value, 0.1), 6) spread from events group by event_type")
def rel_grouped_aggregate(spark, d):
    """The spread between deciles: built in, where the same as a pandas function would gather each group in one task."""
    return table(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.9)) - F.percentile("value", F.lit(0.1)), 6).alias("spread"))


for _kind in ("csv", "json", "orc", "parquet"):

    def _read_back(spark, d, kind=_kind):
        path = f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"
        write_files(table(spark, d, "benchmark").select("item_id", "text"), path, kind)
        return read_files(spark, path, kind, "item_id bigint, text string").select("item_id", F.md5("text").alias("digest"))

    query(f"io_read_back_{_kind}", "select item_id, md5(text) digest from benchmark")(_read_back)


@query("io_read_back_text", "select count(*) n from benchmark, unnest(string_split(text, chr(10))) t(line)")
def io_read_back_text(spark, d):
    path = f"{shared_folder(spark)}/files-{uuid.uuid4().hex}"
    write_files(table(spark, d, "benchmark").select("text"), path, "text")
    return read_files(spark, path, "text", "value string").agg(F.count(F.lit(1)).alias("n"))
