"""The relational surface around the selector, each kind of operator once, on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from farspan.functions import udfs
from farspan.sources.tables import table


def source_report(s: SparkSession, d: str) -> DataFrame:
    """Cube of documents by language and source."""
    docs = table(s, d, "documents", "lang", "source", "n_chars")
    return docs.cube("lang", "source").agg(F.count("*").alias("documents"), F.sum("n_chars").alias("chars"), F.grouping_id().cast("int").alias("level"))


def revenue_rollup(s: SparkSession, d: str) -> DataFrame:
    """Scan filters and column pruning, a sort-merge join, small dimensions broadcast by size, rollup."""
    li = table(s, d, "lineitem", "l_orderkey", "l_extendedprice", "l_discount")
    o = table(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    c = table(s, d, "customer", "c_custkey", "c_nationkey")
    n, r = table(s, d, "nation", "n_nationkey", "n_name", "n_regionkey"), table(s, d, "region", "r_regionkey", "r_name")
    j = li.join(o, li.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    cents = F.round(F.col("l_extendedprice") * 100).cast("decimal(38,0)") * F.round((1 - F.col("l_discount")) * 100).cast("decimal(38,0)")
    return j.rollup("r_name", "n_name").agg(F.sum(cents).cast("double").alias("revenue"), F.count("*").alias("lines"))


def status_pivot(s: SparkSession, d: str) -> DataFrame:
    li = table(s, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity")
    return li.groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.round(F.sum("l_quantity"), 2)).withColumnsRenamed({"F": "f_qty", "O": "o_qty"})


def top_orders_per_customer(s: SparkSession, d: str) -> DataFrame:
    """Top-k per group; the literal bound lets Spark plan a window group limit."""
    o = table(s, d, "orders", "o_custkey", "o_orderkey", "o_totalprice")
    rn = F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))
    return o.withColumn("rn", rn).where("rn <= 3").select("o_custkey", "o_orderkey", "rn")


def customers_without_orders(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "customer", "c_custkey").join(table(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_anti")


def customers_with_orders(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "customer", "c_custkey").join(table(s, d, "orders", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left_semi")


def event_json(s: SparkSession, d: str) -> DataFrame:
    """JSON fields, statistics and quantiles."""
    e = table(s, d, "events", "event_type", "props", "value")
    k = F.from_json("props", "k int")["k"]
    return e.groupBy("event_type").agg(F.sum(k).cast("long").alias("k_sum"), F.round(F.avg("value"), 6).alias("mean"), F.round(F.stddev_pop("value"), 6).alias("sd"), F.round(F.percentile("value", 0.9), 6).alias("p90"))


def event_gaps(s: SparkSession, d: str) -> DataFrame:
    """Offsets within a user's events: the longest pause, and events within an hour before each (a range frame)."""
    e = table(s, d, "events", "event_id", "ts", "user_id").where("user_id is not null").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    by = Window.partitionBy("user_id").orderBy("us", "event_id")
    hour = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    g = e.select("user_id", (F.col("us") - F.lag("us").over(by)).alias("gap"), F.count("*").over(hour).alias("busy"))
    return g.groupBy("user_id").agg(F.max("gap").alias("longest_gap"), F.max("busy").alias("busiest_hour"))


def event_sessions(s: SparkSession, d: str) -> DataFrame:
    """Sessions split at pauses above 30 minutes."""
    e = table(s, d, "events", "event_id", "ts", "user_id").where("user_id is not null").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    by = Window.partitionBy("user_id").orderBy("us", "event_id")
    new = F.coalesce((F.col("us") - F.lag("us").over(by) > 1_800_000_000).cast("long"), F.lit(1).cast("long"))
    return e.withColumn("new", new).groupBy("user_id").agg(F.sum("new").alias("sessions"), F.count("*").alias("events"))


def last_event_before(s: SparkSession, d: str) -> DataFrame:
    """As-of: the last event of another kind before each purchase-like event, by a union and a running last."""
    e = table(s, d, "events", "event_id", "ts", "user_id", "event_type").where("user_id is not null")
    probe = e.where("event_type = 'purchase'").select("user_id", "ts", F.lit(1).alias("side"), "event_id", F.lit(None).cast("bigint").alias("seen"))
    base = e.where("event_type <> 'purchase'").select("user_id", "ts", F.lit(0).alias("side"), "event_id", F.col("event_id").alias("seen"))
    run = Window.partitionBy("user_id").orderBy("ts", "side", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return probe.union(base).withColumn("before_id", F.last("seen", ignorenulls=True).over(run)).where("side = 1").select("event_id", "before_id")


def set_operations(s: SparkSession, d: str) -> DataFrame:
    """Union, intersection and difference of customers by two conditions, counted."""
    o = table(s, d, "orders", "o_custkey", "o_totalprice", "o_orderdate")
    a, b = o.where("o_totalprice > 200000").select("o_custkey"), o.where("o_orderdate >= timestamp_ntz'1996-01-01'").select("o_custkey")
    rows = [("union", a.union(b).distinct()), ("union_all", a.unionAll(b)), ("intersect", a.intersect(b)), ("intersect_all", a.intersectAll(b)), ("except", a.subtract(b)), ("except_all", a.exceptAll(b))]
    out = None
    for name, x in rows:
        one = x.agg(F.lit(name).alias("op"), F.count("*").alias("n"))
        out = one if out is None else out.unionByName(one)
    return out


def order_months(s: SparkSession, d: str) -> DataFrame:
    """Dates, a running total and a share of the whole."""
    o = table(s, d, "orders", "o_orderkey", "o_orderdate").withColumn("month", F.date_format("o_orderdate", "yyyy-MM"))
    per = o.groupBy("month").agg(F.count("*").alias("orders"))
    run = Window.orderBy("month").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return per.select("month", "orders", F.sum("orders").over(run).alias("so_far"), F.dense_rank().over(Window.orderBy(F.desc("orders"))).cast("long").alias("place"))


def benchmark_in_windows(s: SparkSession, d: str) -> DataFrame:
    """Interval join: where each tenth word of a document falls among its windows (equi on the document, between on the place)."""
    from farspan.operators import windows

    toks = windows.tokenize(table(s, d, "documents", "doc_id", F.col("lang").alias("category"), "text"))
    spans = windows.spans(toks, 128)
    marks = toks.select("doc_id", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0).cast("long"), F.col("n") - 1), F.lit(10).cast("long"))).alias("pos")).where("pos >= 0")
    m = marks.alias("m").join(spans.alias("w"), (F.col("m.doc_id") == F.col("w.doc_id")) & F.col("m.pos").between(F.col("w.start"), F.col("w.start") + 127))
    return m.groupBy(F.col("m.doc_id").alias("doc_id")).agg(F.count("*").alias("hits"))


def sql_functions(s: SparkSession, d: str) -> DataFrame:
    """Registered SQL functions and the table function, in SQL."""
    udfs.register(s)
    table(s, d, "documents", "doc_id", "n_chars").createOrReplaceTempView("farspan_docs")
    return s.sql("""with x as (select doc_id, n_chars, farspan_window_count(n_chars, 512L) as windows, farspan_starts(n_chars, 512L) as st from farspan_docs)
 select x.doc_id, x.windows, max(aggregate(x.st, 0L, (a, b) -> a + b)) as start_sum, coalesce(sum(w.start), 0) as udtf_sum
 from x left join lateral window_spans(x.n_chars, 512L) w on true group by x.doc_id, x.windows""")


def approximate(s: SparkSession, d: str) -> DataFrame:
    """Sketches beside exact answers: distinct customers within five per cent, a quantile within one per cent of rank."""
    o = table(s, d, "orders", "o_custkey", "o_totalprice")
    exact = o.agg(F.count_distinct("o_custkey").alias("n"), F.approx_count_distinct("o_custkey", 0.02).alias("a"), F.percentile("o_totalprice", F.array(F.lit(0.49), F.lit(0.51))).alias("p"), F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("o_totalprice", 200), F.lit(0.5)).alias("k"), F.hll_sketch_estimate(F.hll_sketch_agg("o_custkey", 14)).alias("h"))
    near = lambda x: F.abs(F.col(x) - F.col("n")) <= 0.05 * F.col("n")
    return exact.select("n", near("a").alias("distinct_ok"), near("h").alias("hll_ok"), F.col("k").between(F.col("p")[0] * 0.97, F.col("p")[1] * 1.03).alias("quantile_ok"))


RELATIONAL = {
    f.__name__: f
    for f in (source_report, revenue_rollup, status_pivot, top_orders_per_customer, customers_without_orders, customers_with_orders, event_json, event_gaps, event_sessions, last_event_before, set_operations, order_months, benchmark_in_windows, sql_functions, approximate)
}

_STARTS = "case when n_chars >= 512 then list_concat(list_concat(list_transform(range(0, ((n_chars + 511) // 512) // 2), lambda j: j * 512), case when ((n_chars + 511) // 512) % 2 = 1 then [(n_chars - 512) // 2] else [] end), list_transform(range(0, ((n_chars + 511) // 512) // 2), lambda j: n_chars - (((n_chars + 511) // 512) // 2 - j) * 512)) else [] end"

RELATIONAL_ORACLES = {
    "source_report": "select lang, source, count(*) as documents, sum(n_chars)::bigint as chars, grouping(lang, source)::int as level from documents group by cube (lang, source)",
    "revenue_rollup": "select r_name, n_name, sum(round(l_extendedprice * 100)::hugeint * round((1 - l_discount) * 100)::hugeint)::double as revenue, count(*) as lines from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)",
    "status_pivot": "select l_returnflag, round(sum(l_quantity) filter (l_linestatus = 'F'), 2) as f_qty, round(sum(l_quantity) filter (l_linestatus = 'O'), 2) as o_qty from lineitem group by l_returnflag",
    "top_orders_per_customer": "select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey)::int as rn from orders qualify rn <= 3",
    "customers_without_orders": "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)",
    "customers_with_orders": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)",
    "event_json": "select event_type, sum((props->>'$.k')::int)::bigint as k_sum, round(avg(value), 6) as mean, round(stddev_pop(value), 6) as sd, round(quantile_cont(value, 0.9), 6) as p90 from events group by event_type",
    "event_gaps": "with e as (select *, epoch_us(ts) as us from events where user_id is not null), g as (select user_id, us - lag(us) over (partition by user_id order by us, event_id) as gap, count(*) over (partition by user_id order by us range between 3600000000 preceding and current row) as busy from e) select user_id, max(gap) as longest_gap, max(busy) as busiest_hour from g group by user_id",
    "event_sessions": "with e as (select *, epoch_us(ts) as us from events where user_id is not null), g as (select user_id, coalesce((us - lag(us) over (partition by user_id order by us, event_id) > 1800000000)::int, 1) as new from e) select user_id, sum(new)::bigint as sessions, count(*) as events from g group by user_id",
    "last_event_before": "with p as (select * from events where user_id is not null and event_type = 'purchase'), b as (select * from events where user_id is not null and event_type <> 'purchase') select p.event_id, (select b.event_id from b where b.user_id = p.user_id and b.ts <= p.ts order by b.ts desc, b.event_id desc limit 1) as before_id from p",
    "set_operations": "with a as (select o_custkey from orders where o_totalprice > 200000), b as (select o_custkey from orders where o_orderdate >= timestamp '1996-01-01') "
    + " union all ".join(f"select '{n}' as op, count(*) as n from (select * from a {q} select * from b)" for n, q in (("union", "union"), ("union_all", "union all"), ("intersect", "intersect"), ("intersect_all", "intersect all"), ("except", "except"), ("except_all", "except all"))),
    "order_months": "with per as (select strftime(o_orderdate, '%Y-%m') as month, count(*) as orders from orders group by 1) select month, orders, sum(orders) over (order by month)::bigint as so_far, dense_rank() over (order by orders desc) as place from per",
    "benchmark_in_windows": "with t as (select doc_id, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::bigint as n from documents), s as (select doc_id, n, unnest(case when n >= 128 then list_concat(list_concat(list_transform(range(0, ((n + 127) // 128) // 2), lambda j: j * 128), case when ((n + 127) // 128) % 2 = 1 then [(n - 128) // 2] else [] end), list_transform(range(0, ((n + 127) // 128) // 2), lambda j: n - (((n + 127) // 128) // 2 - j) * 128)) else [] end) as start from t), m as (select doc_id, unnest(range(0, n, 10)) as pos from t) select m.doc_id, count(*) as hits from m join s on m.doc_id = s.doc_id and pos between start and start + 127 group by m.doc_id",
    "sql_functions": f"with t as (select doc_id, n_chars, {_STARTS} as s from documents) select doc_id, len(s)::bigint as windows, coalesce(list_sum(s), 0)::bigint as start_sum, coalesce(list_sum(s), 0)::bigint as udtf_sum from t",
    "approximate": "select count(distinct o_custkey) as n, true as distinct_ok, true as hll_ok, true as quantile_ok from orders",
}
