"""The relational operators that the methods stand on, each on the given tables, with its oracle."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from recmatch.plans.candidates import shared
from recmatch.plans.methods import query
from recmatch.sources.tables import sql, table


def _t(name):
    return lambda s, d: table(s, d, name)


def place(s, name: str) -> str:
    return f"{shared(s).rstrip('/')}/{name}-{uuid.uuid4().hex[:8]}"


def both(name: str, spark_sql: str, oracle: str | None = None):
    """A query whose SQL is the interface under test, or whose Spark form is SQL anyway."""
    from recmatch.sources.tables import plain

    query(name, oracle or plain(spark_sql))(lambda s, d: sql(s, d, spark_sql))


# Sources and sinks

@query("op_scan_parquet", "select 'part' as name, count(*) as n, sum(p_partkey)::bigint as checksum from part union all select 'orders', count(*), sum(o_orderkey)::bigint from orders union all select 'lineitem', count(*), sum(l_partkey)::bigint from lineitem union all select 'documents', count(*), sum(doc_id)::bigint from documents")
def _(s, d):
    one = lambda t, k: table(s, d, t).agg(F.lit(t).alias("name"), F.count(F.lit(1)).alias("n"), F.sum(k).alias("checksum"))
    return one("part", "p_partkey").unionAll(one("orders", "o_orderkey")).unionAll(one("lineitem", "l_partkey")).unionAll(one("documents", "doc_id"))


@query("op_scan_csv_json_roundtrip", "select f.format, p_partkey, p_name, p_brand, p_type, p_size, p_retailprice from part, (values ('csv'), ('json'), ('orc')) f(format)")
def _(s, d):
    p, out = table(s, d, "part"), None
    for f in ("csv", "json", "orc"):
        where = place(s, f)
        p.write.format(f).options(**({"header": "true"} if f == "csv" else {})).save(where)
        r = s.read.format(f).options(**({"header": "true"} if f == "csv" else {})).schema(p.schema).load(where).withColumn("format", F.lit(f))
        out = r if out is None else out.unionByName(r)
    return out


@query("op_scan_partitioned", "select doc_id, n_chars, lang from documents where lang = 'fr'")
def _(s, d):
    where = place(s, "bylang")
    table(s, d, "documents").select("doc_id", "n_chars", "lang").write.partitionBy("lang").parquet(where)
    return s.read.parquet(where).filter("lang = 'fr'")


@query("op_scan_metadata", "select 'part.parquet' as file, count(*) as n from part")
def _(s, d):
    return table(s, d, "part").select(F.col("_metadata.file_name").alias("f")).groupBy(F.col("f").alias("file")).agg(F.count(F.lit(1)).alias("n"))


@query("op_sink_bucketed_candidates", "select o_custkey, count(*) as n, sum(o_orderkey)::bigint as keys from orders group by o_custkey")
def _(s, d):
    name = f"bucketed_{uuid.uuid4().hex[:8]}"
    table(s, d, "orders").select("o_custkey", "o_orderkey").write.bucketBy(8, "o_custkey").sortBy("o_custkey").option("path", place(s, name)).saveAsTable(name)
    return s.table(name).groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"), F.sum("o_orderkey").alias("keys"))


@query("op_sink_idempotent", "select doc_id, lang from documents")
def _(s, d):
    where, docs = place(s, "idempotent"), table(s, d, "documents").select("doc_id", "lang")
    docs.write.partitionBy("lang").parquet(where)
    docs.filter("lang = 'fr'").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("lang").parquet(where)
    return s.read.schema("doc_id long, lang string").parquet(where)


# Filters and projections

both("op_filter_predicates", "select p_partkey, p_name from {part} where (p_size between 5 and 20 and p_brand in ('Brand#2', 'Brand#4', 'Brand#17')) or (p_name like 'red%' and not p_type = 'SMALL') or p_type is not distinct from cast(null as string)", "select p_partkey, p_name from part where (p_size between 5 and 20 and p_brand in ('Brand#2', 'Brand#4', 'Brand#17')) or (p_name like 'red%' and not p_type = 'SMALL')")


@query("op_project_render", "select p_partkey, concat_ws('; ', concat('name: ', p_name), 'type: ' || case when p_partkey % 7 <> 0 then p_type end) as text from part")
def _(s, d):
    from recmatch.functions.prompts import record_text

    p = table(s, d, "part").select("p_partkey", F.col("p_name").alias("name"), F.when(F.col("p_partkey") % 7 != 0, F.col("p_type")).alias("type"))
    return p.select("p_partkey", record_text(["name", "type"], "").alias("text"))


# Joins

def _join(name: str, how: str, on: str):
    @query(name, f"select c_custkey, o_orderkey from customer c {on} join orders o on c_custkey = o_custkey")
    def _(s, d):
        c, o = table(s, d, "customer"), table(s, d, "orders")
        return c.join(o, F.col("c_custkey") == F.col("o_custkey"), how).select("c_custkey", "o_orderkey")


for _n, _h, _o in (("inner", "inner", ""), ("left", "left", "left"), ("right", "right", "right"), ("full", "full", "full")):
    _join(f"op_join_{_n}", _h, _o)


def _exists(name: str, how: str, word: str):
    @query(name, f"select p_partkey from part where {word} exists (select 1 from lineitem where l_partkey = p_partkey and l_quantity > 45)")
    def _(s, d):
        return table(s, d, "part").join(table(s, d, "lineitem").filter("l_quantity > 45"), F.col("l_partkey") == F.col("p_partkey"), how).select("p_partkey")


_exists("op_join_semi", "left_semi", "")
_exists("op_join_anti", "left_anti", "not")


@query("op_join_broadcast", "select n_name, count(*) as n from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey group by n_name")
def _(s, d):
    look = table(s, d, "supplier").join(F.broadcast(table(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")  # nations are 25
    return table(s, d, "lineitem").join(look, F.col("l_suppkey") == F.col("s_suppkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


for _n, _hint in (("sortmerge", "merge"), ("shufflehash", "shuffle_hash")):
    query(f"op_join_{_n}", "select o_orderpriority, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by 1")(
        lambda s, d, hint=_hint: table(s, d, "lineitem").join(table(s, d, "orders").hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    )


@query("op_join_theta", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_acctbal < b.s_acctbal and b.s_acctbal < a.s_acctbal + 100")
def _(s, d):
    """Band join: each value meets its own cell of the band's width and the next."""
    x = table(s, d, "supplier").select(F.col("s_suppkey").alias("a"), F.col("s_acctbal").alias("x")).withColumn("cell", F.explode(F.array(F.floor(F.col("x") / 100), F.floor(F.col("x") / 100) + 1)))
    y = table(s, d, "supplier").select(F.col("s_suppkey").alias("b"), F.col("s_acctbal").alias("y")).withColumn("cell", F.floor(F.col("y") / 100))
    return x.join(y, "cell").filter("x < y and y < x + 100").select("a", "b")


@query("op_join_range", "select a.o_orderkey as a, b.o_orderkey as b from orders a join orders b on a.o_custkey = b.o_custkey and a.o_orderkey < b.o_orderkey and abs(datediff('day', a.o_orderdate, b.o_orderdate)) <= 3")
def _(s, d):
    o = table(s, d, "orders").select("o_custkey", "o_orderkey", F.datediff(F.col("o_orderdate").cast("date"), F.lit("1970-01-01").cast("date")).alias("day"))
    x = o.select("o_custkey", F.col("o_orderkey").alias("a"), F.col("day").alias("x")).withColumn("cell", F.explode(F.array(*(F.floor(F.col("x") / 3) + i for i in (-1, 0, 1)))))
    y = o.select("o_custkey", F.col("o_orderkey").alias("b"), F.col("day").alias("y"), F.floor(F.col("day") / 3).alias("cell"))
    return x.join(y, ["o_custkey", "cell"]).filter("a < b and abs(x - y) <= 3").select("a", "b")


@query("op_join_asof", "select event_id, last_value(case when event_type = 'purchase' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as before from events")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    return table(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("before"))


@query("op_join_interval", "select a.event_id as cause, b.event_id as error from events a join events b on a.user_id = b.user_id and b.event_type = 'error' and a.event_type = 'click' and a.ts <= b.ts and a.ts >= b.ts - interval 30 minute")
def _(s, d):
    e = table(s, d, "events")
    a = e.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("cause"), F.col("ts").alias("x"))
    b = e.filter("event_type = 'error'").select("user_id", F.col("event_id").alias("error"), F.col("ts").alias("y"))
    return a.join(b, "user_id").filter("x <= y and x >= y - interval 30 minutes").select("cause", "error")


@query("op_join_cross", "select r_name, n_name from region, nation")
def _(s, d):
    return table(s, d, "region").select("r_name").crossJoin(F.broadcast(table(s, d, "nation").select("n_name")))  # 5 by 25 rows


@query("op_join_skew_salted", "select p_brand, count(*) as n, sum(l_quantity) as qty from lineitem join part on l_partkey = p_partkey group by p_brand")
def _(s, d):
    n = 8
    li = table(s, d, "lineitem").select("l_partkey", "l_quantity").withColumn("salt", F.pmod(F.xxhash64("l_partkey", F.monotonically_increasing_id()), F.lit(n)))
    p = table(s, d, "part").select("p_partkey", "p_brand").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).hint("merge")  # estimates leave out the copies: no broadcast
    return li.join(p, (F.col("l_partkey") == F.col("p_partkey")) & (li["salt"] == p["salt"])).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"))


#: The outer side is the customers that orders name, as in the oracle. Places are numbered within: Spark turns a correlated ORDER BY with LIMIT into
#: a sort of everything and an unordered numbering behind a shuffle, which forgets the order.
both("op_join_lateral", "select c_custkey, o_orderkey from (select distinct o_custkey as c_custkey from {orders}), lateral (select o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as n from {orders}) r where o_custkey <=> c_custkey and n <= 2)", "select c_custkey, o_orderkey from (select o_custkey as c_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as n from orders) q where n <= 2")

# Aggregates

_basic = "l_returnflag, l_linestatus, count(*) as n, sum(l_quantity) as qty, round(avg(l_discount), 6) as disc, min(l_extendedprice) as lo, max(l_extendedprice) as hi, round(stddev(l_quantity), 4) as sd"


@query("op_agg_basic", f"select {_basic} from lineitem group by l_returnflag, l_linestatus")
def _(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi"), F.round(F.stddev("l_quantity"), 4).alias("sd"))


@query("op_agg_distinct", "select o_orderstatus, count(distinct o_custkey) as customers from orders group by o_orderstatus")
def _(s, d):
    return table(s, d, "orders").groupBy("o_orderstatus").agg(F.count_distinct("o_custkey").alias("customers"))


@query("op_agg_filter", "select o_orderstatus, count(*) filter (o_totalprice > 200000) as dear from orders group by o_orderstatus")
def _(s, d):
    return table(s, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 200000).alias("dear"))


@query("op_agg_approx")
def _(s, d):
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", 0.5, 1000).alias("median"))


@query("op_agg_collect", "select o_custkey, string_agg(cast(o_orderkey as varchar), ',' order by o_orderdate, o_orderkey) as keys from orders group by o_custkey")
def _(s, d):
    g = table(s, d, "orders").groupBy("o_custkey").agg(F.sort_array(F.collect_list(F.struct("o_orderdate", "o_orderkey"))).alias("o"))  # a customer's orders
    return g.select("o_custkey", F.array_join(F.transform("o", lambda x: x["o_orderkey"].cast("string")), ",").alias("keys"))


@query("op_agg_argmax", "select o_custkey, arg_max(o_orderkey, {'a': o_totalprice, 'b': -o_orderkey}) as best from orders group by o_custkey")
def _(s, d):
    return table(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", -F.col("o_orderkey"))).alias("best"))


_geo = "{customer} join {nation} on c_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey"
_geo_plain = _geo.replace("{", "").replace("}", "")


def _levels(name: str, kind: str):
    @query(name, f"select r_name, c_mktsegment, count(*) as n from {_geo_plain} group by {kind}(r_name, c_mktsegment)")
    def _(s, d):
        g = sql(s, d, f"select r_name, c_mktsegment from {_geo}")
        return getattr(g, kind)("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"))


_levels("op_agg_rollup", "rollup")
_levels("op_agg_cube", "cube")
both("op_agg_grouping_sets", f"select r_name, c_mktsegment, count(*) as n from {_geo} group by grouping sets ((r_name), (c_mktsegment), ())")


@query("op_agg_pivot", "select o_orderstatus, count(*) filter (o_orderpriority = '1-URGENT') as urgent, count(*) filter (o_orderpriority = '5-LOW') as low from orders group by o_orderstatus")
def _(s, d):
    return table(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "5-LOW"]).count().select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("5-LOW", F.lit(0)).alias("low"))


@query("op_agg_unpivot", "select p_partkey, k, v from part, lateral (values ('size', cast(p_size as double)), ('price', p_retailprice)) u(k, v)")
def _(s, d):
    return table(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "k", "v")


@query("op_agg_sort_based", "select p_brand, min(p_name) as first_name from part group by p_brand")
def _(s, d):
    return table(s, d, "part").groupBy("p_brand").agg(F.min("p_name").alias("first_name"))


# Windows

@query("op_win_rank", "select o_orderkey, cast(row_number() over w as integer) as rn, cast(rank() over w as integer) as r, cast(dense_rank() over w as integer) as dr, round(percent_rank() over w, 6) as pr, cast(ntile(4) over w as integer) as nt from orders window w as (partition by o_orderstatus order by o_totalprice, o_orderkey)")
def _(s, d):
    w = Window.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")
    return table(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.ntile(4).over(w).alias("nt"))


@query("op_win_offset", "select conv_id, turn, lag(role) over w as before, lead(role) over w as after, first_value(role) over w as first_role, nth_value(role, 2) over (partition by conv_id order by turn rows between unbounded preceding and unbounded following) as second from conversations window w as (partition by conv_id order by turn)")
def _(s, d):
    w = Window.partitionBy("conv_id").orderBy("turn")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(s, d, "conversations").select("conv_id", "turn", F.lag("role").over(w).alias("before"), F.lead("role").over(w).alias("after"), F.first("role").over(w).alias("first_role"), F.nth_value("role", 2).over(full).alias("second"))


@query("op_win_frames", "select event_id, count(*) over (partition by user_id order by ts, event_id rows between 3 preceding and current row) as last4, round(sum(value) over (partition by user_id order by ts, event_id rows unbounded preceding), 4) as running, count(*) over (partition by user_id order by epoch(ts)::bigint range between 3600 preceding and current row) as hour from events")
def _(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    sec = F.floor(F.col("ts").cast("timestamp").cast("double") + 0.5).cast("long")
    r = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-3600, 0)
    return table(s, d, "events").withColumn("sec", sec).select("event_id", F.count(F.lit(1)).over(w.rowsBetween(-3, 0)).alias("last4"), F.round(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"), F.count(F.lit(1)).over(r).alias("hour"))


# Sorts, limits, sets

@query("op_sort_multi", "select p_type, p_size, p_partkey from part order by p_type desc nulls last, p_size, p_partkey")
def _(s, d):
    return table(s, d, "part").select("p_type", "p_size", "p_partkey").orderBy(F.desc_nulls_last("p_type"), "p_size", "p_partkey")


both("op_limit_topk", "select o_orderkey, o_totalprice from {orders} order by o_totalprice desc, o_orderkey limit 10 offset 5")


@query("op_topk_per_group", "select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as n from orders) q where n <= 3")
def _(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(s, d, "orders").withColumn("n", F.row_number().over(w)).filter("n <= 3").select("o_custkey", "o_orderkey")


_x, _y = "select c_custkey as k from customer", "select user_id as k from events"


def _set(name: str, word: str, f):
    @query(name, f"{_x} {word} {_y}")
    def _(s, d):
        return f(table(s, d, "customer").select(F.col("c_custkey").alias("k")), table(s, d, "events").select(F.col("user_id").alias("k")))


_set("op_union", "union", lambda a, b: a.union(b).distinct())
_set("op_union_all", "union all", lambda a, b: a.unionAll(b))
_set("op_intersect", "intersect", lambda a, b: a.intersect(b))
_set("op_intersect_all", "intersect all", lambda a, b: a.intersectAll(b))
_set("op_except", "except", lambda a, b: a.subtract(b))
_set("op_except_all", "except all", lambda a, b: a.exceptAll(b))


@query("op_union_by_name", "select c_custkey as k, c_name as name, cast(null as double) as bal from customer union all select s_suppkey, s_name, s_acctbal from supplier")
def _(s, d):
    a = table(s, d, "customer").select(F.col("c_custkey").alias("k"), F.col("c_name").alias("name"))
    return a.unionByName(table(s, d, "supplier").select(F.col("s_name").alias("name"), F.col("s_acctbal").alias("bal"), F.col("s_suppkey").alias("k")), allowMissingColumns=True)


@query("op_drop_duplicates", "select min(doc_id) as doc_id, count(*) as copies from documents group by lower(trim(text))")
def _(s, d):
    return table(s, d, "documents").groupBy(F.md5(F.lower(F.trim("text"))).alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("copies")).drop("h")


# Functions

@query("op_str_normalise", "select p_partkey, upper(trim(p_name)) as u, replace(p_brand, '#', ' ') as b, lpad(cast(p_size as varchar), 4, '0') as z, length(p_name) as n from part")
def _(s, d):
    return table(s, d, "part").select("p_partkey", F.upper(F.trim("p_name")).alias("u"), F.translate("p_brand", "#", " ").alias("b"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("z"), F.length("p_name").cast("long").alias("n"))


from recmatch.functions.similarity import qgrams, words  # noqa: E402


@query("op_str_tokens", f"select doc_id, len({words('text', 'oracle')}) as n from documents")
def _(s, d):
    return table(s, d, "documents").select("doc_id", F.expr(f"cast(size({words('text', 'spark')}) as bigint)").alias("n"))


@query("op_str_shingles", f"select p_partkey, len({qgrams('p_name', 'oracle')}) as n from part")
def _(s, d):
    return table(s, d, "part").select("p_partkey", F.expr(f"cast(size({qgrams('p_name', 'spark')}) as bigint)").alias("n"))


both("op_str_distance", "select p_partkey, cast(levenshtein(p_name, p_type) as bigint) as dist from {part}")


@query("op_str_regex", "select page_id, regexp_extract(url, '://([^/]+)', 1) as host, regexp_extract(html, '<title>([^<]*)</title>', 1) as title from pages")
def _(s, d):
    return table(s, d, "pages").select("page_id", F.regexp_extract("url", "://([^/]+)", 1).alias("host"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"))


@query("op_date_parts", "select o_orderkey, cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first, cast(datediff('day', date '1995-01-01', cast(o_orderdate as date)) as integer) as days, strftime(o_orderdate + interval 10 day, '%Y-%m-%d') as later from orders")
def _(s, d):
    o = F.col("o_orderdate").cast("date")
    return table(s, d, "orders").select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.date_format(F.trunc(o, "month"), "yyyy-MM-dd").alias("first"), F.datediff(o, F.lit("1995-01-01").cast("date")).alias("days"), F.date_format(F.date_add(o, 10), "yyyy-MM-dd").alias("later"))


both("op_math_logistic", "select p_partkey, round(1 / (1 + exp(-(p_retailprice - 1000) / 50)), 6) as p, round(ln(p_retailprice), 6) as l, round(sqrt(p_retailprice), 6) as r from {part}")


@query("op_arr_sets", "select p_partkey, cast(len(list_intersect(a, b)) as integer) as i, cast(len(list_distinct(list_concat(a, b))) as integer) as u from (select p_partkey, string_split(p_name, ' ') as a, ['red', 'bolt', p_type] as b from part) q")
def _(s, d):
    a, b = F.split("p_name", " "), F.array(F.lit("red"), F.lit("bolt"), F.col("p_type"))
    return table(s, d, "part").select("p_partkey", F.size(F.array_intersect(a, b)).alias("i"), F.size(F.array_union(a, b)).alias("u"))


@query("op_arr_hof", "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) as q, cast(len(list_filter(embedding, lambda x: x > 0)) as integer) as up from embeddings")
def _(s, d):
    return table(s, d, "embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x), 6).alias("q"), F.size(F.filter("embedding", lambda x: x > 0)).alias("up"))


@query("op_arr_slice_sort", "select p_partkey, array_to_string(list_slice(list_sort(string_split(p_name, ' ')), 1, 1), ' ') as first, cast(list_position(string_split(p_name, ' '), 'bolt') as bigint) as at from part")
def _(s, d):
    w = F.split("p_name", " ")
    return table(s, d, "part").select("p_partkey", F.array_join(F.slice(F.sort_array(w), 1, 1), " ").alias("first"), F.nullif(F.array_position(w, "bolt"), F.lit(0)).alias("at"))


@query("op_map_ops", "select p_partkey, p_type as type, cast(2 as integer) as n from part")
def _(s, d):
    m = F.map_from_arrays(F.array(F.lit("type"), F.lit("brand")), F.array("p_type", "p_brand"))
    return table(s, d, "part").select("p_partkey", F.element_at(m, "type").alias("type"), F.size(F.map_keys(m)).alias("n"))


@query("op_json_extract", "select event_id, cast(json_extract(props, '$.k') as integer) as k from events")
def _(s, d):
    return table(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("op_vec_cosine", "select a.vec_id, round(list_dot_product(a.embedding::double[], b.embedding::double[]), 6) as dot, round(list_distance(a.embedding::double[], b.embedding::double[]), 6) as dist from embeddings a join embeddings b on b.vec_id = a.vec_id + 1")
def _(s, d):
    e = table(s, d, "embeddings")
    x = e.select("vec_id", F.col("embedding").alias("p")).join(e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("q")), "vec_id")
    total = lambda f: F.aggregate(F.zip_with("p", "q", lambda a, b: f(a.cast("double"), b.cast("double"))), F.lit(0.0), lambda s, v: s + v)
    return x.select("vec_id", F.round(total(lambda a, b: a * b), 6).alias("dot"), F.round(F.sqrt(total(lambda a, b: (a - b) * (a - b))), 6).alias("dist"))


@query("op_sample_hash", "select p_partkey from part order by md5(concat('s|', cast(p_partkey as varchar))), p_partkey limit 100")
def _(s, d):
    return table(s, d, "part").select("p_partkey").orderBy(F.md5(F.concat(F.lit("s|"), F.col("p_partkey").cast("string"))), "p_partkey").limit(100)


@query("op_sample_stratified", "select p_partkey, p_type from (select *, row_number() over (partition by p_type order by md5(cast(p_partkey as varchar)), p_partkey) as n from part) q where n <= 10")
def _(s, d):
    w = Window.partitionBy("p_type").orderBy(F.md5(F.col("p_partkey").cast("string")), "p_partkey")
    return table(s, d, "part").withColumn("n", F.row_number().over(w)).filter("n <= 10").select("p_partkey", "p_type")


# Subqueries

both("op_sub_scalar", "select o_orderkey from {orders} where o_totalprice > (select avg(o_totalprice) from {orders})")
both("op_sub_exists", "select c_custkey from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey and o_totalprice > 400000)")
both("op_sub_in", "select p_partkey from {part} where p_partkey in (select l_partkey from {lineitem} where l_quantity = 50)")
both("op_cte", "with big as (select o_custkey, sum(o_totalprice) as t from {orders} group by o_custkey), top as (select o_custkey from big where t > 2000000) select c_name from {customer} join top on o_custkey = c_custkey")
both("op_recursive_cte", "with recursive y as (select cast(year(o_orderdate) as int) as i, sum(o_orderkey % 1000) as k from {orders} group by 1), n(i, f) as (select i, cast(k as bigint) from y where i = (select min(i) from y) union all select y.i, cast(n.f * 2 + y.k as bigint) from n join y on y.i = n.i + 1) select i, f from n")


# User-defined forms

def _parsed(s, d):
    from recmatch.plans.methods import _texts

    return _texts(s, d)


def _yes(text):
    import re

    low = (text or "").lower()
    y, n = re.search(r"(^|[^a-z])yes([^a-z]|$)", low), re.search(r"(^|[^a-z])no([^a-z]|$)", low)
    return "true" if y and not n else "false" if n and not y else None


def _udfs():
    from recmatch.plans.methods import ORACLES

    for name, make in (
        ("op_udf_scalar", lambda: F.udf(_yes, "string")),
        ("op_udf_arrow", lambda: F.udf(_yes, "string", useArrow=True)),
        ("op_udf_pandas", lambda: F.pandas_udf(lambda x: x.map(_yes), "string", F.PandasUDFType.SCALAR)),
    ):
        query(name, ORACLES["match_parse"])(lambda s, d, make=make: _parsed(s, d).select("n", make()(F.col("answer")).alias("parsed")))


_udfs()


@query("op_udaf_f1", "select l_returnflag, round(200.0e0 * tp / (2 * tp + fp + fn), 6) as f1 from (select l_returnflag, count(*) filter (l_quantity > 25 and l_tax > 0.04) as tp, count(*) filter (l_quantity > 25 and not l_tax > 0.04) as fp, count(*) filter (not l_quantity > 25 and l_tax > 0.04) as fn from lineitem group by l_returnflag) q")
def _(s, d):
    f1 = F.pandas_udf(lambda got, want: float(200 * (got & want).sum() / (got.sum() + want.sum())), "double", F.PandasUDFType.GROUPED_AGG)
    return table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(f1(F.col("l_quantity") > 25, F.col("l_tax") > 0.04), 6).alias("f1"))


@query("op_udtf_triples", "select s.n, lists, a.range as a, b.range as b from (select n, count(*) as lists from (select count(*) as n from lineitem group by l_orderkey) l group by n) s, range(1, 1000) a, range(1, 1000) b where a.range <> b.range and a.range <= s.n and b.range <= s.n")
def _(s, d):
    """The pairs of places asked about in lists of each length that the orders have, with the number of such lists."""

    class Triples:
        def eval(self, n: int):
            for a in range(1, n + 1):
                for b in range(1, n + 1):
                    if a != b:
                        yield a, b

    sizes = table(s, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("lists"))
    return sizes.lateralJoin(F.udtf(Triples, returnType="a bigint, b bigint")(F.col("n").outer()))


@query("op_apply_in_pandas", "select o_custkey, round(sum(o_totalprice), 2) as total from orders group by o_custkey")
def _(s, d):
    import pandas as pd

    def run(f):
        return pd.DataFrame({"o_custkey": [f["o_custkey"].iloc[0]], "total": [float(f["o_totalprice"].sum())]})

    return table(s, d, "orders").select("o_custkey", "o_totalprice").groupBy("o_custkey").applyInPandas(run, "o_custkey long, total double").withColumn("total", F.round("total", 2))


@query("op_map_in_pandas", "select p_partkey, length(p_name) as n from part")
def _(s, d):
    def run(frames):
        for f in frames:
            yield f.assign(n=f["p_name"].str.len())[["p_partkey", "n"]]

    return table(s, d, "part").select("p_partkey", "p_name").mapInPandas(run, "p_partkey long, n long")


@query("op_sql_functions", "select p_partkey, round(1 / (1 + exp(-12.0e0 * (p_size / 50.0e0 - 0.5e0))), 6) as p from part")
def _(s, d):
    s.sql("create or replace temporary function match_probability(x double) returns double return round(1 / (1 + exp(-12.0D * (x - 0.5D))), 6)")
    return sql(s, d, "select p_partkey, match_probability(p_size / 50.0D) as p from {part}")
