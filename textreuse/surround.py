"""Relational operators, functions and round trips that users of the methods need, on the given tables."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .operators import relational as ops
from .registry import query
from .sources import io
from .sources.catalog import load

DEC = "decimal(18,2)"
money = lambda c: F.round(F.sum(F.col(c).cast(DEC)).cast("double"), 2)


@query("rel_scan_project", "select l_orderkey, l_linenumber::bigint as l_linenumber, round(l_extendedprice * (1 - l_discount), 4) as net from lineitem where l_shipdate >= timestamp '1997-01-01'")
def rel_scan_project(spark, sf_dir):
    rows = load(spark, sf_dir, "lineitem").where("l_shipdate >= timestamp '1997-01-01'")
    return rows.select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("rel_filter_predicates", "select o_orderkey from orders where o_orderpriority in ('1-URGENT', '2-HIGH') and o_totalprice between 1000 and 100000 and o_orderstatus <> 'P'")
def rel_filter_predicates(spark, sf_dir):
    o = load(spark, sf_dir, "orders")
    return o.where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_totalprice").between(1000, 100_000) & (F.col("o_orderstatus") != "P")).select("o_orderkey")


@query("rel_null_predicates", "select count(*) filter (quality = 1) as good, count(*) filter (quality <> 1) as bad, count(*) filter (quality is null) as missing, count(*) filter (quality is not distinct from null) as safe from documents left join labels using (doc_id)")
def rel_null_predicates(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    q = F.col("quality")
    return rows.agg(F.count_if(q == 1).alias("good"), F.count_if(q != 1).alias("bad"), F.count_if(q.isNull()).alias("missing"), F.count_if(q.eqNullSafe(F.lit(None))).alias("safe"))


def _join(name: str, how: str, hint: str | None, text: str) -> None:
    @query(name, text)
    def joined(spark, sf_dir):
        l, o = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")  # noqa: E741
        rows = l.join(o.hint(hint) if hint else o, l["l_orderkey"] == o["o_orderkey"], how)
        return rows.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.col("l_quantity").cast(DEC)).cast("double"), 2).alias("quantity"))


_AGG = "select o_orderstatus, count(*) as n, round(sum(l_quantity::decimal(18,2))::double, 2) as quantity from lineitem join orders on l_orderkey = o_orderkey group by 1"
_join("rel_join_merge", "inner", "merge", _AGG)
_join("rel_join_hash", "inner", "shuffle_hash", _AGG)


@query("rel_join_broadcast", "select r_name, count(*) as nations from nation join region on n_regionkey = r_regionkey group by 1")
def rel_join_broadcast(spark, sf_dir):
    n, r = load(spark, sf_dir, "nation"), load(spark, sf_dir, "region")
    return n.join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"]).groupBy("r_name").agg(F.count(F.lit(1)).alias("nations"))


@query("rel_join_left", "select d.doc_id, l.quality::bigint as quality from documents d left join labels l using (doc_id)")
def rel_join_left(spark, sf_dir):
    return load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")


@query("rel_join_semi", "select c_custkey from customer semi join orders on c_custkey = o_custkey")
def rel_join_semi(spark, sf_dir):
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey")


@query("rel_join_anti", "select c_custkey from customer anti join orders on c_custkey = o_custkey")
def rel_join_anti(spark, sf_dir):
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


@query("rel_join_full", "select coalesce(c.c_nationkey, s.s_nationkey)::bigint as nation, customers, suppliers from (select c_nationkey, count(*) as customers from customer group by 1) c full join (select s_nationkey, count(*) as suppliers from supplier group by 1) s on c.c_nationkey = s.s_nationkey")
def rel_join_full(spark, sf_dir):
    c = load(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    s = load(spark, sf_dir, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(s, "nation", "full")


@query("rel_join_cross", "select a.n_nationkey::bigint as a, b.r_regionkey::bigint as b from nation a cross join region b")
def rel_join_cross(spark, sf_dir):
    return load(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("a")).crossJoin(load(spark, sf_dir, "region").select(F.col("r_regionkey").alias("b")))


@query("rel_join_theta", "select a.n_nationkey::bigint as a, b.n_nationkey::bigint as b from nation a join nation b on a.n_regionkey = b.n_regionkey and a.n_nationkey < b.n_nationkey")
def rel_join_theta(spark, sf_dir):
    n = load(spark, sf_dir, "nation")
    a, b = n.select("n_regionkey", F.col("n_nationkey").alias("a")), n.select("n_regionkey", F.col("n_nationkey").alias("b"))
    return a.join(b, "n_regionkey").where("a < b").select("a", "b")


_SPANS = "(select user_id, event_id, floor(epoch(ts))::bigint as s, floor(epoch(ts))::bigint + 600 as e, event_type from events)"


@query("rel_join_interval", f"select v.event_id as view, p.event_id as purchase from {_SPANS} v join {_SPANS} p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and v.s < p.e and p.s < v.e")
def rel_join_interval(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("s", F.unix_timestamp("ts"))
    kind = lambda k, n: e.where(F.col("event_type") == k).select("user_id", F.col("event_id").alias(n), F.col("s").alias(f"{n}_s"), (F.col("s") + 600).alias(f"{n}_e"))
    out = ops.interval_join(kind("view", "view"), kind("purchase", "purchase"), ["user_id"], ("view_s", "view_e"), ("purchase_s", "purchase_e"), 3600)
    return out.select("view", "purchase")


@query("rel_join_asof", "with p as (select * from events where event_type = 'purchase'), v as (select user_id, ts, max(event_id) as event_id from events where event_type = 'view' group by 1, 2) select p.event_id, v.event_id as last_view from p asof left join v on p.user_id = v.user_id and p.ts >= v.ts")
def rel_join_asof(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    views = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("last_view"))
    return ops.as_of(e.where("event_type = 'purchase'").select("user_id", "ts", "event_id"), views, "user_id", "ts", ["last_view"]).select("event_id", "last_view")


@query("rel_lateral_topk", "select n_nationkey::bigint as n_nationkey, t.c_custkey from nation, lateral (select c_custkey from customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2) t")
def rel_lateral_topk(spark, sf_dir):
    c = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("n_nationkey"), "c_custkey", "c_acctbal")
    return ops.top_per_group(c, "n_nationkey", [F.col("c_acctbal").desc(), F.col("c_custkey")], 2).select("n_nationkey", "c_custkey")


# Aggregates


@query("rel_agg_hash", "select l_returnflag, l_linestatus, count(*) as n, round(sum(l_quantity::decimal(18,2))::double, 2) as quantity, min(l_discount) as lo, max(l_discount) as hi from lineitem group by 1, 2")
def rel_agg_hash(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), money("l_quantity").alias("quantity"), F.min("l_discount").alias("lo"), F.max("l_discount").alias("hi"))


@query("rel_agg_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")
def rel_agg_distinct(spark, sf_dir):
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("rel_agg_approx", "select l_returnflag, count(distinct l_partkey) as exact, true as within from lineitem group by 1")
def rel_agg_approx(spark, sf_dir):
    g = load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("e"))
    return g.select("l_returnflag", F.col("e").alias("exact"), (F.abs(F.col("a") - F.col("e")) <= 0.05 * F.col("e")).alias("within"))


_SETS = "select o_orderstatus, o_orderpriority, count(*) as n, grouping_id(o_orderstatus, o_orderpriority) as level from orders group by "


@query("rel_grouping_sets", _SETS + "grouping sets ((o_orderstatus), (o_orderpriority), ())")
def rel_grouping_sets(spark, sf_dir):
    cols = ["o_orderstatus", "o_orderpriority"]
    o = load(spark, sf_dir, "orders").select(*cols)
    return o.groupingSets([[o["o_orderstatus"]], [o["o_orderpriority"]], []], *cols).agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


def _cubes(name: str, how: str) -> None:
    @query(name, f"{_SETS}{how} (o_orderstatus, o_orderpriority)")
    def cubed(spark, sf_dir):
        return getattr(load(spark, sf_dir, "orders"), how)("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("level"))


_cubes("rel_rollup", "rollup")
_cubes("rel_cube", "cube")


@query("rel_pivot", "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as \"F\", count(*) filter (o_orderstatus = 'O') as \"O\", count(*) filter (o_orderstatus = 'P') as \"P\" from orders group by 1")
def rel_pivot(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


@query("rel_percentile", "select o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) as median, round(quantile_cont(o_totalprice, 0.9), 4) as p90 from orders group by 1")
def rel_percentile(spark, sf_dir):
    return load(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("o_totalprice", F.lit(0.9)), 4).alias("p90"))


@query("rel_agg_filtered", "select count(*) filter (p_size > 25) as large, count(*) filter (p_size <= 25) as small, bool_and(p_size > 0) as positive from part")
def rel_agg_filtered(spark, sf_dir):
    return load(spark, sf_dir, "part").agg(F.count_if(F.col("p_size") > 25).alias("large"), F.count_if(F.col("p_size") <= 25).alias("small"), F.bool_and(F.col("p_size") > 0).alias("positive"))


@query("rel_mode_max_by", "with n as (select p_brand, p_type, count(*) as n from part group by 1, 2), m as (select p_brand, p_type, row_number() over (partition by p_brand order by n desc, p_type) as k from n), d as (select p_brand, max(struct_pack(a := p_retailprice, b := p_partkey)) as x from part group by 1) select m.p_brand, p_type as common_type, x.b as dearest from m join d using (p_brand) where k = 1")
def rel_mode_max_by(spark, sf_dir):
    p = load(spark, sf_dir, "part")
    common = ops.top_per_group(p.groupBy("p_brand", "p_type").count(), "p_brand", [F.col("count").desc(), F.col("p_type")], 1).select("p_brand", F.col("p_type").alias("common_type"))
    return common.join(p.groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("dearest")), "p_brand")


# Windows


def _by_customer():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


_W = "(partition by o_custkey order by o_orderdate, o_orderkey"


@query("win_rank", f"select o_orderkey, row_number() over {_W}) as rn, rank() over (partition by o_custkey order by o_orderdate) as rk, dense_rank() over (partition by o_custkey order by o_orderdate) as dr from orders")
def win_rank(spark, sf_dir):
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.row_number().over(_by_customer()).alias("rn"), F.rank().over(by).alias("rk"), F.dense_rank().over(by).alias("dr"))


@query("win_lag_gap", f"select o_orderkey, date_diff('day', lag(o_orderdate) over {_W}), o_orderdate)::bigint as days, lead(o_orderkey) over {_W}) as next_order from orders")
def win_lag_gap(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(_by_customer())).alias("days"), F.lead("o_orderkey").over(_by_customer()).alias("next_order"))


@query("win_running_sum", f"select o_orderkey, round(sum(o_totalprice::decimal(18,2)) over {_W} rows unbounded preceding)::double, 2) as spent from orders")
def win_running_sum(spark, sf_dir):
    frame = _by_customer().rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return load(spark, sf_dir, "orders").select("o_orderkey", F.round(F.sum(F.col("o_totalprice").cast(DEC)).over(frame).cast("double"), 2).alias("spent"))


@query("win_rows_frame", f"select o_orderkey, max(o_totalprice) over {_W} rows between 1 preceding and 2 following) as around from orders")
def win_rows_frame(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", F.max("o_totalprice").over(_by_customer().rowsBetween(-1, 2)).alias("around"))


@query("win_range_frame", "select event_id, count(*) over (partition by user_id order by floor(epoch(ts))::bigint range between 3600 preceding and current row) as last_hour from events")
def win_range_frame(spark, sf_dir):
    frame = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return load(spark, sf_dir, "events").withColumn("s", F.unix_timestamp("ts")).select("event_id", F.count(F.lit(1)).over(frame).alias("last_hour"))


@query("win_ntile_cume", "select s_suppkey, ntile(4) over (partition by s_nationkey order by s_acctbal, s_suppkey) as quarter, round(cume_dist() over (partition by s_nationkey order by s_acctbal), 6) as cume from supplier")
def win_ntile_cume(spark, sf_dir):
    by = Window.partitionBy("s_nationkey")
    return load(spark, sf_dir, "supplier").select("s_suppkey", F.ntile(4).over(by.orderBy("s_acctbal", "s_suppkey")).alias("quarter"), F.round(F.cume_dist().over(by.orderBy("s_acctbal")), 6).alias("cume"))


# Sorts and sets


@query("sort_topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 25")
def sort_topk(spark, sf_dir):
    return load(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(25)


@query("sort_group_topk", "select o_custkey, o_orderkey, rank from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rank from orders) where rank <= 3")
def sort_group_topk(spark, sf_dir):
    return ops.top_per_group(load(spark, sf_dir, "orders"), "o_custkey", [F.col("o_totalprice").desc(), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "rank")


def _set(name: str, method: str, text: str) -> None:
    @query(name, f"select c_nationkey::bigint as nation from customer {text} select s_nationkey from supplier")
    def combined(spark, sf_dir):
        a = load(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("nation"))
        b = load(spark, sf_dir, "supplier").select(F.col("s_nationkey").alias("nation"))
        out = getattr(a, method)(b)
        return out.distinct() if name == "set_union" else out


for _name, _method, _text in (("set_union", "union", "union"), ("set_union_all", "unionAll", "union all"), ("set_intersect", "intersect", "intersect"), ("set_intersect_all", "intersectAll", "intersect all"), ("set_except", "subtract", "except"), ("set_except_all", "exceptAll", "except all")):
    _set(_name, _method, _text)


# Functions


@query("fn_string", "select doc_id, upper(lang) as u, length(text) as n, position('e' in text) as first_e, md5(text) as h, lpad(source, 8, '.') as padded, substr(text, 3, 5) as part, concat_ws('-', lang, source) as joined, levenshtein(lang, source) as distance, translate(lang, 'ef', 'EF') as t from documents")
def fn_string(spark, sf_dir):
    d = load(spark, sf_dir, "documents")
    return d.select("doc_id", F.upper("lang").alias("u"), F.length("text").alias("n"), F.instr("text", "e").alias("first_e"), F.md5("text").alias("h"), F.lpad("source", 8, ".").alias("padded"), F.substring("text", 3, 5).alias("part"), F.concat_ws("-", "lang", "source").alias("joined"), F.levenshtein("lang", "source").alias("distance"), F.translate("lang", "ef", "EF").alias("t"))


@query("fn_math", "select l_orderkey, l_linenumber::bigint as l_linenumber, ceil(l_quantity / 7)::bigint as c, floor(l_quantity / 7)::bigint as f, round(ln(l_extendedprice), 6) as l, round(sqrt(l_extendedprice), 6) as s, l_orderkey % 7 as m, greatest(l_discount, l_tax) as g, round(l_quantity / nullif(l_discount, 0), 4) as q from lineitem")
def fn_math(spark, sf_dir):
    c = F.col
    return load(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.ceil(c("l_quantity") / 7).alias("c"), F.floor(c("l_quantity") / 7).alias("f"), F.round(F.log("l_extendedprice"), 6).alias("l"), F.round(F.sqrt("l_extendedprice"), 6).alias("s"), F.pmod("l_orderkey", F.lit(7)).alias("m"), F.greatest("l_discount", "l_tax").alias("g"), F.round(F.try_divide("l_quantity", "l_discount"), 4).alias("q"))


@query("fn_array", "with w as (select doc_id, string_split(lower(source || ' ' || lang || ' ' || source), ' ') as a from documents) select doc_id, array_to_string(list_sort(list_distinct(a)), '|') as d, len(a) as n, list_contains(a, 'en') as has, array_to_string(a[2:3], '|') as part, array_to_string(list_transform(a, lambda x: upper(x)), '|') as u, array_to_string(list_filter(a, lambda x: length(x) > 2), '|') as f from w")
def fn_array(spark, sf_dir):
    a = F.split(F.lower(F.concat_ws(" ", "source", "lang", "source")), " ")
    d = load(spark, sf_dir, "documents").select("doc_id", a.alias("a"))
    return d.select("doc_id", F.array_join(F.array_sort(F.array_distinct("a")), "|").alias("d"), F.size("a").alias("n"), F.array_contains("a", "en").alias("has"), F.array_join(F.slice("a", 2, 2), "|").alias("part"), F.array_join(F.transform("a", F.upper), "|").alias("u"), F.array_join(F.filter("a", lambda x: F.length(x) > 2), "|").alias("f"))


@query("fn_map", "select lang, string_agg(source || '=' || n, '|' order by source) as counts from (select lang, source, count(*) as n from documents group by 1, 2) group by 1")
def fn_map(spark, sf_dir):
    n = load(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("lang").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("source", "n")))).alias("m"))
    return m.select("lang", F.array_join(F.transform(F.map_entries("m"), lambda e: F.concat_ws("=", e["key"], e["value"].cast("string"))), "|").alias("counts"))


@query("fn_date", "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first_day, strftime(o_orderdate + interval 30 day, '%Y-%m-%d') as due, floor(epoch(o_orderdate))::bigint as s from orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return load(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first_day"), F.date_format(d + F.expr("interval 30 days"), "yyyy-MM-dd").alias("due"), F.unix_timestamp(d).alias("s"))


@query("fn_json", "select event_id, json_valid(props) as valid, len(json_keys(props)) as keys from events")
def fn_json(spark, sf_dir):
    e = load(spark, sf_dir, "events")
    return e.select("event_id", F.get_json_object("props", "$").isNotNull().alias("valid"), F.coalesce(F.size(F.json_object_keys("props")), F.lit(0)).alias("keys"))


@query("fn_decimal", "select l_returnflag, round(sum(l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(18,2)))::double, 2) as net from lineitem group by 1")
def fn_decimal(spark, sf_dir):
    net = F.col("l_extendedprice").cast(DEC) * (F.lit(1).cast(DEC) - F.col("l_discount").cast(DEC))
    return load(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.round(F.sum(net).cast("double"), 2).alias("net"))


@query("fn_null", "select doc_id, coalesce(quality, -1)::bigint as q, nullif(quality, 1)::bigint as n, case when toxic is not null then 'known' else 'unknown' end as known from documents left join labels using (doc_id)")
def fn_null(spark, sf_dir):
    rows = load(spark, sf_dir, "documents").select("doc_id").join(load(spark, sf_dir, "labels"), "doc_id", "left")
    return rows.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.nullif("quality", F.lit(1)).alias("n"), F.nvl2("toxic", F.lit("known"), F.lit("unknown")).alias("known"))


# Round trips


def _place(spark, label: str) -> str:
    return f"{io.shared_folder(spark)}/textreuse-{label}-{uuid.uuid4().hex}"


_PUBS = "select doc_id, source, lang, n_chars, quality::bigint as quality from documents left join labels using (doc_id)"


def _pubs(spark, sf_dir) -> DataFrame:
    return load(spark, sf_dir, "documents").select("doc_id", "source", "lang", "n_chars").join(load(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")


@query("io_json_roundtrip", _PUBS)
def io_json_roundtrip(spark, sf_dir):
    rows, where = _pubs(spark, sf_dir), _place(spark, "jsonl")
    io.write_jsonl(rows, where)
    return io.read_jsonl(spark, where, rows.schema).drop(io.CORRUPT)


@query("io_csv_roundtrip", _PUBS)
def io_csv_roundtrip(spark, sf_dir):
    rows, where = _pubs(spark, sf_dir), _place(spark, "csv")
    io.write_csv(rows, where)
    return io.read_csv(spark, where, rows.schema)


@query("io_partitioned_roundtrip", _PUBS + " where lang = 'en'")
def io_partitioned_roundtrip(spark, sf_dir):
    rows, where = _pubs(spark, sf_dir), _place(spark, "partitioned")
    io.write_partitioned(rows, where, ["lang"])
    return io.read_partitioned(spark, where, rows.schema).where("lang = 'en'")
