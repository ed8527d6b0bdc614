"""Relational operators around the methods: each a Spark expression with a SQL twin.

Outputs are scalar columns; sums of doubles are rounded to six places.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.shingles import banded_sets
from ..sources.scratch import written

Query = Callable[[SparkSession, str], DataFrame]
SPARK: dict[str, Query] = {}
SQL: dict[str, str] = {}


class Tables:
    def __init__(self, spark: SparkSession, sf_dir: str) -> None:
        self.spark, self.dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.dir}/{name}.parquet")


def op(name: str, sql: str | None = None):
    """Register a function of the tables as query ``op_<name>``, with its SQL if there is one."""

    def wrap(f: Callable[[Tables], DataFrame]):
        SPARK[f"op_{name}"] = lambda spark, sf_dir: f(Tables(spark, sf_dir))
        if sql:
            SQL[f"op_{name}"] = sql
        return f

    return wrap


def r6(c: Column) -> Column:
    return F.round(c, 6) + F.lit(0.0)


# --- scan, filter, cases ----------------------------------------------------------------------


@op("scan_project", "select doc_id, lang, cast(length(text) as bigint) as n, 1 as one from documents")
def scan_project(t):
    return t.documents.select("doc_id", "lang", F.length("text").cast("long").alias("n"), F.lit(1).alias("one"))


@op("filter_pred", "select doc_id from documents where lang in ('en', 'de') and n_chars between 50 and 5000 and not (text like '%###%') and regexp_matches(text, '^[A-Z]')")
def filter_pred(t):
    return t.documents.where(F.col("lang").isin("en", "de") & F.col("n_chars").between(50, 5000) & ~F.col("text").like("%###%") & F.col("text").rlike("^[A-Z]")).select("doc_id")


@op("case_null", "select d.doc_id, case when l.quality = 1 then 'good' when l.quality = 0 then 'bad' else 'none' end as q, coalesce(l.toxic, -1) as toxic, nullif(d.lang, 'en') as other, l.quality is not distinct from l.toxic as same from documents d left join labels l using (doc_id)")
def case_null(t):
    l = t.labels  # noqa: E741
    return t.documents.join(l, "doc_id", "left").select("doc_id", F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "bad").otherwise("none").alias("q"), F.coalesce("toxic", F.lit(-1)).alias("toxic"), F.nullif("lang", F.lit("en")).alias("other"), F.col("quality").eqNullSafe(F.col("toxic")).alias("same"))


# --- joins ----------------------------------------------------------------------------------------


@op("join_inner_hash", "select r_name, cast(count(*) as bigint) as n from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")
def join_inner_hash(t):
    n = F.broadcast(t.nation.join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name"))  # 25 rows by definition
    return t.customer.join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@op("join_sortmerge", "select o_orderpriority, cast(count(*) as bigint) as n, round(sum(l_quantity), 6) + 0e0 as q from lineitem join orders on l_orderkey = o_orderkey group by o_orderpriority")
def join_sortmerge(t):
    return t.lineitem.join(t.orders.hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), r6(F.sum("l_quantity")).alias("q"))


@op("join_shuffle_hash", "select c_mktsegment, cast(count(*) as bigint) as n from orders join customer on o_custkey = c_custkey group by c_mktsegment")
def join_shuffle_hash(t):
    return t.orders.join(t.customer.hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


for _how in ("left", "right", "full"):

    @op(f"join_{_how}", f"select coalesce(d.doc_id, l.doc_id) as doc_id, d.lang, l.quality from (select * from documents where lang <> 'en') d {_how} join labels l on d.doc_id = l.doc_id")
    def join_outer(t, how=_how):
        d = t.documents.where("lang <> 'en'").alias("d")
        return d.join(t.labels.alias("l"), F.col("d.doc_id") == F.col("l.doc_id"), how).select(F.coalesce("d.doc_id", "l.doc_id").alias("doc_id"), "lang", "quality")


@op("join_semi", "select doc_id from documents where doc_id in (select doc_id from labels where quality = 1)")
def join_semi(t):
    return t.documents.join(t.labels.where("quality = 1"), "doc_id", "left_semi").select("doc_id")


@op("join_anti", "select doc_id from documents d where not exists (select 1 from labels l where l.doc_id = d.doc_id)")
def join_anti(t):
    return t.documents.join(t.labels, "doc_id", "left_anti").select("doc_id")


@op("join_theta", "select a.p_brand, cast(count(*) as bigint) as n from part a join part b on a.p_brand = b.p_brand and a.p_type = b.p_type and a.p_retailprice < b.p_retailprice group by a.p_brand")
def join_theta(t):
    """The join's pairs, counted and not made: equal rows are one with their number, and those below it are a running sum of numbers."""
    key = ["p_brand", "p_type"]
    price = t.part.where("p_brand is not null and p_type is not null and p_retailprice is not null").groupBy(*key, "p_retailprice").agg(F.count("*").alias("c"))
    below = F.sum("c").over(Window.partitionBy(*key).orderBy("p_retailprice").rowsBetween(Window.unboundedPreceding, -1))
    return price.withColumn("below", below).groupBy("p_brand").agg(F.sum(F.col("c") * F.col("below")).alias("n")).where("n > 0")


@op("join_range", "select p.p_partkey, b.lo from part p join (select 900 + 100 * i as lo, 1000 + 100 * i as hi from (select unnest(range(0, 12)) as i)) b on p.p_retailprice >= b.lo and p.p_retailprice < b.hi")
def join_range(t):
    bins = t.spark.range(12).select((900 + 100 * F.col("id")).alias("lo"), (1000 + 100 * F.col("id")).alias("hi"))  # 12 rows
    return t.part.join(F.broadcast(bins), (F.col("p_retailprice") >= F.col("lo")) & (F.col("p_retailprice") < F.col("hi"))).select("p_partkey", "lo")


@op("join_interval", "select s.event_id as first_id, cast(count(*) as bigint) as n from events s join events p on p.user_id = s.user_id and p.ts > s.ts and p.ts <= s.ts + interval 1 hour where s.event_type <> p.event_type group by s.event_id")
def join_interval(t):
    s, p = t.events.alias("s"), t.events.alias("p")
    return s.join(p, (F.col("p.user_id") == F.col("s.user_id")) & (F.col("p.ts") > F.col("s.ts")) & (F.col("p.ts") <= F.col("s.ts") + F.expr("interval 1 hour")) & (F.col("s.event_type") != F.col("p.event_type"))).groupBy(F.col("s.event_id").alias("first_id")).agg(F.count("*").alias("n"))


@op("join_asof", "with v as (select user_id, ts, event_id from events where event_type = (select min(event_type) from events)), o as (select event_id, user_id, ts from events where event_type = (select max(event_type) from events)) select o.event_id, (select max(v.ts) from v where v.user_id = o.user_id and v.ts <= o.ts)::varchar as last_ts from o")
def join_asof(t):
    e = t.events.select("event_id", "user_id", "ts", "event_type")
    ends = e.agg(F.min("event_type").alias("lo"), F.max("event_type").alias("hi"))  # one row
    tagged = e.join(F.broadcast(ends)).where((F.col("event_type") == F.col("lo")) | (F.col("event_type") == F.col("hi"))).withColumn("right", F.col("event_type") == F.col("lo"))
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("right")).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return tagged.withColumn("last_ts", F.last(F.when(F.col("right"), F.col("ts")), ignorenulls=True).over(w)).where(~F.col("right")).select("event_id", stamp(F.col("last_ts")).alias("last_ts"))


def stamp(c: Column) -> Column:
    """A timestamp as the other engine prints it: no trailing zeros of the fraction."""
    whole = F.date_format(c, "yyyy-MM-dd HH:mm:ss")
    return F.when(F.date_format(c, "SSSSSS") == "000000", whole).otherwise(F.regexp_replace(F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS"), "0+$", ""))


@op("join_self_next", "select a.conv_id, a.turn, cast(length(b.text) as bigint) as n from conversations a join conversations b on b.conv_id = a.conv_id and b.turn = a.turn + 1 where a.role = 'user' and b.role = 'assistant'")
def join_self_next(t):
    w = Window.partitionBy("conv_id").orderBy("turn")
    c = t.conversations.withColumns({"next_turn": F.lead("turn").over(w), "next_role": F.lead("role").over(w), "next_text": F.lead("text").over(w)})
    return c.where("role = 'user' and next_role = 'assistant' and next_turn = turn + 1").select("conv_id", "turn", F.length("next_text").cast("long").alias("n"))


# --- aggregates -----------------------------------------------------------------------------------


@op("agg_hash", "select l_returnflag, l_linestatus, cast(count(*) as bigint) as n, round(sum(l_quantity), 6) + 0e0 as s, round(avg(l_extendedprice), 6) + 0e0 as a, min(l_discount) as lo, max(l_tax) as hi, round(stddev_samp(l_quantity), 6) + 0e0 as sd, round(corr(l_quantity, l_extendedprice), 6) + 0e0 as co from lineitem group by l_returnflag, l_linestatus")
def agg_hash(t):
    return t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), r6(F.sum("l_quantity")).alias("s"), r6(F.avg("l_extendedprice")).alias("a"), F.min("l_discount").alias("lo"), F.max("l_tax").alias("hi"), r6(F.stddev_samp("l_quantity")).alias("sd"), r6(F.corr("l_quantity", "l_extendedprice")).alias("co"))


@op("agg_distinct", "select lang, cast(count(distinct source) as bigint) as n from documents group by lang")
def agg_distinct(t):
    return t.documents.groupBy("lang").agg(F.count_distinct("source").alias("n"))


@op("agg_filter", "select cast(count(*) filter (quality = 1) as bigint) as good, cast(coalesce(sum(case when toxic = 1 then 1 else 0 end), 0) as bigint) as toxic from labels")
def agg_filter(t):
    return t.labels.agg(F.count_if(F.col("quality") == 1).alias("good"), F.coalesce(F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0)), F.lit(0)).cast("long").alias("toxic"))


@op("agg_percentile", "select lang, round(quantile_cont(n_chars, 0.5), 6) + 0e0 as med, round(quantile_cont(n_chars, 0.9), 6) + 0e0 as p90 from documents group by lang")
def agg_percentile(t):
    return t.documents.groupBy("lang").agg(r6(F.percentile("n_chars", F.lit(0.5))).alias("med"), r6(F.percentile("n_chars", F.lit(0.9))).alias("p90"))


@op("approx_percentile")
def approx_percentile(t):
    return t.documents.groupBy("lang").agg(F.percentile_approx("n_chars", 0.5, 10000).alias("med"))


@op("approx_distinct")
def approx_distinct(t):
    return t.events.agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@op("rollup", "select lang, source, cast(grouping_id(lang, source) as bigint) as g, cast(count(*) as bigint) as n from documents group by rollup (lang, source)")
def rollup(t):
    return t.documents.rollup("lang", "source").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"))


@op("cube", "select lang, source, cast(grouping_id(lang, source) as bigint) as g, cast(count(*) as bigint) as n from documents group by cube (lang, source)")
def cube(t):
    return t.documents.cube("lang", "source").agg(F.grouping_id().cast("long").alias("g"), F.count("*").alias("n"))


@op("grouping_sets", "select c_mktsegment, c_nationkey, cast(count(*) as bigint) as n from customer group by grouping sets ((c_mktsegment), (c_nationkey))")
def grouping_sets(t):
    return t.customer.groupingSets([[F.col("c_mktsegment")], [F.col("c_nationkey")]], "c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@op("pivot", "select lang, cast(count(*) filter (source = 'src0') as bigint) as src0, cast(count(*) filter (source = 'src1') as bigint) as src1 from documents group by lang")
def pivot(t):
    return t.documents.groupBy("lang").pivot("source", ["src0", "src1"]).count().na.fill(0)


@op("unpivot", "select s_suppkey, 'key' as what, cast(s_nationkey as double) as x from supplier union all select s_suppkey, 'bal', s_acctbal from supplier")
def unpivot(t):
    s = t.supplier.select("s_suppkey", F.col("s_nationkey").cast("double").alias("key"), F.col("s_acctbal").alias("bal"))
    return s.unpivot("s_suppkey", ["key", "bal"], "what", "x")


@op("argmax", "select lang, doc_id from (select lang, doc_id, row_number() over (partition by lang order by n_chars desc, doc_id) as r from documents) where r = 1")
def argmax(t):
    return t.documents.groupBy("lang").agg(F.max_by("doc_id", F.struct("n_chars", -F.col("doc_id"))).alias("doc_id"))


@op("collect", "select conv_id, string_agg(role, '>' order by turn) as roles from conversations group by conv_id")
def collect(t):
    return t.conversations.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role"))), lambda x: x["role"]), ">").alias("roles"))


@op("vector_sum", "select label, i, round(avg(x), 6) + 0e0 as m from (select label, generate_subscripts(embedding, 1) as i, cast(unnest(embedding) as double) as x from embeddings) group by label, i")
def vector_sum(t):
    return t.embeddings.select("label", F.posexplode("embedding").alias("p", "x")).groupBy("label", (F.col("p") + 1).cast("long").alias("i")).agg(r6(F.avg(F.col("x").cast("double"))).alias("m"))


# --- windows ---------------------------------------------------------------------------------------

_RANKS = "row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt"


@op("win_rank", f"select doc_id, {_RANKS}, round(percent_rank() over w, 6) + 0e0 as pr, round(cume_dist() over w, 6) + 0e0 as cd from documents window w as (partition by lang order by n_chars desc, doc_id)")
def win_rank(t):
    w = Window.partitionBy("lang").orderBy(F.desc("n_chars"), "doc_id")
    return t.documents.select("doc_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("nt"), r6(F.percent_rank().over(w)).alias("pr"), r6(F.cume_dist().over(w)).alias("cd"))


@op("win_lead_lag", "select conv_id, turn, lag(role) over w as p, lead(role) over w as n, first_value(role) over w as f, last_value(role) over (partition by conv_id order by turn rows between unbounded preceding and unbounded following) as l, nth_value(role, 2) over (partition by conv_id order by turn rows between unbounded preceding and unbounded following) as s from conversations window w as (partition by conv_id order by turn)")
def win_lead_lag(t):
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t.conversations.select("conv_id", "turn", F.lag("role").over(w).alias("p"), F.lead("role").over(w).alias("n"), F.first_value("role").over(w).alias("f"), F.last_value("role").over(whole).alias("l"), F.nth_value("role", 2).over(whole).alias("s"))


@op("win_running", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row), 6) + 0e0 as s from events")
def win_running(t):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t.events.select("event_id", r6(F.sum("value").over(w)).alias("s"))


@op("win_range", "select event_id, cast(count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as bigint) as n from events")
def win_range(t):
    return t.events.select("event_id", F.expr("count(*) over (partition by user_id order by ts range between interval 1 hour preceding and current row)").alias("n"))


@op("sort_limit", "select p_partkey, p_retailprice from part order by p_retailprice desc, p_partkey limit 20")
def sort_limit(t):
    return t.part.orderBy(F.desc("p_retailprice"), "p_partkey").limit(20).select("p_partkey", "p_retailprice")


@op("offset", "select p_partkey from part order by p_partkey limit 10 offset 30")
def offset(t):
    return t.part.select("p_partkey").orderBy("p_partkey").offset(30).limit(10)


@op("topk_group", "select o_custkey, o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 3")
def topk_group(t):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t.orders.withColumn("r", F.row_number().over(w)).where("r <= 3").select("o_custkey", "o_orderkey")


# --- set operations -----------------------------------------------------------------------------------


@op("union", "select md5(text) as h from documents union all select md5(text) from benchmark")
def union(t):
    return t.documents.select(F.md5("text").alias("h")).union(t.benchmark.select(F.md5("text")))


@op("union_by_name", "select doc_id as id, lang, null::varchar as extra from documents union all select item_id, null, 'b' from benchmark")
def union_by_name(t):
    return t.documents.select(F.col("doc_id").alias("id"), "lang").unionByName(t.benchmark.select(F.lit("b").alias("extra"), F.col("item_id").alias("id")), allowMissingColumns=True).select("id", "lang", "extra")


for _name, _sql in (("intersect", "intersect"), ("intersect_all", "intersect all"), ("except", "except"), ("except_all", "except all")):

    @op(_name, f"select lang, source from documents where n_chars > 1000 {_sql} select lang, source from documents where n_chars < 2000")
    def set_op(t, name=_name):
        a, b = (t.documents.where(p).select("lang", "source") for p in ("n_chars > 1000", "n_chars < 2000"))
        return {"intersect": a.intersect, "intersect_all": a.intersectAll, "except": a.subtract, "except_all": a.exceptAll}[name](b)


# --- functions ----------------------------------------------------------------------------------------


@op("str", "select p_partkey, substr(p_name, 2, 3) as a, upper(p_name) as b, replace(p_type, ' ', '_') as c, lpad(cast(p_size as varchar), 4, '0') as d, reverse(p_brand) as e, regexp_extract(p_brand, '[0-9]+') as f, cast(levenshtein(p_name, p_type) as integer) as g, cast(instr(p_name, 'a') as integer) as h, translate(p_brand, 'Bd', 'xy') as i, split_part(p_type, ' ', 1) as j from part")
def strings(t):
    return t.part.select("p_partkey", F.substring("p_name", 2, 3).alias("a"), F.upper("p_name").alias("b"), F.replace("p_type", F.lit(" "), F.lit("_")).alias("c"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("d"), F.reverse("p_brand").alias("e"), F.regexp_extract("p_brand", "[0-9]+", 0).alias("f"), F.levenshtein("p_name", "p_type").alias("g"), F.instr("p_name", "a").alias("h"), F.translate("p_brand", "Bd", "xy").alias("i"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("j"))


@op("bytes", "select doc_id, md5(text) as m, sha256(text) as s, cast(octet_length(encode(text)) as bigint) as n, substr(hex(text), 1, 16) as h from documents")
def byte_functions(t):
    return t.documents.select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"), F.octet_length("text").cast("long").alias("n"), F.substring(F.hex("text"), 1, 16).alias("h"))


@op("html_text", "select page_id, md5(trim(regexp_replace(regexp_replace(regexp_replace(html, '(?s)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '[ \\n\\r\\t]+', ' ', 'g'))) as m from pages")
def html_text(t):
    bare = F.regexp_replace("html", r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return t.pages.select("page_id", F.md5(F.trim(F.regexp_replace(F.regexp_replace(bare, "<[^>]*>", " "), r"[ \n\r\t]+", " "))).alias("m"))


@op("date", "select o_orderkey, cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first_day, cast(date_diff('day', timestamp '1990-01-01', date_trunc('day', o_orderdate)) as integer) as days, strftime(o_orderdate + interval 10 day, '%Y-%m-%d') as later, cast(dayofyear(o_orderdate) as integer) as doy from orders")
def dates(t):
    d = F.col("o_orderdate")
    return t.orders.select("o_orderkey", F.year(d).alias("y"), F.month(d).alias("m"), F.date_format(F.date_trunc("month", d), "yyyy-MM-dd").alias("first_day"), F.datediff(d, F.lit("1990-01-01")).alias("days"), F.date_format(F.date_add(d, 10), "yyyy-MM-dd").alias("later"), F.dayofyear(d).alias("doy"))


@op("math", "select l_orderkey, l_linenumber, round(exp(l_discount), 6) + 0e0 as a, round(ln(l_quantity + 1), 6) + 0e0 as b, round(pow(l_tax, 2), 6) + 0e0 as c, round(sqrt(l_quantity), 6) + 0e0 as d, greatest(l_tax, l_discount) as e, least(l_tax, l_discount) as f, cast(sign(l_discount - 0.05e0) as integer) as g, abs(l_tax - l_discount) as h from lineitem")
def maths(t):
    c = F.col
    return t.lineitem.select("l_orderkey", "l_linenumber", r6(F.exp("l_discount")).alias("a"), r6(F.log(c("l_quantity") + 1)).alias("b"), r6(F.pow("l_tax", F.lit(2))).alias("c"), r6(F.sqrt("l_quantity")).alias("d"), F.greatest("l_tax", "l_discount").alias("e"), F.least("l_tax", "l_discount").alias("f"), F.signum(c("l_discount") - 0.05).cast("int").alias("g"), F.abs(c("l_tax") - c("l_discount")).alias("h"))


_DOT = "list_sum(list_transform(range(1, 65), lambda i: cast({a}[i] as double) * cast({b}[i] as double)))"


@op("array", "select vec_id, round(list_sum(list_transform(embedding, lambda x: cast(x as double) * 2)), 6) + 0e0 as twice, cast(len(list_filter(embedding, lambda x: x > 0)) as integer) as pos, cast(len(list_distinct(embedding[1:8])) as integer) as few from embeddings")
def arrays(t):
    return t.embeddings.select("vec_id", r6(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * 2), F.lit(0.0), lambda a, x: a + x)).alias("twice"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.size(F.array_distinct(F.slice("embedding", 1, 8))).alias("few"))


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


@op("dot", f"select vec_id, round({_DOT.format(a='embedding', b='embedding')}, 6) + 0e0 as n from embeddings")
def dots(t):
    return t.embeddings.select("vec_id", r6(dot("embedding", "embedding")).alias("n"))


@op("cosine_topk", f"select a, b from (select x.vec_id as a, y.vec_id as b, row_number() over (partition by x.vec_id order by round({_DOT.format(a='x.embedding', b='y.embedding')}, 9) desc, y.vec_id) as r from (select * from embeddings where vec_id % 20 = 0) x join embeddings y on x.vec_id <> y.vec_id) where r <= 3")
def cosine_topk(t):
    """A stated query set (ids divisible by 20) against all rows."""
    x = t.embeddings.where("vec_id % 20 = 0").select(F.col("vec_id").alias("a"), F.col("embedding").alias("u"))
    y = t.embeddings.select(F.col("vec_id").alias("b"), F.col("embedding").alias("v"))
    w = Window.partitionBy("a").orderBy(F.desc("s"), "b")
    return y.join(x, F.col("a") != F.col("b")).withColumn("s", F.round(dot("u", "v"), 9)).withColumn("r", F.row_number().over(w)).where("r <= 3").select("a", "b")


@op("map_struct", "select user_id, cast(count(*) filter (event_type = 'click') as bigint) as clicks, cast(count(distinct event_type) as integer) as kinds from events group by user_id")
def map_struct(t):
    pairs = t.events.groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m"))
    return pairs.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).alias("clicks"), F.size(F.map_filter("m", lambda k, v: v > 0)).alias("kinds"))


@op("json", "select event_id, cast(json_extract_string(props, '$.k') as integer) as k from events")
def jsons(t):
    return t.events.select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@op("ngrams", "select g, cast(count(*) as bigint) as n from (select unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) as g from (select string_split(text, ' ') as w from benchmark)) group by g")
def ngrams(t):
    w = F.split("text", " ")
    grams = F.transform(F.sequence(F.lit(0), F.size(w) - 2), lambda i: F.concat_ws(" ", F.get(w, i), F.get(w, i + 1)))
    return t.benchmark.select(F.explode(F.when(F.size(w) > 1, grams)).alias("g")).groupBy("g").agg(F.count("*").alias("n"))


@op("dedup_exact", "select min(doc_id) as doc_id, cast(count(*) as bigint) as copies from documents group by md5(text)")
def dedup_exact(t):
    return t.documents.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("h")


@op("dedup_near")
def dedup_near(t, bands: int = 8, rows: int = 3, words: int = 5, block: int = 200):
    """MinHash bands over word shingles of whole texts; links (lesser id, greater id) verified by Jaccard of the sets.

    Equal sets are one, linked with its copies.  All pairs of a band's sets are verified, block against block.
    """
    made = written(banded_sets(t.documents, words, bands, rows), "sets")
    same = ["f1", "f2", "n"]
    equal = made.groupBy(*same).agg(F.min("doc_id").alias("a"))
    copies = made.join(equal, same).where("a <> doc_id").select("a", F.col("doc_id").alias("b")).distinct()
    sets = made.join(equal.select(F.col("a").alias("doc_id")).distinct(), "doc_id", "left_semi").select(F.col("doc_id").alias("a"), "s", "keys")
    banded = sets.select("a", F.explode("keys").alias("band"))
    met = banded.groupBy("band").agg(F.count("*").alias("n")).where("n > 1").select("band", F.ceil(F.col("n") / block).alias("blocks"))
    dealt = banded.join(met, "band").withColumn("own", F.pmod(F.xxhash64("band", "a"), F.col("blocks")))
    x = dealt.select("band", "a", F.col("own").alias("x"), F.explode(F.sequence(F.col("own"), F.col("blocks") - 1)).alias("y"))
    y = dealt.select("band", F.col("a").alias("b"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("own"))).alias("x"), F.col("own").alias("y"))
    pairs = x.join(y, ["band", "x", "y"]).where("x <> y or a < b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
    pairs = written(pairs, "pairs")
    both = F.size(F.array_intersect("s", "t"))
    near = pairs.join(sets.select("a", "s"), "a").join(sets.select(F.col("a").alias("b"), F.col("s").alias("t")), "b").where(both >= 0.8 * (F.size("s") + F.size("t") - both)).select("a", "b")
    return near.unionByName(copies)


@op("subquery", "select o_orderkey from orders o where o_totalprice > (select avg(i.o_totalprice) from orders i where i.o_custkey = o.o_custkey) and exists (select 1 from lineitem l where l.l_orderkey = o.o_orderkey)")
def subquery(t):
    t.orders.createOrReplaceTempView("tilt_orders")
    t.lineitem.createOrReplaceTempView("tilt_lineitem")
    return t.spark.sql("select o_orderkey from tilt_orders o where o_totalprice > (select avg(i.o_totalprice) from tilt_orders i where i.o_custkey = o.o_custkey) and exists (select 1 from tilt_lineitem l where l.l_orderkey = o.o_orderkey)")


@op("cte", "with big as (select o_custkey, count(*) as n from orders group by o_custkey) select cast(n as bigint) as n, cast(count(*) as bigint) as customers from big group by n")
def cte(t):
    t.orders.createOrReplaceTempView("tilt_orders")
    return t.spark.sql("with big as (select o_custkey, count(*) as n from tilt_orders group by o_custkey) select n, count(*) as customers from big group by n")


_HALVED = "with recursive s(o_orderpriority, step, rate) as (select o_orderpriority, 0, max(cast(o_totalprice as double)) from {orders} group by o_orderpriority union all select o_orderpriority, step + 1, rate * 0.5e0 from s where step < 9) select o_orderpriority, step, rate from s"


@op("recursive", _HALVED.format(orders="orders"))
def recursive(t):
    """A rate halved nine times, for each priority from its orders' largest price."""
    t.orders.createOrReplaceTempView("tilt_orders")
    return t.spark.sql(_HALVED.format(orders="tilt_orders"))


# --- time windows in batch form -----------------------------------------------------------------------


@op("win_tumbling", "select strftime(time_bucket(interval 1 hour, ts), '%Y-%m-%d %H:%M') as start, event_type, cast(count(*) as bigint) as n from events group by 1, 2")
def win_tumbling(t):
    return t.events.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "event_type", "n")


@op("win_sliding", "select strftime(s, '%Y-%m-%d %H:%M') as start, cast(count(*) as bigint) as n from (select unnest([time_bucket(interval 30 minute, ts), time_bucket(interval 30 minute, ts) - interval 30 minute]) as s from events) group by 1")
def win_sliding(t):
    return t.events.groupBy(F.window("ts", "1 hour", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


@op("win_session", "with g as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) < interval 30 minute then 0 else 1 end as fresh from events), s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows between unbounded preceding and current row) as no from g) select user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') as start, cast(count(*) as bigint) as n from s group by user_id, no")
def win_session(t):
    return t.events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


# --- measures of pairs and vectors in relational form -----------------------------------------------

_GRAMS = " union all ".join(f"select id, {n} as n, unnest(list_transform(range(1, len(w) - {n} + 2), lambda i: array_to_string(w[i:i + {n} - 1], ' '))) as g from {{0}} where len(w) >= {n}" for n in range(1, 5))


@op("bleu", f"""
with p as (select conv_id * 1000 + turn as id, string_split(lag(text) over (partition by conv_id order by turn), ' ') as h, string_split(text, ' ') as r from conversations),
q as (select * from p where h is not null), hw as (select id, h as w from q), rw as (select id, r as w from q),
hg as (select id, n, g, count(*) as c from ({_GRAMS.format("hw")}) group by id, n, g), rg as (select id, n, g, count(*) as c from ({_GRAMS.format("rw")}) group by id, n, g),
m as (select hg.n, cast(sum(least(hg.c, coalesce(rg.c, 0))) as double) as hit, cast(sum(hg.c) as double) as total from hg left join rg on rg.id = hg.id and rg.n = hg.n and rg.g = hg.g group by hg.n),
l as (select cast(sum(len(h)) as double) as hl, cast(sum(len(r)) as double) as rl from q)
select round(exp(avg(ln((hit + 1e-9) / total))) * (select exp(least(0e0, 1 - rl / hl)) from l), 6) + 0e0 as bleu, cast(count(*) as bigint) as orders from m""")
def bleu(t):
    """Corpus BLEU of each turn against the one before it: clipped n-grams by hash aggregates, then one row."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    pairs = t.conversations.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.split(F.lag("text").over(w), " ").alias("h"), F.split("text", " ").alias("r")).where("h is not null")

    def of_order(words: str, n: int) -> Column:
        return F.when(F.size(words) >= n, F.transform(F.sequence(F.lit(1), F.size(words) - n + 1), lambda i: F.array_join(F.slice(words, i, n), " ")))

    def grams(words: str, count: str) -> DataFrame:
        orders = F.array(*[F.struct(F.lit(n).alias("n"), of_order(words, n).alias("gs")) for n in range(1, 5)])
        return pairs.select("id", F.explode(orders).alias("o")).select("id", "o.n", F.explode("o.gs").alias("g")).groupBy("id", "n", "g").agg(F.count("*").alias(count))

    met = grams("h", "c").join(grams("r", "rc"), ["id", "n", "g"], "left").groupBy("n").agg(F.sum(F.least("c", F.coalesce("rc", F.lit(0)))).alias("hit"), F.sum("c").alias("total"))
    sizes = pairs.agg(F.sum(F.size("h")).alias("hl"), F.sum(F.size("r")).alias("rl"))
    one = met.agg(F.exp(F.avg(F.log((F.col("hit") + 1e-9) / F.col("total")))).alias("p"), F.count("*").alias("orders"))
    return one.crossJoin(sizes).select(r6(F.col("p") * F.exp(F.least(F.lit(0.0), 1 - F.col("rl") / F.col("hl")))).alias("bleu"), "orders")  # two single rows


@op("caption_accuracy", """
with x as (select vec_id, label, generate_subscripts(embedding, 1) as i, cast(unnest(embedding) as double) as x from embeddings),
m as (select label, i, avg(x) as m from x where vec_id % 2 = 0 group by label, i),
s as (select x.vec_id, x.label as own, m.label, round(sum(x.x * m.m), 9) as s from x join m on m.i = x.i where x.vec_id % 2 = 1 group by x.vec_id, x.label, m.label),
b as (select vec_id, own, label, row_number() over (partition by vec_id order by s desc, label) as r from s)
select round(avg(case when own = label then 1e0 else 0e0 end), 6) + 0e0 as accuracy, cast(count(*) as bigint) as n from b where r = 1""")
def caption_accuracy(t):
    """Held-out vectors (odd ids) to the nearest class vector, the mean of its even ids."""
    x = t.embeddings.select("vec_id", "label", F.posexplode("embedding").alias("i", "x")).withColumn("x", F.col("x").cast("double"))
    m = x.where("vec_id % 2 = 0").groupBy("label", "i").agg(F.avg("x").alias("m")).withColumnRenamed("label", "other")
    s = x.where("vec_id % 2 = 1").join(m, "i").groupBy("vec_id", "label", "other").agg(F.round(F.sum(F.col("x") * F.col("m")), 9).alias("s"))
    best = s.groupBy("vec_id", "label").agg(F.max_by("other", F.struct("s", -F.col("other"))).alias("got"))
    return best.agg(r6(F.avg(F.when(F.col("got") == F.col("label"), 1.0).otherwise(0.0))).alias("accuracy"), F.count("*").alias("n"))
