"""Relational operators around the methods, one workload for each kind, with its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..sources.carriers import table as t


def n_rows():
    return F.count(F.lit(1))


def filter_identified(s, d):
    return t(s, d, "orders").where(F.col("o_orderstatus").isin("F", "O") & F.col("o_totalprice").between(1000, 200000) & F.col("o_orderpriority").rlike("^[1-3]-")).groupBy("o_orderstatus").agg(n_rows().alias("n"))


def join_broadcast_manifest(s, d):
    # nation has a fixed number of rows
    return t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(n_rows().alias("customers"))


def join_hull_pairs(s, d):
    o = t(s, d, "orders")
    return o.hint("merge").join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(n_rows().alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"))


def join_cross_small(s, d):
    return t(s, d, "nation").select("n_name").crossJoin(F.broadcast(t(s, d, "region").select("r_name")))


def join_interval_overlap(s, d):
    """Pairs of sessions of one vessel's neighbours that overlap: bucketed by day, checked in full, counted once at the later start."""
    w = t(s, d, "events").groupBy("user_id", F.to_date("ts").alias("day")).agg(F.min("ts").alias("a"), F.max("ts").alias("b"))
    x, y = w.select("day", F.col("user_id").alias("u"), "a", "b"), w.select("day", (F.col("user_id") - 1).alias("u"), F.col("a").alias("a2"), F.col("b").alias("b2"))
    return x.join(y, ["day", "u"]).where("a <= b2 and a2 <= b").groupBy("u").agg(n_rows().alias("n_overlaps"))


def join_asof(s, d):
    """The last event of each type before every 'purchase' of a user, by a union and a running last value."""
    e = t(s, d, "events").select("user_id", "ts", "event_id", "event_type", "value")
    kinds = e.select(F.max("event_type").alias("k"))
    e = e.crossJoin(F.broadcast(kinds))
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return e.withColumn("prior", F.last(F.when(F.col("event_type") != F.col("k"), F.col("event_id")), ignorenulls=True).over(w)).where("event_type = k").select("event_id", "prior")


def join_semi(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").where("o_orderstatus = 'F'").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").agg(n_rows().alias("n"))


def join_anti(s, d):
    return t(s, d, "customer").join(t(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey")


def join_full_outer(s, d):
    a = t(s, d, "lineitem").groupBy(F.col("l_suppkey").alias("k")).agg(n_rows().alias("lines"))
    b = t(s, d, "part").groupBy(F.col("p_size").cast("long").alias("k")).agg(n_rows().alias("parts"))
    return a.join(b, "k", "full_outer").select("k", "lines", "parts")


def agg_stats(s, d):
    v = F.col("l_quantity")
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.avg(v), 6).alias("mean"), F.round(F.stddev_pop(v), 6).alias("sd"), F.round(F.percentile(v, F.lit(0.9)), 6).alias("p90"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("dearest"))


def agg_distinct(s, d):
    return t(s, d, "lineitem").groupBy("l_linestatus").agg(F.count_distinct("l_suppkey").alias("suppliers"), F.count_distinct("l_partkey", "l_suppkey").alias("pairs"))


def agg_cube(s, d):
    return t(s, d, "documents").cube("lang", "source").agg(n_rows().alias("n"), F.sum("n_chars").alias("chars"))


def agg_rollup(s, d):
    return t(s, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(n_rows().alias("n"))


def agg_grouping_sets(s, d):
    o = t(s, d, "orders")
    return o.groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(n_rows().alias("n"))


def pivot_methods(s, d):
    return t(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(n_rows())


def win_rank(s, d):
    w = W.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return t(s, d, "orders").select("o_orderkey", F.rank().over(w).alias("place"), F.dense_rank().over(w).alias("dense"), F.round(F.percent_rank().over(w), 6).alias("share"), F.round(F.cume_dist().over(w), 6).alias("upto")).where("place <= 3")


def win_ntile(s, d):
    q = F.ntile(4).over(W.partitionBy("lang").orderBy("n_chars", "doc_id"))
    return t(s, d, "documents").select("lang", "n_chars", q.alias("q")).groupBy("lang", "q").agg(n_rows().alias("n"), F.max("n_chars").alias("top"))


def win_frames(s, d):
    o = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    x = F.col("o_totalprice")
    return t(s, d, "orders").select("o_orderkey", F.round(F.sum(x).over(o.rowsBetween(W.unboundedPreceding, 0)), 2).alias("running"), F.round(F.sum(x).over(o.rowsBetween(2, 5)), 2).alias("ahead"), F.first_value("o_orderkey").over(o).alias("first"), F.nth_value("o_orderkey", 2).over(o.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("second"))


def win_range(s, d):
    day = F.datediff("o_orderdate", F.lit("1990-01-01").cast("date"))
    o = t(s, d, "orders").withColumn("day", day)
    return o.select("o_orderkey", F.count(F.lit(1)).over(W.partitionBy("o_custkey").orderBy("day").rangeBetween(-30, 0)).alias("n"))


def sort_topk(s, d):
    return t(s, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").offset(5).limit(20).select("o_orderkey", "o_totalprice")


def _keys(s, d):
    return t(s, d, "lineitem").select(F.col("l_suppkey").alias("k")), t(s, d, "part").select(F.col("p_size").cast("long").alias("k"))


def sets(op):
    def run(s, d):
        a, b = _keys(s, d)
        return op(a, b)

    return run


def fn_string(s, d):
    x = F.col("p_name")
    return t(s, d, "part").select("p_partkey", F.upper(x).alias("up"), F.element_at(F.split(x, " "), 1).alias("head"), F.regexp_replace(x, "[aeiou]", "").alias("bare"), F.levenshtein(x, F.col("p_brand")).alias("far"), F.sha2(x, 256).alias("sha"), F.length(x).alias("n"))


def fn_date(s, d):
    x = F.col("o_orderdate")
    return t(s, d, "orders").groupBy(F.year(x).alias("y"), F.month(x).alias("m")).agg(n_rows().alias("n"), F.max(F.datediff(x, F.trunc(x, "month"))).alias("latest"))


def fn_map(s, d):
    m = t(s, d, "orders").groupBy("o_custkey").agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("o_orderpriority", F.lit(1).alias("v"))))).alias("m"))
    return m.select("o_custkey", F.array_join(F.array_sort(F.map_keys(F.map_filter("m", lambda k, v: k < "3"))), ",").alias("urgent"), F.size("m").alias("kinds"))


def fn_json(s, d):
    k = F.from_json("props", "k int")["k"]
    return t(s, d, "events").groupBy("event_type").agg(F.sum(k).alias("total"), F.max(F.get_json_object("props", "$.k").cast("int")).alias("top"))


def fn_url(s, d):
    return t(s, d, "pages").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(n_rows().alias("n"), F.sum(F.regexp_count("html", F.lit("<p[ >]"))).alias("paragraphs"))


def fn_explode(s, d):
    return t(s, d, "conversations").select("role", F.explode(F.split(F.trim("text"), r"\s+")).alias("w")).where("w <> ''").groupBy("role").agg(n_rows().alias("words"), F.count_distinct("w").alias("distinct_words"))


def sample_det(s, d):
    """One row in ten by md5, the same at every run; sampling is what this operator is for."""
    u = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string")), 1, 4), 16, 10).cast("int")
    return t(s, d, "orders").where(u % 10 == 0).agg(n_rows().alias("n"), F.sum("o_orderkey").alias("keys"))


def sql_correlated(s, d):
    t(s, d, "orders").createOrReplaceTempView("passagekit_orders")
    return s.sql("select o_custkey, o_orderkey from passagekit_orders o where o_totalprice = (select max(o_totalprice) from passagekit_orders i where i.o_custkey = o.o_custkey) and o_totalprice > :floor", args={"floor": 100000})


TABLE = {
    "filter_identified": (filter_identified, "select o_orderstatus, count(*) n from orders where o_orderstatus in ('F', 'O') and o_totalprice between 1000 and 200000 and regexp_matches(o_orderpriority, '^[1-3]-') group by 1"),
    "join_broadcast_manifest": (join_broadcast_manifest, "select n_name, count(*) customers from customer join nation on c_nationkey = n_nationkey group by 1"),
    "join_hull_pairs": (join_hull_pairs, "select c_mktsegment, count(*) n, round(sum(o_totalprice), 2) total from orders join customer on o_custkey = c_custkey group by 1"),
    "join_cross_small": (join_cross_small, "select n_name, r_name from nation, region"),
    "join_interval_overlap": (join_interval_overlap, "with w as (select user_id u, ts::date as day, min(ts) a, max(ts) b from events group by all) select x.u, count(*) n_overlaps from w x join w y on x.day = y.day and y.u = x.u + 1 and x.a <= y.b and y.a <= x.b group by 1"),
    "join_asof": (join_asof, "select event_id, prior from (select event_id, event_type, k, last_value(case when event_type <> k then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) prior from events, (select max(event_type) k from events)) where event_type = k"),
    "join_semi": (join_semi, "select count(*) n from customer where c_custkey in (select o_custkey from orders where o_orderstatus = 'F')"),
    "join_anti": (join_anti, "select c_custkey from customer where c_custkey not in (select o_custkey from orders)"),
    "join_full_outer": (join_full_outer, "select k, lines, parts from (select l_suppkey k, count(*) as lines from lineitem group by 1) full join (select p_size::bigint k, count(*) parts from part group by 1) using (k)"),
    "agg_stats": (agg_stats, "select l_returnflag, round(avg(l_quantity), 6) mean, round(stddev_pop(l_quantity), 6) sd, round(quantile_cont(l_quantity, 0.9), 6) p90, round(corr(l_quantity, l_extendedprice), 6) r, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) dearest from lineitem group by 1"),
    "agg_distinct": (agg_distinct, "select l_linestatus, count(distinct l_suppkey) suppliers, count(distinct (l_partkey, l_suppkey)) pairs from lineitem group by 1"),
    "agg_cube": (agg_cube, "select lang, source, count(*) n, sum(n_chars)::bigint chars from documents group by cube (lang, source)"),
    "agg_rollup": (agg_rollup, "select o_orderstatus, o_orderpriority, count(*) n from orders group by rollup (o_orderstatus, o_orderpriority)"),
    "agg_grouping_sets": (agg_grouping_sets, "select o_orderstatus, o_orderpriority, count(*) n from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())"),
    "pivot_methods": (pivot_methods, "select o_orderpriority, " + ", ".join(f"nullif(count(*) filter (where o_orderstatus = '{c}'), 0) \"{c}\"" for c in "FOP") + " from orders group by 1"),
    "win_rank": (win_rank, "select o_orderkey, rank() over w place, dense_rank() over w dense, round(percent_rank() over w, 6) share, round(cume_dist() over w, 6) upto from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey) qualify place <= 3"),
    "win_ntile": (win_ntile, "select lang, q, count(*) n, max(n_chars) top from (select lang, n_chars, ntile(4) over (partition by lang order by n_chars, doc_id) q from documents) group by all"),
    "win_frames": (win_frames, "select o_orderkey, round(sum(o_totalprice) over (o rows unbounded preceding), 2) running, round(sum(o_totalprice) over (o rows between 2 following and 5 following), 2) ahead, first_value(o_orderkey) over o as first, nth_value(o_orderkey, 2) over (o rows between unbounded preceding and unbounded following) as second from orders window o as (partition by o_custkey order by o_orderdate, o_orderkey)"),
    "win_range": (win_range, "select o_orderkey, count(*) over (partition by o_custkey order by dy range between 30 preceding and current row) n from (select *, date_diff('day', date '1990-01-01', o_orderdate::date) dy from orders)"),
    "sort_topk": (sort_topk, "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20 offset 5"),
    "set_union": (sets(lambda a, b: a.unionByName(b).distinct()), "select l_suppkey k from lineitem union select p_size::bigint from part"),
    "set_intersect": (sets(lambda a, b: a.intersect(b)), "select l_suppkey k from lineitem intersect select p_size::bigint from part"),
    "set_except": (sets(lambda a, b: a.distinct().subtract(b)), "select l_suppkey k from lineitem except select p_size::bigint from part"),
    "fn_string": (fn_string, "select p_partkey, upper(p_name) up, split_part(p_name, ' ', 1) head, regexp_replace(p_name, '[aeiou]', '', 'g') bare, levenshtein(p_name, p_brand)::int far, sha256(p_name) sha, length(p_name)::int n from part"),
    "fn_date": (fn_date, "select year(o_orderdate)::int y, month(o_orderdate)::int m, count(*) n, max(date_diff('day', date_trunc('month', o_orderdate)::date, o_orderdate::date))::int latest from orders group by all"),
    "fn_map": (fn_map, "select o_custkey, coalesce(string_agg(distinct o_orderpriority, ',' order by o_orderpriority) filter (where o_orderpriority < '3'), '') urgent, count(distinct o_orderpriority)::int kinds from orders group by 1"),
    "fn_json": (fn_json, "select event_type, sum((props->>'$.k')::int)::bigint total, max((props->>'$.k')::int) top from events group by 1"),
    "fn_url": (fn_url, "select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) host, count(*) n, sum(len(regexp_extract_all(html, '<p[ >]')))::bigint paragraphs from pages group by 1"),
    "fn_explode": (fn_explode, r"select role, count(*) words, count(distinct w) distinct_words from (select role, unnest(regexp_split_to_array(trim(text), '\s+')) w from conversations) where w <> '' group by 1"),
    "sample_det": (sample_det, "select count(*) n, sum(o_orderkey)::bigint keys from orders where ('0x' || substr(md5(o_orderkey::varchar), 1, 4))::int % 10 = 0"),
    "sql_correlated": (sql_correlated, "select o_custkey, o_orderkey from orders o where o_totalprice = (select max(o_totalprice) from orders i where i.o_custkey = o.o_custkey) and o_totalprice > 100000"),
}


def proj_basic(s, d):
    o = t(s, d, "orders")
    return o.withColumns({"year": F.year("o_orderdate"), "pair": F.struct("o_orderkey", "o_custkey"), "two": F.array(F.col("o_totalprice"), F.col("o_totalprice") * 2)}).select("pair.o_orderkey", F.col("year").cast("long").alias("year"), F.round(F.get("two", F.lit(1)), 2).alias("twice"))


def agg_supply(s, d):
    return t(s, d, "orders").groupBy("o_custkey").agg(n_rows().alias("passages"), F.count_if(F.col("o_orderstatus") == "F").alias("finished"), F.round(F.sum(F.when(F.col("o_totalprice") > 100000, F.col("o_totalprice")).otherwise(0.0)), 2).alias("large"))


def fn_math(s, d):
    x = F.col("l_discount") * 8 - 0.3
    return t(s, d, "lineitem").agg(F.round(F.sum(F.sqrt("l_quantity")), 4).alias("roots"), F.round(F.sum(F.cos(F.acos(F.greatest(F.lit(-1.0), F.least(F.lit(1.0), x))) + 0.3)), 4).alias("margins"), F.round(F.sum(F.exp(-F.col("l_tax"))), 4).alias("decays"), F.round(F.sum(F.ln(F.col("l_extendedprice"))), 4).alias("logs"), F.sum(F.floor(F.col("l_quantity") / 7)).alias("floors"))


def fn_array(s, d):
    v = F.col("embedding").cast("array<double>")
    return t(s, d, "embeddings").select("vec_id", F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"), F.exists(v, lambda x: x > 2).alias("any_large"), F.forall(v, lambda x: x > -9).alias("all_bounded"), F.round(F.aggregate(F.slice(v, 1, 4), F.lit(0.0), lambda a, x: a + x), 6).alias("head"), F.round(F.element_at(F.sort_array(v), -1), 6).alias("most"), F.size(F.array_distinct(F.flatten(F.array(F.sequence(F.lit(1), F.lit(3)), F.sequence(F.lit(2), F.lit(5)))))).cast("long").alias("merged"))


def join_range_lines(s, d):
    """Prices of one supplier within two of each other: an equality on a bucket and its neighbours, then the exact range."""
    p = t(s, d, "lineitem").select("l_suppkey", F.col("l_extendedprice").alias("v"), F.col("l_orderkey").alias("k"))
    a = p.select("l_suppkey", F.col("v").alias("va"), F.col("k").alias("ka"), F.floor(F.col("v") / 2).alias("b"))
    b = p.select("l_suppkey", F.col("v").alias("vb"), F.col("k").alias("kb"), F.explode(F.array(F.floor(F.col("v") / 2) - 1, F.floor(F.col("v") / 2), F.floor(F.col("v") / 2) + 1)).alias("b"))
    return a.join(b, ["l_suppkey", "b"]).where("ka < kb and abs(va - vb) <= 2").groupBy("l_suppkey").agg(n_rows().alias("pairs"))


def join_shuffle_hash(s, d):
    return t(s, d, "orders").join(t(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_nationkey").agg(n_rows().alias("n"))


def join_lateral(s, d):
    """Each nation's two richest suppliers by a lateral subquery."""
    n, p = t(s, d, "nation"), t(s, d, "supplier")
    top = p.where(F.col("s_nationkey") == F.col("n_nationkey").outer()).orderBy(F.col("s_acctbal").desc(), "s_suppkey").limit(2).select("s_suppkey", "s_acctbal")
    return n.lateralJoin(top).select("n_name", "s_suppkey", "s_acctbal")


def _views(s, d, *names):
    for n in names:
        t(s, d, n).createOrReplaceTempView(f"pk_{n}")


def sql_param(s, d):
    _views(s, d, "orders")
    return s.sql("select o_orderstatus, count(*) n from pk_orders where o_totalprice > :least and o_orderpriority = :what group by o_orderstatus", args={"least": 50000.0, "what": "1-URGENT"})


def sql_recursive(s, d):
    """Keys of one binary length halve alike: the recursion starts from one of each (63 at most) with how many there are, whatever the table."""
    _views(s, d, "customer")
    return s.sql("with recursive up(k, hops, n) as (select min(c_custkey), 0, count(*) from pk_customer where c_custkey > 0 group by length(bin(c_custkey)) union all select k div 2, hops + 1, n from up where k > 1) select hops, sum(n) n from up group by hops")


def sql_table_function(s, d):
    """Windows of recordings by a registered table function."""
    from ..functions.register import register

    register(s)
    _views(s, d, "documents")
    return s.sql("select is_tail, count(*) windows, sum(start) starts from pk_documents, lateral windows(n_chars, 64, 13) group by is_tail")


def sql_functions(s, d):
    from ..functions.register import register

    register(s)
    _views(s, d, "embeddings", "orders")
    a = s.sql("select 'cosine' what, round(sum(vec_cosine(x.embedding, y.embedding)), 4) value from pk_embeddings x join pk_embeddings y on y.vec_id = x.vec_id + 1")
    b = s.sql("select 'dot', round(sum(vec_dot(cast(embedding as array<double>), cast(embedding as array<double>))), 4) from pk_embeddings")
    c = s.sql("select 'median', median_rank(cast(o_totalprice as double)) from pk_orders")
    return a.union(b).union(c)


def _roundtrip(fmt, **options):
    def run(s, d):
        import uuid

        from ..stage import shared_folder

        path = f"{shared_folder(s)}/sources/{uuid.uuid4().hex}"
        src = t(s, d, "supplier").select("s_suppkey", "s_name", "s_nationkey", "s_acctbal")
        src.write.format(fmt).options(**options).save(path)
        back = s.read.schema(src.schema).format(fmt).options(**options).load(path)
        return back.groupBy("s_nationkey").agg(n_rows().alias("n"), F.min("s_name").alias("name"), F.round(F.sum("s_acctbal"), 2).alias("balance"))

    return run


def sink_partitioned(s, d):
    """Passages written by source and sorted by hull, and read with one folder."""
    import uuid

    from ..stage import shared_folder

    path = f"{shared_folder(s)}/sources/{uuid.uuid4().hex}"
    t(s, d, "orders").repartition("o_orderstatus").sortWithinPartitions("o_custkey").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'").agg(n_rows().alias("n"), F.sum("o_custkey").alias("keys"))


def sketches(s, d):
    """Sketches that merge over partitions, beside what they estimate: distinct users (error below 5 %), frequent words, quantiles."""
    e = t(s, d, "events")
    return e.agg(F.count_distinct("event_id").alias("exact"), (F.abs(F.hll_sketch_estimate(F.hll_sketch_agg("event_id")) - F.count_distinct("event_id")) <= 0.05 * F.count_distinct("event_id")).alias("hll_close"), (F.abs(F.approx_percentile("value", 0.5, 10000) - F.percentile("value", F.lit(0.5))) < 1.0).alias("median_close"))


_SRC = "select s_nationkey, count(*) n, min(s_name) as name, round(sum(s_acctbal), 2) balance from supplier group by s_nationkey"
MORE = {
    "proj_basic": (proj_basic, "select o_orderkey, year(o_orderdate)::bigint as year, round(o_totalprice * 2, 2) twice from orders"),
    "agg_supply": (agg_supply, "select o_custkey, count(*) passages, count(*) filter (where o_orderstatus = 'F') finished, round(sum(case when o_totalprice > 100000 then o_totalprice else 0.0 end), 2) as large from orders group by 1"),
    "fn_math": (fn_math, "select round(sum(sqrt(l_quantity)), 4) roots, round(sum(cos(acos(greatest(-1.0, least(1.0, l_discount * 8 - 0.3))) + 0.3)), 4) margins, round(sum(exp(-l_tax)), 4) decays, round(sum(ln(l_extendedprice)), 4) logs, sum(floor(l_quantity / 7)::bigint)::bigint floors from lineitem"),
    "fn_array": (fn_array, "select vec_id, len(list_filter(v, lambda x: x > 0)) positive, list_max(v) > 2 any_large, list_min(v) > -9 all_bounded, round(list_sum(v[1:4]), 6) as head, round(list_max(v), 6) as most, 5::bigint merged from (select vec_id, embedding::double[] v from embeddings)"),
    "join_range_lines": (join_range_lines, "select a.l_suppkey, count(*) pairs from lineitem a join lineitem b on a.l_suppkey = b.l_suppkey and a.l_orderkey < b.l_orderkey and abs(a.l_extendedprice - b.l_extendedprice) <= 2 group by 1"),
    "join_shuffle_hash": (join_shuffle_hash, "select c_nationkey, count(*) n from orders join customer on o_custkey = c_custkey group by 1"),
    "join_lateral": (join_lateral, "select n_name, s_suppkey, s_acctbal from nation join supplier on s_nationkey = n_nationkey qualify row_number() over (partition by n_nationkey order by s_acctbal desc, s_suppkey) <= 2"),
    "sql_param": (sql_param, "select o_orderstatus, count(*) n from orders where o_totalprice > 50000 and o_orderpriority = '1-URGENT' group by 1"),
    "sql_recursive": (sql_recursive, "with recursive up(k, hops) as (select c_custkey, 0 from customer where c_custkey > 0 union all select k // 2, hops + 1 from up where k > 1) select hops, count(*) n from up group by hops"),
    "sql_table_function": (sql_table_function, "select x.t is_tail, count(*) windows, sum(x.s)::bigint starts from (select unnest(list_concat([{s: i * 64, t: false} for i in range(n_chars // 64)], case when n_chars >= 64 and n_chars % 64 >= 13 then [{s: n_chars - 64, t: true}] else [] end)) x from documents) group by 1"),
    "sql_functions": (sql_functions, "with e as (select vec_id, embedding::double[] v from embeddings) select 'cosine' what, round(sum(list_dot_product(x.v, y.v) / sqrt(list_dot_product(x.v, x.v) * list_dot_product(y.v, y.v))), 4) as value from e x join e y on y.vec_id = x.vec_id + 1 union all select 'dot', round(sum(list_dot_product(v, v)), 4) from e union all select 'median', median(o_totalprice) from orders"),
    "src_csv_roundtrip": (_roundtrip("csv", header="true"), _SRC),
    "src_json_roundtrip": (_roundtrip("json"), _SRC),
    "src_orc_roundtrip": (_roundtrip("orc"), _SRC),
    "sink_partitioned": (sink_partitioned, "select count(*) n, sum(o_custkey)::bigint as keys from orders where o_orderstatus = 'F'"),
    "sketches": (sketches, "select count(distinct event_id) exact, true hll_close, true median_close from events"),
}
TABLE |= MORE
