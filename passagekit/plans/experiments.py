"""Further workloads: identity and splits, preprocessing, query sets, line scores as a method, audit, bootstraps; each with its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..operators import augment as A
from ..operators import blocked as B
from ..operators import dedup as D
from ..operators import encoder as E
from ..operators import measures as M
from ..operators import preprocess as Q
from ..operators import protocol as P
from ..operators import supply as S
from ..operators import tonal as T
from ..sources import carriers as C
from ..stage import settled
from . import retrieval as R
from . import signals as G
from . import supply as Y

t = C.table
n_rows = lambda: F.count(F.lit(1))


# ---- identity and splits
def keyed_customers(s, d):
    rec = t(s, d, "customer").select(F.when(F.col("c_acctbal") > 0, F.col("c_custkey")).alias("key_a"), F.when(F.col("c_nationkey") > 3, F.col("c_name")).alias("key_b"))
    return S.key_hulls(rec).groupBy("key_kind").agg(n_rows().alias("recordings"), F.count_distinct("hull_id").alias("hulls"))


def dropped_unidentified(s, d):
    ids = t(s, d, "customer").select(F.when(F.col("c_custkey") % 7 == 0, F.col("c_name")).when(F.col("c_custkey") % 11 > 0, F.col("c_custkey").cast("string")).alias("hull_id"))
    kept, gone = S.identified(ids)
    return kept.select(F.lit("kept").alias("what")).unionByName(gone.select(F.lit("unidentified").alias("what"))).groupBy("what").agg(n_rows().alias("recordings"))


def proximity_sliding(s, d):
    p = Y._pings(s, d)
    by = p.groupBy(F.window("ts", "300 seconds", "150 seconds")["start"].alias("start"), "vessel_id").agg(F.min("range").alias("r"))
    out = by.groupBy("start").agg(F.count_if(F.col("r") <= 20).alias("near"), F.count_if(F.col("r") <= 60).alias("clear"))
    return out.agg(n_rows().alias("windows"), F.count_if(F.expr("near = 1 and clear = 1")).alias("keyed"))


def nation_distances(s, d):
    lat, lon = (lambda k: k * 7.0 - 80), (lambda k: k * 14.0 - 170)
    n = t(s, d, "nation").select(F.col("n_nationkey").cast("double").alias("k"))
    return n.select(F.col("k").cast("long").alias("k"), F.round(Q.great_circle(lat(F.col("k")), lon(F.col("k")), F.lit(10.0), F.lit(20.0)), 4).alias("km"))


def _passages(s, d):
    """Orders as passages of their customers, the priority as sensor, the price as speed where it is logged."""
    return t(s, d, "orders").select(F.col("o_custkey").alias("hull_id"), F.col("o_orderkey").alias("passage_id"), F.to_date("o_orderdate").alias("day"), F.col("o_orderpriority").alias("sensor"), F.when(F.col("o_orderstatus") == "F", F.col("o_totalprice")).alias("speed"))


def enrolled(s, d):
    return S.split_enrolled(_passages(s, d), 8, 3, 5).groupBy("part").agg(n_rows().alias("hulls"), F.sum("n").alias("passages"))


def heldout_log(s, d):
    """Orders as a log of evaluations: the priority is the set, the customer the model, and a finished one was chosen by its score."""
    log = t(s, d, "orders").select(F.col("o_orderpriority").alias("set"), F.col("o_custkey").alias("model"), (F.col("o_orderstatus") == "F").alias("selected"))
    return S.heldout_uses(log)


def clip_leak(s, d):
    """Recordings and hulls on both sides when segments are split one by one, beside a hull-disjoint split, which has none."""
    rec = t(s, d, "documents").select(F.col("doc_id").alias("recording_id"), F.concat_ws("|", "lang", "source").alias("hull_id"), F.col("n_chars").alias("n_samples"))
    seg = S.split_clips(S.segment(rec, 64, 13, keep=("hull_id",)))
    both = lambda on: S.leakage(seg.where("part = 'train'"), seg.where("part <> 'train'"), on).agg(n_rows().alias("n"))
    return both("recording_id").select(F.lit("recordings").alias("what"), "n").unionByName(both("hull_id").select(F.lit("hulls").alias("what"), "n"))


def sampled(s, d):
    w = t(s, d, "orders").select(F.col("o_orderkey").alias("tensor_id"), F.col("o_totalprice").alias("w"))
    return S.weighted_sampler(w, 100).select("tensor_id")


def regular(s, d):
    g = Q.regular_grid(t(s, d, "events"), "user_id", "value", 86400)
    return g.groupBy("user_id").agg(n_rows().alias("slots"), F.round(F.sum("value"), 4).alias("total"))


# ---- segments
def _znormed(s, d):
    return G._segments(s, d, 32).withColumn("z", A.znorm(F.col("x")))


def znorm_stats(s, d):
    fold = lambda v: F.aggregate(v, F.lit(0.0), lambda a, b: a + b)
    z = _znormed(s, d).select((fold(F.col("z")) / 32).alias("m"), F.sqrt(fold(F.transform("z", lambda v: v * v)) / 32).alias("sd"))
    return z.agg(n_rows().alias("segments"), F.count_if(F.abs("m") > 1e-9).alias("off_centre"), F.count_if(F.abs(F.col("sd") - 1) > 1e-9).alias("off_scale"))


def segment_census(s, d):
    rec = t(s, d, "documents").select(F.col("doc_id").alias("recording_id"), F.concat_ws("|", F.coalesce("lang", F.lit("")), F.coalesce("source", F.lit("")), (F.col("doc_id") % 50).cast("string")).alias("hull_id"), F.col("n_chars").alias("n_samples"))
    part = S.split_hulls(rec).select("hull_id", "part")
    seg = S.segment(rec, 64, 13, keep=("hull_id",)).join(part, "hull_id")
    return seg.rollup("part").agg(n_rows().alias("segments"), F.count_distinct("recording_id").alias("recordings"))


RECS = "rec as (select doc_id recording_id, concat_ws('|', coalesce(lang, ''), coalesce(source, ''), (doc_id % 50)::varchar) hull_id, n_chars n_samples from documents), prt as (select hull_id, case when count(*) >= 2 and ('0x' || substr(md5('7|' || hull_id), 1, 8))::bigint % 1000 < 100 then 'validation' else 'train' end part from rec group by hull_id), sgm as (select recording_id, hull_id, unnest(list_concat([i * 64 for i in range(n_samples // 64)], case when n_samples >= 64 and n_samples % 64 >= 13 then [n_samples - 64] else [] end)) s from rec)"


def pooled(s, d):
    seg = t(s, d, "embeddings").select((F.col("label").cast("long") * 1000 + F.col("vec_id") % 50).alias("passage_id"), F.col("embedding").cast("array<double>").alias("vec"))
    p = P.pool_passages(seg)
    return p.select("passage_id", "n", F.round(F.aggregate(F.transform("vec", lambda v, i: v * (i + 1)), F.lit(0.0), lambda a, b: a + b), 6).alias("mark"))


# ---- query sets and models
def _nets(s, d):
    """Scores of the base network and of one without the enrolled hulls' mean within-hull difference (ours, not a fine-tune)."""
    return G.xnet_scores(s, d)


def xnet_query_sets(s, d):
    sc = _nets(s, d).where("method = 'base'")
    sets = sc.withColumn("set", F.lit("full")).unionByName(sc.where("q_hull % 2 = 1").withColumn("set", F.lit("held-out")))
    return sets.groupBy("set").agg(F.count_distinct("query_id").alias("queries"), F.count_distinct("q_hull").alias("hulls"), F.count_distinct("gallery_id").alias("gallery"))


def xnet_lift(s, d):
    m = G.xnet_metrics(s, d)
    m = m.select(F.substring_index("method", " ", 1).alias("method"), F.substring_index("method", " ", -1).alias("set"), "medr", "auc", "rank1")
    return M.lift(m, "base")


def xnet_finetuned(s, d):
    """Base weights, fine-tune A on the enrolled hulls and B with added single-passage hulls, evaluated on all query hulls and on those
    that neither saw. Warm starts of the encoder by the margin loss; half years of suppliers are passages."""
    spec = E.SMALL
    half = G._segments(s, d, 32).withColumn("hull_id", F.col("hull_id").cast("long"))
    seg = settled(half.select(F.col("recording_id").alias("passage_id"), "hull_id", "start", "x"))
    parts = settled(S.split_enrolled(seg.select("hull_id", "passage_id").distinct(), 8, 0, 4))
    base, _ = E.train(s, _tensors(seg, parts, "n > 0", 16), spec, [1e-3])
    models = {"base": base}
    for name, who, epochs in (("tuned a", "part = 'enrolled'", 2), ("tuned b", "part in ('enrolled', 'added') or n = 2", 1)):
        models[name], _ = E.train(s, _tensors(seg, parts, who, 24), spec, [5e-4] * epochs, {k: v for k, v in base.items() if k != "head"})
    out = None
    for name, model in models.items():
        e = E.embed(seg.select(F.col("passage_id").alias("recording_id"), "start", "x"), model, spec)
        p = P.pool_passages(e.select(F.col("recording_id").alias("passage_id"), "vec")).join(seg.select("passage_id", "hull_id").distinct(), "passage_id")
        r = B.ranks(settled(p.select("passage_id", "hull_id", "vec")), k=0).join(parts.select(F.col("hull_id").alias("q_hull"), "part"), "q_hull")
        for which, cond in (("full", "true"), ("held-out", "part = 'held-out'")):
            one = M.rank_measures(r.where(cond).select(F.lit(f"{name} {which}").alias("method"), "query_id", "rank"))
            out = one if out is None else out.unionByName(one)
    return out


def _tensors(seg, parts, who, hulls):
    """Tensors of the first hulls of those that `who` names: a head is as wide as its classes."""
    own = parts.where(who).orderBy(F.md5(F.col("hull_id").cast("string"))).limit(hulls).withColumn("cls", F.row_number().over(W.orderBy("hull_id")) - 1)
    return seg.join(F.broadcast(own.select("hull_id", "cls")), "hull_id").select(F.xxhash64("passage_id", "start").alias("tensor_id"), "cls", "x")


def fixed_ranks(s, d):
    p = settled(C.planted(t(s, d, "embeddings")))
    return M.rank_measures(P.true_rank(P.fixed_gallery(p.where("passage_no > 0"), p.where("passage_no = 0"))))


def hull_ranks(s, d):
    return M.rank_measures(P.true_rank_of_hulls(R._all(s, d)))


def overlap_free(s, d):
    """Sessions of one vessel: pairs that the constraint leaves, of all ordered pairs."""
    ev = t(s, d, "events").where("event_type = 'purchase'").groupBy("user_id", F.to_date("ts").alias("day")).agg(F.min("ts").alias("first"), F.max("ts").alias("last"))
    spans = settled(ev.select((F.col("user_id") * 100000 + F.datediff("day", F.lit("2000-01-01"))).alias("passage_id"), "user_id", "first", (F.col("last") + F.expr("interval 20 hours")).alias("last")))
    side = lambda i: spans.select(F.col("passage_id").alias(i), "user_id")
    pairs = side("query_id").join(side("gallery_id"), "user_id")
    return P.cross_passage(pairs, spans.drop("user_id")).agg(n_rows().alias("pairs"))


SPANS = "e as (select user_id, ts::date dd, min(ts) a, max(ts) b from events where event_type = 'purchase' group by all), sp as (select user_id, user_id * 100000 + (dd - date '2000-01-01') pid, a, b + interval 20 hours b from e)"


def roundtrip(s, d):
    """Scores written, read again and compared with scores computed anew."""
    first = R._planted_scores(s, d)
    again = P.leave_one_out(C.planted(t(s, d, "embeddings"))).select("query_id", "gallery_id", F.col("sim").alias("again"))
    both = first.join(again, ["query_id", "gallery_id"], "full_outer")
    return both.agg(n_rows().alias("pairs"), F.count_if(F.coalesce(F.abs(F.col("sim") - F.col("again")) > 1e-4, F.lit(True))).alias("beyond"))


def weighted_fusion(s, d):
    return M.evaluate_networks(R._networks(s, d, fused="weighted", weights={"a": 1.0, "b": 3.0}), ["weighted"])


# ---- lines as a method
def _line_passages(s, d):
    """Supplier years as passages with line sets; their suppliers are hulls."""
    li = t(s, d, "lineitem").withColumn("rid", (F.col("l_suppkey") * 10000 + F.year("l_shipdate")).cast("long"))
    order = W.partitionBy("rid").orderBy("l_shipdate", "l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    at = li.select("rid", (F.row_number().over(order) - 1).alias("k"), F.col("l_extendedprice").alias("v"))
    f = at.groupBy(F.col("rid").alias("rec"), F.expr("k div 32").cast("long").alias("frame")).agg(F.transform(F.array_sort(F.collect_list(F.struct("k", "v"))), lambda x: x["v"]).alias("x")).where("size(x) = 32")
    found = T.persistent(settled(T.lines(T.whiten(T.spectrum(f, 32, 16)))), f, 0.3)
    return T.line_sets(found).select(F.col("rec").alias("passage_id"), F.expr("rec div 10000").alias("hull_id"), "bits")


def tonal_metrics(s, d):
    ranks, points = T.line_measures(_line_passages(s, d))
    return M.rank_measures(ranks).join(M.curve_of_points(points).where("eer is not null"), "method")


LINES = Y.WHITE.replace("fr as (select l_suppkey rec, (row_number() over (partition by l_suppkey order by", "fr as (select l_suppkey * 10000 + year(l_shipdate) rec, (row_number() over (partition by l_suppkey, year(l_shipdate) order by").replace(">= 0.1)", ">= 0.3)")
_NEAR = "((1::bigint << ({b} - 1)::int) | (1::bigint << {b}::int) | (1::bigint << ({b} + 1)::int))"
TONAL = f"""{LINES}, pa as (select rec passage_id, rec // 10000 hull_id, bit_or(1::bigint << bin::int) bits, bit_or({_NEAR.format(b='bin')}) wide from pl group by rec),
    pr as (select q.passage_id query_id, g.passage_id gallery_id, q.hull_id q_hull, g.hull_id g_hull, bit_count(q.bits & g.wide) a, bit_count(g.bits & q.wide) b, bit_count(q.bits) n, bit_count(g.bits) m from pa q join pa g on q.passage_id <> g.passage_id where q.hull_id in (select hull_id from pa group by 1 having count(*) > 1)),
    s as (select 'one side' as method, query_id, gallery_id, q_hull, g_hull, round(a::double / n, 9) sim from pr union all select 'both sides', query_id, gallery_id, q_hull, g_hull, round((a::double + b) / (n::double + m), 9) from pr)"""


def tonal_tpsw(s, d):
    w = T.whiten(T.spectrum(Y._frames(s, d), 32, 16))
    return w.groupBy("rec", "bin").agg(n_rows().alias("frames"), F.round(F.avg("ratio"), 6).alias("ratio"))


def shared_lines(s, d):
    """Lines that the first two recordings have in common, within one bin."""
    found = settled(Y._lines(s, d)[1])
    return T.common_lines(found, 1, 2).select("bin", F.round("persistence", 6).alias("persistence"))


# ---- deduplication
def nominated(s, d):
    return D.nominate(G._rec(s, d)).select("a", "b", "reason")


def texture(s, d):
    return G._evidence(s, d).where("reason = 'same hull'").select("a", "b", "t")


def illusory(s, d):
    _, m = G._moved(s, d)
    return m.groupBy("hull").agg(n_rows().alias("recordings"), F.count_distinct("transit_id").alias("transits")).where("recordings > 1 and transits = 1")


def doc_islands(s, d):
    """Runs of neighbouring ids among texts that several hulls (language and source) hold, byte for byte."""
    rec = t(s, d, "documents").where("text is not null").select("doc_id", F.concat_ws("|", "lang", "source").alias("hull"), F.md5("text").alias("h"))
    shared = rec.groupBy("h").agg(F.count_distinct("hull").alias("n")).where("n > 1")
    return D.islands(rec.join(shared, "h", "left_semi").withColumn("block", F.expr("doc_id div 1000")), "block", "doc_id")


def findings(s, d):
    dig = G._rec(s, d).select("rid", F.md5(F.concat_ws(",", F.transform("x", lambda v: F.round(v, 2).cast("string")))).alias("g"))
    dig = settled(dig)
    p = D.nominate(G._rec(s, d)).where("reason <> 'same hull'").select("a", "b")
    p = p.join(dig.select(F.col("rid").alias("a"), F.col("g").alias("a_digest")), "a").join(dig.select(F.col("rid").alias("b"), F.col("g").alias("b_digest")), "b")
    return D.finding_class(p, 10000).groupBy("finding").agg(n_rows().alias("pairs"))


def report(s, d):
    v = D.evidence(D.nominate(G._rec(s, d), carry=("res", "z"))).where("reason = 'same hull'")
    v = v.select(F.when(F.col("a_hull") % 10 == 0, "validation").otherwise("train").alias("part"), "same_key", (G.RULES[0].verdict(F.col("t"), F.col("w")) != "distinct").alias("confirmed"))
    return D.audit_report(v)


def rule_compare(s, d):
    """Pairs under the joint rule and single cuts, on the evidence of the recordings themselves."""
    ev = G._evidence(s, d)
    v = G.RULES[0].verdict(F.col("t"), F.col("w"))
    return ev.groupBy(v.alias("verdict")).agg(n_rows().alias("pairs"), F.count_if(F.col("t") >= 0.10).alias("cut10"), F.count_if(F.col("t") >= 0.37).alias("cut37"))


def accepted(s, d):
    """Expected decisions, written down before the rule ran: every re-filed recording is merged with its original."""
    ev = G._evidence(s, d).where("a = -b and reason = 'same hull'")
    got = ev.select("a", (G.RULES[3].verdict(F.col("t"), F.col("w")) != "distinct").alias("value"))
    want = G._rec(s, d).where("rid < 0").select(F.col("rid").alias("a"), F.lit(True).alias("value"))
    return D.acceptance(got, want, ["a"]).select("a", "expected", "got", "ok")


def null_bars_published(s, d):
    """The null bars at four times the p95, as published, beside twice."""
    ev = settled(D.evidence(D.null_pairs(G._rec(s, d), 300)))
    two = D.null_bars(ev, 2.0).withColumn("factor", F.lit(2.0))
    return two.unionByName(D.null_bars(ev, 4.0).withColumn("factor", F.lit(4.0)))


# ---- large gallery of events
def event_reid(s, d):
    """Days of a user as passages, histograms of their values as vectors."""
    at, n = F.least(F.floor(F.col("value") / 10.0), F.lit(15)), n_rows()
    by = t(s, d, "events").groupBy(F.col("user_id").alias("hull"), F.to_date("ts").alias("day")).agg(F.array(*(F.count_if(at == b) / n for b in range(16))).alias("h"))
    h = settled(by.select((F.col("hull") * 100000 + F.datediff("day", F.lit("2000-01-01"))).alias("passage_id"), F.col("hull").alias("hull_id"), "h"))
    rec = settled(D.residual(h, 16).select("passage_id", "hull_id", F.transform("res", lambda v: F.round(v, 6)).alias("vec")))
    return M.rank_measures(B.ranks(rec, k=0).select(F.lit("blocked").alias("method"), "query_id", "rank"))


EVENTS = "r0 as (select user_id * 100000 + (ts::date - date '2000-01-01') rid, user_id hull, list(value order by ts, event_id) x from events group by 1, 2), h0 as (select rid, hull, list_transform(range(16), lambda b: len(list_filter(x, lambda v: least(floor(v / 10), 15) = b)) / len(x)) h from r0), hm as (select list(m order by k) mean_h from (select k, avg(e) m from (select unnest(h) e, generate_subscripts(h, 1) k from h0) group by k)), h1 as (select rid, hull, list_transform(range(1, 17), lambda i: h[i] - mean_h[i]) q from h0, hm), pa as (select rid passage_id, hull hull_id, '' as source, list_transform(q, lambda v: round(v / coalesce(nullif(sqrt(list_dot_product(q, q)), 0), 1), 6)) vec from h1)"


# ---- inference
def two_way(s, d):
    return _interval(R._networks(s, d).bootstrap(lambda hulls: (M.draws(hulls, 100), M.draws(hulls, 100, offset=100)), 100))


def naive(s, d):
    return _interval(M.bootstrap_queries(settled(M.query_wins_of_ranks(R._ranks(s, d))), 100))


def _interval(b):
    return b.groupBy("method").agg(F.round(F.percentile("auc", F.lit(0.025)), 6).alias("lo"), F.round(F.percentile("auc", F.lit(0.975)), 6).alias("hi"))


def _draws(name: str, of: str, unit: str, shift: int = 0) -> str:
    return f"{name}l as (select distinct {unit} u from {of}), {name}h as (select u, row_number() over (order by u) - 1 pick from {name}l), {name} as (select r, u, count(*) w from (select r, ('0x' || substr(md5((r + {shift}) || '|' || p), 1, 8))::bigint % (select count(*) from {name}l) pick from (select unnest(range(100)) r) a, (select unnest(range((select count(*) from {name}l))) p) b) join {name}h using (pick) group by all)"


_CI = "select method, round(quantile_cont(auc, 0.025), 6) lo, round(quantile_cont(auc, 0.975), 6) hi from bt group by method"
_RANKED = "r as (select method, query_id, q_hull, best, 1 + count(*) filter (where sim > best) as rank, count(*) candidates from (select *, max(case when q_hull = g_hull then sim end) over (partition by method, query_id) best from s2) where best is not null group by all)"
XN = lambda: G.TABLE["xnet_metrics"][1]

TABLE = {
    "key_first_identifier": (keyed_customers, "with k as (select case when c_acctbal > 0 then c_custkey::varchar end a, case when c_nationkey > 3 then c_name end b from customer) select case when a is not null then 'key_a' when b is not null then 'key_b' end key_kind, count(*) recordings, count(distinct coalesce(a, b)) hulls from k group by 1"),
    "drop_unidentified": (dropped_unidentified, "select case when c_custkey % 7 <> 0 and c_custkey % 11 > 0 then 'kept' else 'unidentified' end what, count(*) recordings from customer group by 1"),
    "proximity_sliding": (proximity_sliding, "with e as (select user_id, value, unnest([time_bucket(interval 150 seconds, ts), time_bucket(interval 150 seconds, ts) - interval 150 seconds]) w from events), b as (select w, user_id, min(value) r from e group by all), p as (select w, count(*) filter (where r <= 20) near, count(*) filter (where r <= 60) clear from b group by w) select count(*) windows, count(*) filter (where near = 1 and clear = 1) keyed from p"),
    "fn_great_circle": (nation_distances, "select k::bigint k, round(2 * 6371 * asin(sqrt(least(1.0, power(sin((radians(10.0) - radians(k * 7.0 - 80)) / 2), 2) + cos(radians(k * 7.0 - 80)) * cos(radians(10.0)) * power(sin(radians(20.0 - (k * 14.0 - 170)) / 2), 2)))), 4) km from (select n_nationkey::double k from nation)"),
    "split_enrolled": (enrolled, "with b as (select o_custkey h, count(*) n, md5('7|' || o_custkey) u from orders group by 1), k as (select *, row_number() over (partition by n > 1 order by u) k from b) select case when n > 1 and k <= 3 then 'sequestered' when n > 1 and k <= 11 then 'enrolled' when n > 1 then 'held-out' when k <= 5 then 'added' else 'gallery' end part, count(*) hulls, sum(n)::bigint passages from k group by 1"),
    "heldout_uses": (heldout_log, "select o_orderpriority as set, count(*) uses, count(*) filter (where o_orderstatus = 'F') selections from orders group by 1"),
    "split_clips_control": (clip_leak, "with seg as (select recording_id, hull_id, unnest(list_concat([i * 64 for i in range(n_samples // 64)], case when n_samples >= 64 and n_samples % 64 >= 13 then [n_samples - 64] else [] end)) s from (select doc_id recording_id, concat_ws('|', lang, source) hull_id, n_chars n_samples from documents)), p as (select *, ('0x' || substr(md5('7|' || recording_id || '|' || s), 1, 8))::bigint % 1000 < 100 v from seg) select 'recordings' as what, count(*) n from (select recording_id from p group by 1 having bool_or(v) and not bool_and(v)) union all select 'hulls', count(*) from (select hull_id from p group by 1 having bool_or(v) and not bool_and(v))"),
    "corpus_readiness": (lambda s, d: S.corpus_readiness(_passages(s, d)), "select count(*) hulls, count(*) filter (where d > 1) repeat_days, count(*) filter (where p > 1) several_sensors, sum(v)::bigint with_speed from (select o_custkey, count(distinct o_orderdate::date) d, count(distinct o_orderpriority) p, count(*) filter (where o_orderstatus = 'F') v from orders group by 1)"),
    "pair_supply": (lambda s, d: S.pair_supply(_passages(s, d)), "select count(*) filter (where n > 1) with_pairs, count(*) filter (where n = 1) singletons, sum(n * (n - 1) // 2)::bigint pairs from (select count(*) n from orders group by o_custkey)"),
    "weighted_sampler": (sampled, "select o_orderkey tensor_id from orders order by -ln((('0x' || substr(md5('7|' || o_orderkey), 1, 8))::bigint + 0.5) / 4294967296.0) / o_totalprice, o_orderkey limit 100"),
    "regular_grid": (regular, "with b as (select user_id, epoch(ts)::bigint // 86400 slot, arg_max(value, (ts, value)) v from events group by all), n as (select *, coalesce(lead(slot) over (partition by user_id order by slot) - slot, 1) k from b) select user_id, sum(k)::bigint slots, round(sum(k * v), 4) total from n group by user_id"),
    "segment_tail": (lambda s, d: S.segment_outcomes(Y._docs(s, d), 64, 13), "select case when n_chars is null or n_chars < 64 then 'short' when n_chars % 64 = 0 then 'no tail' when n_chars % 64 >= 13 then 'tail kept' else 'tail dropped' end outcome, count(*) recordings, sum(coalesce(n_chars, 0) % 64)::bigint tail_samples from documents group by 1"),
    "segment_znorm_stats": (znorm_stats, f"with {G.REC}, sg as (select x[s + 1:s + 32] x from (select x, unnest(list_concat([i * 32 for i in range(len(x) // 32)], case when len(x) >= 32 and len(x) % 32 >= 6 then [len(x) - 32] else [] end)) s from r0)) select count(*) segments, 0::bigint off_centre, count(*) filter (where list_stddev_pop(x) <= 1e-12) off_scale from sg"),
    "segment_census": (segment_census, f"with {RECS} select part, count(*) segments, count(distinct recording_id) recordings from sgm join prt using (hull_id) group by rollup(part)"),
    "pool_passages": (pooled, "with u as (select label::bigint * 1000 + vec_id % 50 passage_id, vec_id, list_transform(embedding::double[], lambda x: x / sqrt(list_dot_product(embedding::double[], embedding::double[]))) v from embeddings), m as (select passage_id, k, avg(e) m, count(*) n from (select passage_id, unnest(v) e, generate_subscripts(v, 1) k from u) group by all), l as (select passage_id, max(n) n, list(m order by k) v from m group by 1) select passage_id, n, round(list_sum(list_transform(range(1, len(v) + 1), lambda i: v[i] * i)) / sqrt(list_dot_product(v, v)), 6) mark from l"),
    "xnet_query_sets": (xnet_query_sets, f"with {R.BASE}, {R._planted('p0', lam=3.0)}, {R._scores('s', 'p0', 'base')} select 'full' as set, count(distinct query_id) queries, count(distinct q_hull) hulls, count(distinct gallery_id) gallery from s union all select 'held-out', count(distinct query_id), count(distinct q_hull), count(distinct gallery_id) from s where q_hull % 2 = 1"),
    "xnet_lift": (xnet_lift, f"with xm as ({XN()}), y as (select split_part(method, ' ', 1) m, split_part(method, ' ', 2) set, * from xm) select a.m as method, a.set, round(a.medr / b.medr, 6) medr_ratio, round(a.auc - b.auc, 6) auc_gain, round(a.rank1 - b.rank1, 6) rank1_gain from y a join y b on a.set = b.set and b.m = 'base' and a.m <> 'base'"),
    "xnet_finetuned": (xnet_finetuned, None),
    "fixed_gallery": (fixed_ranks, f"with {R.BASE}, {R._planted('pa')}, s as (select 'fixed' as method, q.passage_id query_id, g.passage_id gallery_id, q.hull_id q_hull, g.hull_id g_hull, round(list_dot_product(q.vec, g.vec), 9) sim from pa q join pa g on q.passage_no > 0 and g.passage_no = 0), {R.RANKS} select method, {R.RANK_COLS} from r group by method"),
    "rank_by_hull": (hull_ranks, f"with {R.THREE.rsplit(', r as', 1)[0]}, s2 as (select method, query_id, q_hull, g_hull, max(sim) sim from s group by all), {_RANKED} select method, {R.RANK_COLS} from r group by method"),
    "cross_passage_pairs": (overlap_free, f"with {SPANS} select count(*) pairs from sp q join sp g on q.user_id = g.user_id and q.pid <> g.pid where q.b < g.a or g.b < q.a"),
    "score_roundtrip": (roundtrip, f"with {R.SINGLE} select count(*) pairs, 0::bigint beyond from s"),
    "fused_weighted": (weighted_fusion, f"with {R.THREE.split('sf as (')[0].rstrip().rstrip(',')}, s as (select 'weighted' as method, query_id, gallery_id, q_hull, g_hull, round(sum(z * case when method = 'a' then 1.0 else 3.0 end) / 4, 9) sim from z group by query_id, gallery_id, q_hull, g_hull), {R.RANKS}, {R.POINTS} {R.ROW}"),
    "false_top": (lambda s, d: M.wrong_top_of_ranks(R._ranks(s, d)), f"with {R.THREE}, tp as (select method, q_hull, g_hull, sim from s qualify row_number() over (partition by method, query_id order by sim desc, gallery_id) = 1) select method, count(*) n, round(min(sim), 6) lowest, round(avg(sim), 6) mean, round(max(sim), 6) highest from tp where q_hull <> g_hull group by method"),
    "discordance": (lambda s, d: M.discordance(R._ranks(s, d), "a", "b"), f"with {R.THREE}, x as (select query_id, max(rank) filter (where method = 'a') ra, max(rank) filter (where method = 'b') rb from r group by query_id) select k, count(*) queries, count(*) filter (where (ra <= k) <> (rb <= k)) discordant, round(avg(case when (ra <= k) <> (rb <= k) then 1.0 else 0 end), 6) share from x, (select unnest([1, 5, 10]) k) group by k"),
    "eer": (lambda s, d: M.eer_of_points(R._networks(s, d).points()), f"with {R.THREE}, {R.POINTS} select * from eer"),
    "auc_all_genuine": (lambda s, d: M.curve_of_points(R._networks(s, d).points("all")).select("method", "auc"), f"with {R.THREE}, pts as (select method, sim, (q_hull = g_hull)::int same from s), rc as (select method, sim, sum(same) g, sum(1 - same) i, sum(sum(1 - same)) over (partition by method order by sim desc) ci, sum(sum(same)) over (partition by method) tg, sum(sum(1 - same)) over (partition by method) ti from pts group by method, sim) select method, round(sum(g * (ti - ci + 0.5 * i)) / max(tg::double * ti), 6) auc from rc group by method"),
    "tonal_metrics": (tonal_metrics, f"with {TONAL}, {R.RANKS}, {R.POINTS} {R.ROW}"),
    "tonal_tpsw": (tonal_tpsw, f"with {Y.WHITE} select rec, bin, count(*) frames, round(avg(ratio), 6) ratio from wh group by rec, bin"),
    "tonal_common": (shared_lines, f"with {Y.WHITE} select bin, round(persistence, 6) persistence from pl where rec = 1 and exists (select 1 from pl g where g.rec = 2 and abs(g.bin - pl.bin) <= 1)"),
    "meta_groups": (lambda s, d: t(s, d, "documents").groupBy("lang", "source", F.expr("n_chars div 100").alias("bucket")).agg(n_rows().alias("n")), "select lang, source, n_chars // 100 bucket, count(*) n from documents group by all"),
    "dedup_nominate": (nominated, f"with {G.PREP}, {G.PAIRS} select a, b, reason from prs"),
    "dedup_texture_hist": (texture, f"with {G.EV} select a, b, t from ev where reason = 'same hull'"),
    "dedup_illusory": (illusory, f"{G.TRANSITS} select hull, count(*) recordings, count(distinct transit_id) transits from mv group by hull having count(*) > 1 and count(distinct transit_id) = 1"),
    "dedup_islands": (doc_islands, "with r as (select doc_id, concat_ws('|', lang, source) hull, md5(text) h from documents where text is not null), i as (select doc_id, doc_id // 1000 block from r where h in (select h from r group by h having count(distinct hull) > 1)) select block, min(doc_id) as first, max(doc_id) as last, count(*) n from (select *, doc_id - row_number() over (partition by block order by doc_id) run from i) group by block, run"),
    "dedup_findings": (findings, f"with {G.PREP}, {G.PAIRS}, dg as (select rid, md5(array_to_string(list_transform(x, lambda v: round(v, 2)::varchar), ',')) g from rec) select case when x.g = y.g then 'identical file' when abs(a - b) <= 10000 then 'neighbouring ids' else 'shared scene' end finding, count(*) pairs from prs join dg x on x.rid = a join dg y on y.rid = b where reason <> 'same hull' group by 1"),
    "dedup_audit_report": (report, f"with {G.EV}, v as (select case when ah % 10 = 0 then 'validation' else 'train' end part, case when x.key = y.key and {G.JOINT} <> 'distinct' then 'both' when {G.JOINT} <> 'distinct' then 'audio only' when x.key = y.key then 'metadata only' else 'neither' end who from ev join pre x on x.rid = a join pre y on y.rid = b where reason = 'same hull') select part, who, count(*) pairs from v group by cube(part, who)"),
    "dedup_rule_compare": (rule_compare, f"with {G.EV} select {G.JOINT} verdict, count(*) pairs, count(*) filter (where t >= 0.10) cut10, count(*) filter (where t >= 0.37) cut37 from ev group by 1"),
    "dedup_acceptance": (accepted, f"with {G.EV}, e as (select a, w >= 0.8 or t >= 0.6 got from ev where a = -b and reason = 'same hull') select rid a, true expected, got, coalesce(got, false) ok from rec left join e on rid = a where rid < 0"),
    "dedup_null_bars": (null_bars_published, f"with {G.EV}, {G.NULLS}, f as (select unnest([2.0::double, 4.0]) factor) select factor, count(*) n_null, round(quantile_cont(t, 0.99), 6) texture_bar, round(factor * quantile_cont(w, 0.95), 6) wave_bar from nv, f group by factor"),
    "event_reid": (event_reid, f"with {EVENTS}, {R._scores('s', 'pa', 'blocked')}, {R.RANKS} select method, {R.RANK_COLS} from r group by method"),
    "boot_two_way": (two_way, f"with {R.THREE}, {R.WINS}, {_draws('da', 'wm', 'g_of')}, {_draws('db', 'wm', 'g_of', 100)}, bt as (select method, da.r, sum(da.w * db.w * wins) / sum(da.w * db.w * pairs) auc from wm join da on da.u = g_of join db on db.u = i_of and db.r = da.r group by all) {_CI}"),
    "boot_naive": (naive, f"with {R.THREE}, g as (select method, query_id, max(sim) gs from s where q_hull = g_hull group by all), qw as (select method, query_id, sum(case when gs > sim then 1.0 when gs = sim then 0.5 else 0 end)::double wins, count(*) pairs from g join s using (method, query_id) where q_hull <> g_hull group by all), {_draws('da', 'qw', 'query_id')}, bt as (select method, r, sum(w * wins) / sum(w * pairs) auc from qw join da on u = query_id group by all) {_CI}"),
}
