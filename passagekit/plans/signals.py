"""Workloads on deduplication evidence, augmentation, the encoder and large galleries, each with its SQL where SQL can state it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.vectors import add, dot, unit
from ..operators import augment as A
from ..operators import blocked as B
from ..operators import dedup as D
from ..operators import encoder as E
from ..operators import measures as M
from ..operators import protocol as P
from ..operators import supply as S
from ..sources import carriers as C
from ..stage import settled
from . import retrieval as R
from . import supply as Y

WIDTH, BINS, STEP = 3500.0, 32, 2000.0
RULES = [D.Rule(), D.Rule("cut10", 0.10, None, None), D.Rule("cut37", 0.37, None, None), D.Rule("short", 0.60, None, None)]
# some ninety samples a recording: chance correlations are larger than of audio, so the published bars refuse every published
# rule; with twice the p95 (not four times) the gate approves the stricter last one, which makes the transit map
FACTOR = 2.0

# ---- DuckDB side of the supplier-year recordings and their evidence
REC = """r0 as (select l_suppkey * 10000 + year(l_shipdate) rid, l_suppkey::bigint hull, list(l_extendedprice order by l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity, l_extendedprice) x from lineitem group by all),
    rec as (select rid, hull, x from r0 union all select -rid, hull, list_transform(x, lambda v: 0.99 * v + 100.0) from r0 where hull % 5 = 0 and rid % 3 = 0)"""
HIST = """h0 as (select rid, hull, x, list_transform(range(32), lambda b: len(list_filter(x, lambda v: least(floor(v / 3500), 31) = b)) / len(x)) h from {of}),
    hm as (select list(m order by k) mean_h from (select k, avg(e) m from (select unnest(h) e, generate_subscripts(h, 1) k from h0) group by k)),
    h1 as (select rid, hull, x, list_transform(range(1, 33), lambda i: h[i] - mean_h[i]) q from h0, hm),
    h2 as (select rid, hull, x, list_transform(q, lambda v: v / coalesce(nullif(sqrt(list_dot_product(q, q)), 0), 1)) res from h1)"""
PREP = f"""{REC}, {HIST.format(of='rec')},
    c1 as (select rid, hull, res, len(x) || '|' || floor(list_max(x) / 2000)::bigint as key, list_transform(x, lambda v: v - list_avg(x)) c from h2),
    pre as (select rid, hull, res, key, list_transform(c, lambda v: case when sqrt(list_dot_product(c, c) / len(c)) > 1e-12 then v / sqrt(list_dot_product(c, c) / len(c)) else 0 end) z from c1)"""


def _lag(k: int) -> str:
    x, y = ("az", "bz") if k >= 0 else ("bz", "az")
    m = f"greatest(0, least(len({x}), len({y}) - {abs(k)}))"
    return f"abs(coalesce(list_dot_product({x}[1:{m}], {y}[{abs(k) + 1}:{abs(k)} + {m}]), 0))"


PAIRS = """rare as (select key from pre group by key having count(*) between 2 and 4),
    prs as (select a.rid a, b.rid b, a.hull ah, b.hull bh, a.res ar, b.res br, a.z az, b.z bz, 'same hull' as reason from pre a join pre b on a.hull = b.hull and a.rid < b.rid
      union all select a.rid, b.rid, a.hull, b.hull, a.res, b.res, a.z, b.z, 'rare key' from pre a join pre b on a.key = b.key and a.hull <> b.hull and a.rid < b.rid where a.key in (select key from rare)
      union all select a.rid, b.rid, a.hull, b.hull, a.res, b.res, a.z, b.z, 'rare length' from pre a join pre b on len(a.z) = len(b.z) and a.key <> b.key and a.hull <> b.hull and a.rid < b.rid where len(a.z) in (select len(z) from pre group by 1 having count(*) between 2 and 4))"""
EVID = "select a, b, ah, bh, reason, round(list_dot_product(ar, br), 6) t, round(greatest(" + ", ".join(_lag(k) for k in range(-3, 4)) + ") / sqrt(len(az) * len(bz)::double), 6) w from {of}"
JOINT = "case when w >= 0.80 then 'same capture' when t >= 0.40 or t >= 0.20 and w >= 0.15 then 'same transit' else 'distinct' end"
EV = f"{PREP}, {PAIRS}, ev as ({EVID.format(of='prs')})"
NULLS = f"""n0 as (select *, md5(rid::varchar) u from pre order by u limit 600),
    n1 as (select rid a, hull ah, res ar, z az, lead(rid) over o b, lead(hull) over o bh, lead(res) over o br, lead(z) over o bz, u, 'null' as reason from n0 window o as (order by u)),
    n2 as (select * from n1 where b is not null and ah <> bh qualify row_number() over (order by u) <= 300), nv as ({EVID.format(of='n2')}),
    bars as (select count(*) n_null, round(quantile_cont(t, 0.99), 6) texture_bar, round(2 * quantile_cont(w, 0.95), 6) wave_bar from nv)"""
CLOSURE = """edg as (select a, b from ev where reason = 'same hull' and (w >= 0.80 or t >= 0.60)), sym as (select a, b from edg union all select b, a from edg)"""
TRANSITS = f"with recursive {EV}, {CLOSURE}, reach as (select rid a, rid b from pre union select reach.a, sym.b from reach join sym on reach.b = sym.a), mv as (select rid, hull, t transit_id from pre join (select a, min(b) t from reach group by a) on a = rid)"


def _rec(s, d):
    return settled(D.prepared(C.supplier_years(C.table(s, d, "lineitem")), WIDTH, BINS, STEP))


def _evidence(s, d):
    return D.evidence(D.nominate(_rec(s, d), carry=("res", "z")))


def _verdict(ev):
    return ev.withColumn("verdict", RULES[0].verdict(F.col("t"), F.col("w")))


def _moved(s, d):
    rec = _rec(s, d)
    edges = _evidence(s, d).where("reason = 'same hull'").where(RULES[3].verdict(F.col("t"), F.col("w")) != "distinct")
    return rec, D.transits(edges, rec)


def nominate_counts(s, d):
    return D.nominate(_rec(s, d)).groupBy("reason").agg(F.count(F.lit(1)).alias("pairs"), F.count_distinct("a").alias("recordings"))


def null_quantiles(s, d):
    return D.null_bars(D.evidence(D.null_pairs(_rec(s, d), 300)), FACTOR)


def gate_verdicts(s, d):
    rec = _rec(s, d)
    known = rec.where("rid < 0").select(F.col("rid").alias("a"), (-F.col("rid")).alias("b"))
    return D.gate(_evidence(s, d), known, D.null_bars(D.evidence(D.null_pairs(rec, 300)), FACTOR), RULES)


def audit(s, d):
    _, m = _moved(s, d)
    by = m.groupBy("hull").agg(F.count(F.lit(1)).alias("r"), F.count_distinct("transit_id").alias("t"))
    by = D.require(by, gate_verdicts(s, d), "short")
    return by.agg(F.sum("r").alias("recordings"), F.sum("t").alias("transits"), F.sum(F.col("r") - F.col("t")).alias("redundant"), F.count_if((F.col("r") > 1) & (F.col("t") == 1)).alias("illusory_hulls"))


def cross_hull(s, d):
    """Confirmed pairs across hulls are reported as label noise and never merged."""
    v = _verdict(_evidence(s, d)).where("reason <> 'same hull'")
    return v.groupBy("verdict").agg(F.count(F.lit(1)).alias("pairs"))


def merge_quality(s, d):
    """Pairs of one hull that metadata alone would merge, against those the audio confirms."""
    v = _verdict(D.evidence(D.nominate(_rec(s, d), carry=("res", "z"))))
    same, audio = F.col("same_key"), F.col("verdict") != "distinct"
    return v.where("reason = 'same hull'").agg(F.count_if(same & audio).alias("in_both"), F.count_if(same & ~audio).alias("metadata_only"), F.count_if(~same & audio).alias("audio_only"))


def fft_evidence(s, d):
    return D.fft_evidence(D.nominate(_rec(s, d), carry=("x",))).groupBy("reason").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(RULES[0].verdict(F.col("t"), F.col("w")) != "distinct").alias("confirmed"), F.avg("t").alias("mean_t"))


# ---- augmentation of whole series beside a fixed ambient series
SEG = f"{REC}, sg as (select rid, list_transform(x, lambda v: v / 1000) x from rec), am as (select rid, x, list_transform(range(len(x)), lambda i: sin(1.7 * i)) nz from sg)"


def _seg(s, d):
    rec = C.supplier_years(C.table(s, d, "lineitem"))
    nz = F.transform("x", lambda v, i: F.sin(F.lit(1.7) * i))
    return rec.select("rid", F.transform("x", lambda v: v / 1000).alias("x"), nz.alias("nz"))


def _summed(df, y):
    """A checksum of each array that its order changes; the factor keeps sums of short decimals off the ties of rounding."""
    return df.select("rid", F.round(F.aggregate(F.transform(y, lambda v, i: v * (i + 1)), F.lit(0.0), lambda a, b: a + b) * 1.4142135623, 4).alias("mark"))


def _aug(make, sql):
    return (lambda s, d: _summed(_seg(s, d), make(F.col("x"), F.col("nz"))), f"with {SEG}, y as (select rid, {sql} y from am) select rid, round(list_sum(list_transform(range(1, len(y) + 1), lambda i: y[i] * i)) * 1.4142135623::double, 4) mark from y")


def gain_inert(s, d):
    x = F.col("x")
    return _summed(_seg(s, d), F.zip_with(A.znorm(A.gain(x, 7.0)), A.znorm(x), lambda a, b: F.round(F.abs(a - b), 6)))


def _segments(s, d, width=64):
    rec = C.supplier_years(C.table(s, d, "lineitem"), copies=False).select(F.col("rid").alias("recording_id"), F.col("hull").alias("hull_id"), F.size("x").cast("long").alias("n_samples"), F.col("x").alias("all_x"))
    at = S.segment(rec, width, width // 5, keep=("hull_id", "all_x"))
    return at.select("recording_id", "hull_id", "start", F.slice("all_x", F.col("start").cast("int") + 1, F.lit(width)).alias("x"))


def peak_check(s, d):
    noise = np.random.default_rng(5).normal(0, 1, (8, 64))
    a = A.augment(_segments(s, d), noise, rate=64.0).where("copy > 0")
    return a.select(F.explode("ops").alias("op"), "peak_kept").groupBy("op").agg(F.count(F.lit(1)).alias("copies"), F.count_if("peak_kept").alias("peak_kept"))


# ---- encoder
def encoder_embed(s, d):
    return E.embed_pooled(C.document_segments(C.table(s, d, "documents")), E.init(E.SMALL), E.SMALL).select("recording_id", "vec")


def kernel_crest(s, d):
    """The given vectors as kernels, their label as branch."""
    emb = C.table(s, d, "embeddings").select(F.col("label").cast("long").alias("branch"), F.col("vec_id").cast("long").alias("kernel"), F.col("embedding").cast("array<double>").alias("w"))
    k = E.inspect_vectors(emb, E.EncoderSpec().rate)
    return k.groupBy("branch").agg(F.median("crest").alias("median_crest"), F.max_by("peak_hz", "crest").alias("peak_hz"), F.max_by("cycles", "crest").alias("cycles"), F.sum("lines").alias("lines"))


def encoder_params(s, d):
    """Parameters of the network and of a head with one prototype for each customer with orders."""
    spec = E.EncoderSpec()
    return C.table(s, d, "orders").agg(F.count_distinct("o_custkey").alias("hulls")).select("hulls", F.lit(E.count_params(spec)).cast("long").alias("params"), (F.col("hulls") * spec.widths[-1]).alias("head"))


def encoder_train(s, d):
    """Margin-loss training on the hulls of all suppliers: the classes of the head, which the driver holds anyway."""
    seg = _segments(s, d)
    hulls = s.createDataFrame([(int(r[0]), k) for k, r in enumerate(C.table(s, d, "supplier").select("s_suppkey").distinct().orderBy("s_suppkey").collect())], "hull_id long, cls long")
    t = seg.join(F.broadcast(hulls), "hull_id").select(F.xxhash64("recording_id", "start").alias("tensor_id"), "cls", "x")
    _, history = E.train(s, t, E.SMALL, [1e-3, 1e-3]) if not hulls.isEmpty() else ({}, [])
    return s.createDataFrame([(a, float(b)) for a, b in history], "step long, loss double")


# ---- galleries
def _passages(s, d, copies=False):
    rec = D.histogram_residual(C.supplier_years(C.table(s, d, "lineitem"), copies), WIDTH, BINS)
    return rec.select(F.col("rid").alias("passage_id"), F.col("hull").alias("hull_id"), F.lit("").alias("source"), F.col("res").alias("vec"))


def supplier_reid(s, d):
    r = B.ranks(settled(_passages(s, d)), k=0).select(F.lit("blocked").alias("method"), "query_id", "q_hull", "best", "rank", "candidates")
    return M.rank_measures(r)


def split_half(s, d):
    """Both halves of one series, which the protocol forbids: a hull's only other passage is its own recording."""
    rec = C.supplier_years(C.table(s, d, "lineitem"), copies=False)
    n = F.expr("size(x) div 2")
    half = rec.where("size(x) >= 2").select("rid", F.col("rid").alias("hull"), F.explode(F.array(F.struct(F.lit(0).alias("h"), F.slice("x", F.lit(1), n).alias("x")), F.struct(F.lit(1).alias("h"), F.slice("x", n + 1, F.size("x") - n).alias("x")))).alias("p"))
    half = D.histogram_residual(half.select((F.col("rid") * 2 + F.col("p.h")).alias("rid"), "hull", F.col("p.x").alias("x")), WIDTH, BINS)
    p = half.select(F.col("rid").alias("passage_id"), F.col("hull").alias("hull_id"), F.col("res").alias("vec"))
    return M.rank_measures(B.ranks(settled(p), k=0).select(F.lit("halves").alias("method"), "query_id", "q_hull", "best", "rank", "candidates"))


def collapsed_gallery(s, d):
    """First passages query a gallery of one mean per hull made of the others."""
    p = settled(C.planted(C.table(s, d, "embeddings")))
    g = P.collapse(p.where("passage_no > 0")).select(F.col("hull_id").alias("g_hull"), F.col("vec").alias("gv"))
    q = p.where("passage_no = 0").select(F.col("passage_id").alias("query_id"), F.col("hull_id").alias("q_hull"), F.col("vec").alias("qv"))
    sc = q.crossJoin(g).select(F.lit("collapsed").alias("method"), "query_id", F.col("g_hull").alias("gallery_id"), "q_hull", "g_hull", F.round(dot("qv", "gv"), 9).alias("sim"))
    return M.rank_measures(P.true_rank(sc))


def boot_medr(s, d):
    r = settled(R._ranks(s, d).select("method", "query_id", "q_hull", "rank"))
    w = M.draws(r.select(F.col("q_hull").alias("hull")).distinct(), 200)
    by = r.join(w, r["q_hull"] == w["hull"]).groupBy("method", "r").agg(F.percentile("rank", F.lit(0.5), F.col("w")).alias("medr"))
    return by.groupBy("method").agg(F.round(F.percentile("medr", F.lit(0.025)), 6).alias("lo"), F.round(F.percentile("medr", F.lit(0.975)), 6).alias("hi"))


def xnet_scores(s, d):
    """Two query sets of a harder network, by the base vectors and by vectors without the enrolled hulls' mean within-hull difference."""
    p = settled(C.planted(C.table(s, d, "embeddings"), lam=3.0))
    first = p.where("passage_no = 0 and hull_id % 2 = 0").select("hull_id", F.col("vec").alias("f"))
    diff = p.where("passage_no > 0").join(first, "hull_id").select(F.posexplode(add("vec", "f", -1.0))).groupBy("pos").agg(F.avg("col").alias("m"))
    axis = diff.agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "m"))), lambda x: x["m"]).alias("u")).select(unit(F.col("u")).alias("u"))
    flat = F.zip_with("vec", "u", lambda a, b: a - b * F.col("along"))
    tuned = p.crossJoin(F.broadcast(axis)).withColumn("along", dot("vec", "u")).withColumn("vec", unit(flat)).drop("u", "along")
    sc = settled(P.leave_one_out(p, method="base").unionByName(P.leave_one_out(settled(tuned), method="tuned")))
    return sc


def xnet_metrics(s, d):
    sc = xnet_scores(s, d)
    both = sc.withColumn("method", F.concat_ws(" ", "method", F.lit("full"))).unionByName(sc.where("q_hull % 2 = 1").withColumn("method", F.concat_ws(" ", "method", F.lit("held-out"))))
    return M.evaluate(both, P.true_rank(both))


def score_drift(s, d):
    """Scores regenerated in single precision against the stored ones."""
    a = R._planted_scores(s, d)
    b = a.select("query_id", "gallery_id", F.col("sim").cast("float").cast("double").alias("again"))
    return a.join(b, ["query_id", "gallery_id"], "full_outer").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.coalesce(F.abs(F.col("sim") - F.col("again")) > 1e-4, F.lit(True))).alias("beyond"))


def checkpoint_epochs(s, d):
    """Epochs of a log of steps (orders by two months) that are kept: every third up to the ninth, then all; with their steps."""
    return Y.steps_log(s, d).where("epoch <= 9 and epoch % 3 = 0 or epoch > 9").groupBy("epoch").agg(F.count(F.lit(1)).alias("steps"))


def benchmark_leak(s, d):
    """Benchmark passages of which a thirteen-word run stands in a document."""
    words = lambda c: F.filter(F.split(F.lower(c), "[^a-z0-9]+"), lambda w: w != "")
    runs = lambda t, i: C.table(s, d, t).select(i, words(F.coalesce("text", F.lit(""))).alias("w")).where("size(w) >= 13").select(i, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 12), lambda k: F.array_join(F.slice("w", k, 13), " ")))).alias("g"))
    return runs("documents", "doc_id").join(runs("benchmark", "item_id"), "g").groupBy("item_id").agg(F.count_distinct("doc_id").alias("documents"))


_RUNS = "select {i}, w[k:k + 12] g from (select {i}, w, unnest(range(1, len(w) - 11)) k from (select {i}, list_filter(regexp_split_to_array(lower(text), '[^a-z0-9]+'), lambda x: x <> '') w from {t}) where len(w) >= 13)"
TABLE = {
    "dedup_nominate_counts": (nominate_counts, f"with {PREP}, {PAIRS} select reason, count(*) pairs, count(distinct a) recordings from prs group by reason"),
    "dedup_adjudicate": (lambda s, d: _verdict(_evidence(s, d)).select("a", "b", "reason", "t", "w", "verdict"), f"with {EV} select a, b, reason, t, w, {JOINT} verdict from ev"),
    "dedup_null_quantiles": (null_quantiles, f"with {PREP}, {NULLS} select * from bars"),
    "dedup_gate_verdicts": (gate_verdicts, f"with {EV}, {NULLS}, kn as (select * from ev where a = -b), ru as (select * from (values ('joint', 0.40::double, 0.20::double, 0.15::double), ('cut10', 0.10, null, null), ('cut37', 0.37, null, null), ('short', 0.60, null, null)) v(rule, alone, two, wave)) select rule, count(*) known, count(*) filter (where w >= 0.8 or t >= alone or coalesce(t >= two and w >= wave, false)) recalled, max(texture_bar) texture_bar, max(wave_bar) wave_bar, known = recalled and alone > max(texture_bar) and 0.8 >= max(wave_bar) approved from kn, ru, bars group by rule, alone"),
    "dedup_map": (lambda s, d: _moved(s, d)[1], f"{TRANSITS} select rid, hull, transit_id from mv"),
    "dedup_representatives": (lambda s, d: D.representatives(*_moved(s, d)).select("transit_id", "rid", "recordings"), f"{TRANSITS} select transit_id, arg_min(mv.rid, (-len(x), mv.rid)) rid, count(*) recordings from mv join rec on mv.rid = rec.rid group by transit_id"),
    "dedup_audit": (audit, f"{TRANSITS} select sum(r)::bigint recordings, sum(t)::bigint transits, sum(r - t)::bigint redundant, count(*) filter (where r > 1 and t = 1) illusory_hulls from (select hull, count(*) r, count(distinct transit_id) t from mv group by hull)"),
    "dedup_cross_hull": (cross_hull, f"with {EV} select {JOINT} verdict, count(*) pairs from ev where reason <> 'same hull' group by 1"),
    "dedup_merge_quality": (merge_quality, f"with {EV} select count(*) filter (where same and audio) in_both, count(*) filter (where same and not audio) metadata_only, count(*) filter (where not same and audio) audio_only from (select x.key = y.key same, {JOINT} <> 'distinct' audio from ev join pre x on x.rid = a join pre y on y.rid = b where reason = 'same hull')"),
    "dedup_fft_evidence": (fft_evidence, None),
    "aug_roll": _aug(lambda x, n: A.roll(x, 5), "list_transform(range(1, len(x) + 1), lambda i: x[(((i - 6) % len(x)) + len(x)) % len(x) + 1])"),
    "aug_mask": _aug(lambda x, n: A.mask_with_ambient(x, n, 3, 4), "list_transform(range(1, len(x) + 1), lambda i: case when i between 4 and 7 then nz[i] else x[i] end)"),
    "aug_mix": _aug(lambda x, n: A.mix_ambient(x, n, 10.0), "list_transform(range(1, len(x) + 1), lambda i: x[i] + nz[i] * coalesce(sqrt(list_dot_product(x, x) / nullif(list_dot_product(nz, nz), 0) / 10), 0))"),
    "aug_multipath": _aug(lambda x, n: A.multipath(x, [(2, -0.3), (5, 0.2)]), "list_transform(range(1, len(x) + 1), lambda i: x[i] + case when i > 2 then -0.3 * x[i - 2] else 0 end + case when i > 5 then 0.2 * x[i - 5] else 0 end)"),
    "aug_gain_inert": (gain_inert, f"with {SEG} select rid, 0.0::double mark from sg"),
    "aug_peak_check": (peak_check, None),
    "encoder_embed": (encoder_embed, None),
    "kernel_crest": (kernel_crest, None),
    "encoder_params": (encoder_params, "with st as (select * from (values (1, 64), (64, 128), (128, 256), (256, 512), (512, 512)) v(i, o)) select (64 * (127 + 511 + 2047 + 8191) + 4 * 3 * 64 + 64 * 4 + 4 + 4 * (4 * 64 + 64) + sum(9 * i * o + 3 * o))::bigint params, any_value(n) hulls, (512 * any_value(n))::bigint head from st, (select count(distinct o_custkey) n from orders)"),
    "encoder_train": (encoder_train, None),
    "supplier_reid": (supplier_reid, f"with {REC}, {HIST.format(of='r0')}, pa as (select rid passage_id, hull hull_id, '' as source, res vec from h2), {R._scores('s', 'pa', 'blocked')}, {R.RANKS} select method, {R.RANK_COLS} from r group by method"),
    "split_half": (split_half, f"with {REC}, hf as (select rid * 2 rid, rid hull, x[1:len(x) // 2] x from r0 where len(x) >= 2 union all select rid * 2 + 1, rid, x[len(x) // 2 + 1:] from r0 where len(x) >= 2), {HIST.format(of='hf')}, pa as (select rid passage_id, hull hull_id, '' as source, res vec from h2), {R._scores('s', 'pa', 'halves')}, {R.RANKS} select method, {R.RANK_COLS} from r group by method"),
    "collapsed_gallery": (collapsed_gallery, f"with {R.BASE}, {R._planted('pa')}, mn as (select hull_id, k, avg(e) m from (select hull_id, unnest(vec) e, generate_subscripts(vec, 1) k from pa where passage_no > 0) group by all), gv as (select hull_id, list(m order by k) v from mn group by hull_id), s as (select 'collapsed' as method, passage_id query_id, p.hull_id q_hull, g.hull_id g_hull, round(list_dot_product(vec, v) / sqrt(list_dot_product(v, v)), 9) sim from pa p, gv g where passage_no = 0), {R.RANKS} select method, {R.RANK_COLS} from r group by method"),
    "boot_medr_ci": (boot_medr, f"with {R.THREE}, {R.WINS}, {R.DRAWS}, md as (select method, dr.r, quantile_cont(rank, 0.5) medr from (select r.method, r.q_hull, r.rank from r) q join dr on dr.hull = q.q_hull, unnest(range(dr.w)) group by all) select method, round(quantile_cont(medr, 0.025), 6) lo, round(quantile_cont(medr, 0.975), 6) hi from md group by method"),
    "xnet_metrics": (xnet_metrics, f"with {R.BASE}, {R._planted('p0', lam=3.0)}, fi as (select hull_id, vec f from p0 where passage_no = 0 and hull_id % 2 = 0), dm as (select k, avg(e) m from (select vec[k] - f[k] e, k from p0 join fi using (hull_id), (select unnest(range(1, 65)) k) where passage_no > 0) group by k), ax as (select list(m order by k) v from dm), u as (select list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) u from ax), t0 as (select passage_id, hull_id, source, list_transform(range(1, 65), lambda i: vec[i] - u[i] * list_dot_product(vec, u)) v from p0, u), t1 as (select passage_id, hull_id, source, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) vec from t0), {R._scores('sb', 'p0', 'base')}, {R._scores('st', 't1', 'tuned')}, sc as (select * from sb union all select * from st), s as (select * replace (method || ' full' as method) from sc union all select * replace (method || ' held-out' as method) from sc where q_hull % 2 = 1), {R.RANKS}, {R.POINTS} {R.ROW}"),
    "score_drift": (score_drift, f"with {R.SINGLE} select count(*) pairs, count(*) filter (where abs(sim - sim::float) > 1e-4) beyond from s"),
    "checkpoint_epochs": (checkpoint_epochs, f"with {Y.LOG} select epoch, count(*) steps from lg where epoch <= 9 and epoch % 3 = 0 or epoch > 9 group by 1"),
    "benchmark_leak": (benchmark_leak, f"with a as ({_RUNS.format(i='doc_id', t='documents')}), b as ({_RUNS.format(i='item_id', t='benchmark')}) select item_id, count(distinct doc_id) documents from a join b using (g) group by item_id"),
}
