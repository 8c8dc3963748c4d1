"""Approximate nearest neighbours on robust-pruned directed graphs, one for each shard.

Equal vectors are one point of the index (with the few smallest ids that can ever be returned for it), so a very common
vector is one point however often it occurs. Points are dealt to shards of bounded size by a hash; each shard builds its
graph alone: points enter in batches, a greedy beam search from the medoid proposes neighbours for each, and pruning
keeps a candidate only if no kept neighbour is closer to it by the factor alpha, so that edges stay diverse; back edges
are pruned in the same way. A beam search takes a block of queries through every shard's graph at once; the shards' answers
are merged and scores computed in double precision on the original vectors.

Vectors that are null, zero or hold a null or non-finite component take no part, as points or queries. Vectors of different lengths
have no cosine: each length has shards of its own, and a query searches those of its length. Magnitudes do not matter. With fewer
candidates than k all are returned. Ties go to the smaller id. Rows that repeat an id are one candidate. An empty table gives
an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import materialise

SHARD, DEGREE, BEAM, ALPHA = 4096, 32, 64, 1.2


class Graph:
    """A robust-pruned graph over unit vectors (float32), built in batches. Nearness: dot product."""

    def __init__(self, x, degree: int = DEGREE, beam: int = BEAM, alpha: float = ALPHA, batch: int = 512):
        import numpy as np

        self.x, self.degree = x, degree
        n = len(x)
        self.edges = np.full((n, degree), -1, dtype=np.int32)
        self.start = int(np.argmax(x @ x.mean(0))) if n else 0
        order = np.random.default_rng(7).permutation(n)
        order = np.concatenate([[self.start], order[order != self.start]]) if n else order
        at, size = 1, 16
        while at < n:
            new = order[at : at + size]
            ids, sims = self.search(x[new], beam)
            # points that enter together may be neighbours of each other
            among = x[new] @ x[new].T
            np.fill_diagonal(among, -np.inf)
            ids = np.concatenate([ids, np.broadcast_to(new, (len(new), len(new)))], 1)
            sims = np.concatenate([sims, among], 1)
            sims[ids == new[:, None]] = -np.inf
            self.edges[new] = self._prune(ids, sims, beam, alpha)
            self._back(new, alpha)
            at, size = at + size, min(batch, 2 * size)

    def _prune(self, ids, sims, most: int, alpha: float):
        """Rows of at most `degree` diverse neighbours out of candidate rows."""
        import numpy as np

        most = min(most + self.degree, ids.shape[1])
        top = np.argpartition(-sims, most - 1, axis=1)[:, :most] if most < ids.shape[1] else np.broadcast_to(np.arange(most), ids.shape[:1] + (most,))
        ids, sims = np.take_along_axis(ids, top, 1), np.take_along_axis(sims, top, 1)
        by = np.argsort(-sims, axis=1, kind="stable")
        ids, sims = np.take_along_axis(ids, by, 1), np.take_along_axis(sims, by, 1)
        sims = np.where(ids < 0, -np.inf, sims)
        dist = np.sqrt(np.maximum(2 - 2 * sims, 0))
        out = np.full((len(ids), self.degree), -1, dtype=np.int32)
        free, filled = np.isfinite(sims), np.zeros(len(ids), dtype=np.int64)
        rows = np.arange(len(ids))
        v = self.x[np.maximum(ids, 0)]
        for _ in range(self.degree):
            first = np.argmax(free, axis=1)
            ok = free[rows, first]
            if not ok.any():
                break
            out[rows[ok], filled[ok]] = ids[rows[ok], first[ok]]
            filled[ok] += 1
            free[rows, first] = False
            between = np.sqrt(np.maximum(2 - 2 * np.einsum("rcd,rd->rc", v, v[rows, first]), 0))
            free &= ~((alpha * between <= dist) & ok[:, None])
        return out

    def _back(self, new, alpha: float):
        """Edges back to the new points; a full row is pruned anew."""
        import numpy as np

        heads = self.edges[new]
        src = np.repeat(new, self.degree)[heads.ravel() >= 0]
        dst = heads.ravel()[heads.ravel() >= 0]
        by = np.argsort(dst, kind="stable")
        src, dst = src[by], dst[by]
        who, first, count = np.unique(dst, return_index=True, return_counts=True)
        wide = np.full((len(who), self.degree + int(count.max(initial=0))), -1, dtype=np.int32)
        wide[:, : self.degree] = self.edges[who]
        wide[np.repeat(np.arange(len(who)), count), self.degree + np.arange(len(dst)) - np.repeat(first, count)] = src
        # an edge that is there already counts once
        wide.sort(axis=1)
        wide[:, 1:][wide[:, 1:] == wide[:, :-1]] = -1
        used = (wide >= 0).sum(1)
        few = used <= self.degree
        kept = -np.sort(-wide, axis=1)[:, : self.degree]
        self.edges[who[few]] = kept[few]
        if (~few).any():
            ids = wide[~few]
            sims = np.where(ids < 0, -np.inf, np.einsum("rcd,rd->rc", self.x[np.maximum(ids, 0)], self.x[who[~few]]))
            self.edges[who[~few]] = self._prune(ids, sims, ids.shape[1], alpha)

    def search(self, q, beam: int = BEAM, block: int = 512):
        """(ids, nearness) of the `beam` best points found for each row of q, best first; -1 where there are fewer."""
        import numpy as np

        out_i, out_s = [], []
        n = len(self.x)
        for at in range(0, len(q), block):
            part = q[at : at + block]
            m = len(part)
            rows = np.arange(m)[:, None]
            ids = np.full((m, beam), -1, dtype=np.int32)
            sims = np.full((m, beam), -np.inf, dtype=np.float32)
            done = np.zeros((m, beam), dtype=bool)
            seen = np.zeros((m, n + 1), dtype=bool)  # the last column stands for "no point"
            seen[:, n] = True
            ids[:, 0], sims[:, 0] = self.start, part @ self.x[self.start]
            seen[:, self.start] = True
            while True:
                open_ = np.where(done | (ids < 0), -np.inf, sims)
                best = np.argmax(open_, axis=1)
                live = np.flatnonzero(np.isfinite(open_[np.arange(m), best]))
                if not len(live):
                    break
                done[live, best[live]] = True
                near = self.edges[ids[live, best[live]]]
                near = np.where(near < 0, n, near)
                fresh = ~seen[live[:, None], near]
                seen[live[:, None], near] = True
                near = np.where(fresh, near, -1)
                s = np.einsum("rcd,rd->rc", self.x[np.maximum(near, 0)], part[live])
                s[near < 0] = -np.inf
                all_i, all_s = np.concatenate([ids[live], near], 1), np.concatenate([sims[live], s], 1)
                all_d = np.concatenate([done[live], np.zeros(near.shape, bool)], 1)
                top = np.argpartition(-all_s, beam - 1, axis=1)[:, :beam]
                ids[live], sims[live], done[live] = (np.take_along_axis(a, top, 1) for a in (all_i, all_s, all_d))
            by = np.argsort(-sims, axis=1, kind="stable")
            out_i.append(ids[rows, by])
            out_s.append(sims[rows, by])
        if not out_i:
            return np.zeros((0, beam), np.int32), np.zeros((0, beam), np.float32)
        return np.concatenate(out_i), np.concatenate(out_s)


def scaled(rows):
    """Rows as doubles, each times the power of two that brings its largest component to 1/2 .. 1: nothing is rounded, no norm overflows."""
    import numpy as np

    x = np.array(rows, dtype=np.float64)
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1))[1][:, None])


def _unit(x):
    import numpy as np

    return (x / np.linalg.norm(x, axis=1, keepdims=True)).astype(np.float32)


def usable(vectors: DataFrame, id_col: str, vec_col: str) -> DataFrame:
    """id and vector (doubles) of the rows that take part."""
    v = F.col("v")
    ok = v.isNotNull() & (F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col(id_col).alias("id"), F.col(vec_col).cast("array<double>").alias("v")).where("id is not null").where(F.coalesce(ok, F.lit(False)))


def build(points: DataFrame, k: int, shard: int = SHARD) -> DataFrame:
    """The index: one row a shard and part of it (edges and vectors as arrays, ids of each point). points: id and v."""
    key = F.xxhash64("v")
    # the k + 1 smallest ids of a vector are all that can be returned for it (one of them may be the query)
    few = points.withColumn("h", key).dropDuplicates(["id", "v"]).withColumn("n", F.row_number().over(W.partitionBy("h", "v").orderBy("id"))).where(F.col("n") <= k + 1)
    one = few.groupBy("h", "v").agg(F.array_sort(F.collect_list("id")).alias("ids"))
    one = materialise(one)
    shards = max(1, -(-one.count() // shard))
    dealt = one.withColumn("shard", F.pmod(F.xxhash64("h", F.lit(5)), F.lit(shards)).cast("int")).withColumn("size", F.size("v"))

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values("h").reset_index(drop=True)
        g = Graph(_unit(scaled(list(pdf["v"]))))
        return pd.DataFrame({"shard": pdf["shard"], "size": pdf["size"], "point": range(len(pdf)), "start": g.start, "v": pdf["v"], "ids": pdf["ids"], "edges": list(g.edges)})

    schema = f"shard int, size int, point int, start int, v array<double>, ids array<{dict(points.dtypes)['id']}>, edges array<int>"
    return materialise(dealt.groupBy("shard", "size").applyInPandas(run, schema))


def search(index: DataFrame, queries: DataFrame, k: int = 5, beam: int = BEAM, block: int = 20_000) -> DataFrame:
    """query_id, rank, vec_id and score of the k nearest found for each query (id and v)."""
    id_type = dict(queries.dtypes)["id"]
    blocks = max(1, -(-queries.count() // block))
    shards = index.select(F.col("shard").alias("_shard"), F.col("size").alias("_size")).distinct().select((F.col("_shard") + 0).alias("shard"), (F.col("_size") + 0).alias("size"))
    # every block of queries meets every shard: that is the operator (a stated query set against all rows, in blocks)
    dealt = queries.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    dealt = dealt.withColumn("size", F.size("v")).join(shards, "size")
    held = index.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def run(pts, qs):
        import numpy as np
        import pandas as pd

        out = {c: [] for c in ("query_id", "vec_id", "score")}
        if len(pts) and len(qs):
            pts = pts.sort_values("point").reset_index(drop=True)
            g = Graph.__new__(Graph)
            vecs = scaled(list(pts["v"]))
            g.x, g.edges, g.start, g.degree = _unit(vecs), np.array(list(pts["edges"]), dtype=np.int32), int(pts["start"][0]), 0
            raw = scaled(list(qs["v"]))
            found, _ = g.search(_unit(raw), beam)
            norms = np.sqrt((vecs * vecs).sum(1))
            for q, v, row in zip(qs["id"], raw, found, strict=True):
                row = row[row >= 0]
                score = (vecs[row] @ v) / (norms[row] * np.sqrt(v @ v))
                n = 0
                for p in np.argsort(-score, kind="stable"):
                    if n >= k and score[p] < edge:
                        break
                    for i in pts["ids"][row[p]]:
                        if i != q:
                            out["query_id"].append(q)
                            out["vec_id"].append(i)
                            out["score"].append(float(score[p]))
                            n += 1
                    edge = score[p]
        return pd.DataFrame(out)

    schema = f"query_id {id_type}, vec_id {id_type}, score double"
    got = held.groupBy("shard", "size", "block").cogroup(dealt.groupBy("shard", "size", "block")).applyInPandas(run, schema).dropDuplicates(["query_id", "vec_id"])
    return got.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id"))).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    points = usable(table(spark, sf_dir, "embeddings"), "vec_id", "embedding")
    return search(build(points, 5), points.where("id % 50 = 0"), 5)
