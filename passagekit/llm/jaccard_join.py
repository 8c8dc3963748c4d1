"""N-gram Jaccard join: an exact metric-space self-join of shingle sets.

Jaccard distance is a metric. Equal sets are one point. Points that can link at all share a shingle among the first few
of a common order (the length of that prefix follows from the threshold); the points with a given shingle in their prefix
form a patch, and the patch's point with the smallest key is its pivot. Patches are told apart
by size, as sets of very different size cannot link. All patches with one pivot make up its region, so every link lies inside
some region: that of the pivot of a shared shingle. One-bit sketches (they differ in no more bits than the sets in shingles) drop what cannot
link inside a small region.

A wide region is cut by the executors together: a few of its points are pivots, every point goes to the Voronoi cell of the nearest one, and
where it stands within twice the threshold of another pivot's claim, a copy goes to that cell too (two points that link and lie in different cells
meet in the earlier one, by the triangle inequality). Points within the threshold of their pivot are linked to it and leave; of those that
remain only the ones within twice the threshold of the pivot are held against them, in blocks; the remaining points and copies of a cell are
a region of their own, until regions are small or no longer shrink.

A region that fits one task is joined recursively and exactly: distances to a pivot are computed, what lies within the threshold is linked to it
and forms one class, the triangle inequality leaves to be compared with that class only the boundary (distance at most twice the threshold) and, of
the class, the window whose pivot distance differs by at most the threshold; the rest goes on with a new pivot. Regions of more than `weight`
shingles are cut into blocks, and each pair of blocks, with the pivot replicated into it, is one task's bounded job.

Any common order is exact; ours puts shingles of many documents last, so that a passage shared by very many documents does not
make a region. They are found by counts within each task that are summed (at most `most_common` of them).

Null and empty texts have no set and link with nothing (their class is their own id). Fewer words than a shingle make one
shingle of the whole. Rows with the same id and text count once as a set and each appear in the result. An empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import discard, materialise, slices

WORDS, PERCENT, WEIGHT, MOST_COMMON = 4, 85, 2_000_000, 1 << 21
#: Points from which a region is wide, pivots of a wide region, points of one task's share of it, rounds at most.
SMALL, PIVOTS, SHARE, ROUNDS = 800, 4, 200, 6


#: Two odd factors of the hashes, bytes of a word hashed in steps of eight (longer ones by xxhash), bytes of text hashed at once.
_MIX, _FOLD, LONG, AT_ONCE = 0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 64, 1 << 20


def _mixed(h):
    """A one-to-one map of 64-bit numbers in which every bit depends on all."""
    import numpy as np

    h = h ^ (h >> np.uint64(32))
    h *= np.uint64(_MIX)
    h ^= h >> np.uint64(29)
    h *= np.uint64(_FOLD)
    h ^= h >> np.uint64(32)
    return h


def word_hashes(texts):
    """64-bit hashes of all words of an Arrow column of texts (A-Z lower-cased), and each text's first place among them, ended by their number.

    Words are found and hashed over the bytes of all texts at once, eight bytes of every word in a step; a word's hash depends on its bytes alone.
    """
    import numpy as np
    import pyarrow as pa
    import xxhash

    if texts.null_count:
        texts = texts.fill_null("")
    _, offsets, data = texts.buffers()
    at = np.frombuffer(offsets, np.int64 if pa.types.is_large_string(texts.type) else np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64) if len(texts) else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8)[at[0] : at[-1]] if data and at[-1] > at[0] else np.zeros(0, np.uint8)
    at -= at[0]
    size = len(raw)
    low, gap = np.arange(256, dtype=np.uint8), np.zeros(256, bool)
    low[65:91] += 32
    gap[[32, *range(9, 14)]] = True
    chars = np.zeros(size + 8, np.uint8)  # eight bytes can be read at every place
    chars[:size] = low[raw]
    apart = np.ones(size + 2, bool)
    apart[1:-1] = gap[raw]
    begins, ends = apart[:-2] & ~apart[1:-1], ~apart[1:-1] & apart[2:]
    edge = at[(at > 0) & (at < size)]  # no word goes from one text into the next
    begins[edge] |= ~apart[edge + 1]
    ends[edge - 1] |= ~apart[edge]
    first, last = np.flatnonzero(begins), np.flatnonzero(ends) + 1
    n = last - first
    eight = np.ndarray(size + 1, "<u8", chars, 0, (1,))
    keep = np.array([(1 << 8 * i) - 1 for i in range(9)], np.uint64)
    h = _mixed((eight[first] & keep[np.minimum(n, 8)]) ^ (n.astype(np.uint64) * np.uint64(_MIX)))
    more, step = np.flatnonzero((n > 8) & (n <= LONG)), 8
    while len(more):
        h[more] = _mixed(h[more] ^ (eight[first[more] + step] & keep[np.minimum(n[more] - step, 8)]))
        step += 8
        more = more[n[more] > step]
    for i in np.flatnonzero(n > LONG):
        h[i] = xxhash.xxh3_64_intdigest(chars[first[i] : last[i]])
    return h, np.searchsorted(first, at)


def _chained(h, k: int, seed: int = 0):
    """Hashes of all runs of k word hashes."""
    import numpy as np

    out = np.full(max(len(h) - k + 1, 0), seed, np.uint64)
    for i in range(k):
        out ^= h[i : i + len(out)]
        out *= np.uint64(_MIX)
        out ^= out >> np.uint64(31)
    out *= np.uint64(_FOLD)
    out ^= out >> np.uint64(32)
    return out


def shingle_sets(texts, k: int = WORDS):
    """For each text of an Arrow column its sorted distinct 64-bit hashes of the k-word shingles, about AT_ONCE bytes of text at a time."""
    import numpy as np
    import pyarrow.compute as pc

    size = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    at = 0
    while at < len(texts):
        end = max(at + 1, int(np.searchsorted(size, AT_ONCE + (size[at - 1] if at else 0), side="right")))
        h, cut = word_hashes(texts.slice(at, end - at))
        every, at = _chained(h, k), end
        for a, b in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            if 0 < b - a < k:  # the whole text is one shingle, told from runs of k words by its length
                yield _chained(h[a:b], b - a, b - a)
                continue
            out = every[a : max(b - k + 1, a)]
            out.sort()
            new = np.ones(len(out), bool)
            np.not_equal(out[1:], out[:-1], out=new[1:])
            yield out[new]


def digest(shingles) -> int:
    import xxhash

    h = xxhash.xxh3_64_intdigest(shingles.tobytes())
    return h - (1 << 64) if h >> 63 else h


def sketch(shingles) -> bytes:
    """One bit for each residue that occurs, about as many bits as shingles (a power of two)."""
    import numpy as np

    size = 1 << max(6, int(len(shingles) - 1).bit_length())
    bits = np.zeros(size, dtype=bool)
    bits[((shingles >> np.uint64(20)) & np.uint64(size - 1)).astype(np.int64)] = True
    return np.packbits(bits).tobytes()


def may_link(sizes, sketches: list[bytes], percent: int):
    """Which sets of a small region may link with another one of it.

    Sketches differ in at most as many bits as the sets do in shingles, so a pair whose sketches differ in more bits than
    linked sets of their sizes can is out.
    """
    import numpy as np

    least = min(map(len, sketches))
    rows = np.empty((len(sketches), least), np.uint8)
    for k, b in enumerate(sketches):
        x = np.frombuffer(b, np.uint8)
        while len(x) > least:
            x = x[: len(x) // 2] | x[len(x) // 2 :]
        rows[k] = x
    rows, n, ok = rows.view(np.uint64), np.asarray(sizes), np.zeros(len(sketches), bool)
    for k in range(len(rows) - 1):
        a, b = n[k], n[k + 1 :]
        differ = np.bitwise_count(rows[k] ^ rows[k + 1 :]).sum(1, dtype=np.int64)
        good = (100 * np.minimum(a, b) >= percent * np.maximum(a, b)) & (differ * (100 + percent) <= (100 - percent) * (a + b))
        ok[k + 1 :] |= good
        ok[k] |= good.any()
    return ok


def prefix_length(n: int, percent: int) -> int:
    return n - (percent * n + 99) // 100 + 1


def linked(common: int, a: int, b: int, percent: int) -> bool:
    return 100 * common >= percent * (a + b - common)


def sets(docs: DataFrame, id_col: str, text_col: str, k: int = WORDS) -> DataFrame:
    """id, n (size of its set), d (digest of it; null for no set) and its sketch."""

    def run(it):
        import pyarrow as pa

        for batch in slices(it):
            own = list(shingle_sets(batch.column(1), k))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(s) for s in own], pa.int64()), pa.array([digest(s) if len(s) else None for s in own], pa.int64()), pa.array([sketch(s) if len(s) else None for s in own], pa.binary())], names=["id", "n", "d", "bits"])

    return docs.select(F.col(id_col).alias("id"), F.col(text_col)).mapInArrow(run, f"id {dict(docs.dtypes)[id_col]}, n long, d long, bits binary")


def _per_set(docs: DataFrame, text_col: str, k: int, schema: str, start, each, end=None) -> DataFrame:
    """mapInArrow over the distinct sets of each task: each(state, shingles, digest) gives column arrays or nothing."""
    names = [f.split()[0] for f in schema.split(", ")]

    def run(it):
        import numpy as np
        import pyarrow as pa

        seen, state = set(), start()
        for batch in slices(it):
            out = []
            for s in shingle_sets(batch.column(0), k):
                if len(s) and (d := digest(s)) not in seen:
                    if len(seen) > 2_000_000:
                        seen.clear()
                    seen.add(d)
                    got = each(state, s, d)
                    if got is not None:
                        out.append(got)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) if isinstance(c[0], np.ndarray) else pa.array([x for y in c for x in y]) for c in zip(*out, strict=True)], names=names)
        if end:
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in end(state)], names=names)

    return docs.select(F.col(text_col)).mapInArrow(run, schema)


def common_shingles(docs: DataFrame, text_col: str, k: int, most: int = MOST_COMMON, local: int = 4, least: int = 24):
    """Hashes of the most common shingles, as a sorted array of at most `most`.

    Counted in each task over its distinct sets; those met `local` times in a task are summed over tasks.
    """
    import numpy as np

    def each(state, s, d):
        state["new"].append(s[s < np.uint64(1 << 63)])  # prefixes hold small hashes, so the smaller half is enough
        state["n"] += len(s)
        if state["n"] > 4_000_000:
            fold(state)

    def fold(state):
        u, c = np.unique(np.concatenate(state["new"]), return_counts=True)
        few = c < 2  # rare within four million: not worth remembering
        state["kept"].append((u[~few], c[~few]))
        state["new"], state["n"] = [], 0

    def end(state):
        if state["new"]:
            fold(state)
        if not state["kept"]:
            return [np.zeros(0, np.int64)] * 2
        u, inv = np.unique(np.concatenate([a for a, _ in state["kept"]]), return_inverse=True)
        c = np.bincount(inv, np.concatenate([b for _, b in state["kept"]]), len(u)).astype(np.int64)
        return [u[c >= local].astype(np.int64), c[c >= local]]

    rows = _per_set(docs, text_col, k, "s long, c long", lambda: {"new": [], "n": 0, "kept": []}, each, end)
    top = rows.groupBy("s").agg(F.sum("c").alias("c")).where(F.col("c") >= least).orderBy(F.col("c").desc(), "s").limit(most)
    return np.sort(top.select("s").toArrow()["s"].to_numpy().astype(np.uint64))


def prefixes(docs: DataFrame, text_col: str, k: int, percent: int, common) -> DataFrame:
    """s, n, d: the shingles of each set's prefix."""
    import numpy as np

    sent = docs.sparkSession.sparkContext.broadcast(common)
    bits = 25

    def start():
        last = np.zeros(1 << bits, dtype=bool)
        last[(sent.value >> np.uint64(38)) & np.uint64((1 << bits) - 1)] = True
        return last

    def each(last, s, d):
        late = last[(s >> np.uint64(38)) & np.uint64((1 << bits) - 1)]
        p = np.concatenate([s[~late], s[late]])[: prefix_length(len(s), percent)].view(np.int64)
        return p, np.full(len(p), len(s), np.int64), np.full(len(p), d, np.int64)

    return _per_set(docs, text_col, k, "s long, n long, d long", start, each)


def regions(rows: DataFrame, parts: int, percent: int) -> DataFrame:
    """pivot, d, n: members of each region, pivots included. One pass over sorted patches, whatever their size.

    A patch is told apart by size: sets whose sizes allow a link are in the same band or in neighbouring ones, so a pair of
    neighbouring bands of a patch has a pivot of its own, the first set of the lower band.
    """
    width = math.log(100 / percent) * (1 + 1e-6)

    def run(it):
        import numpy as np
        import pyarrow as pa

        # the two groups (patch, band, lead and its size) that the last batch ended with
        held, told = np.zeros((2, 4), np.int64) - 1, set()
        for batch in it:
            s, band, d, n = (batch.column(i).to_numpy() for i in range(4))
            if not len(s):
                continue
            new = np.concatenate([[s[0] != held[1, 0] or band[0] != held[1, 1]], (s[1:] != s[:-1]) | (band[1:] != band[:-1])])
            at = np.flatnonzero(new)
            groups = np.concatenate([held, np.stack([s[at], band[at], d[at], n[at]], 1)])
            own = np.cumsum(new) + 1
            held = groups[-2:]
            lead, below = groups[own], groups[own - 1]
            near = (below[:, 0] == s) & (below[:, 1] == band - 1)
            pairs = np.concatenate([np.stack([lead[:, 2], d, n, lead[:, 3]], 1)[lead[:, 2] != d], np.stack([below[:, 2], d, n, below[:, 3]], 1)[near & (below[:, 2] != d)]])
            if len(pairs):
                found = np.unique(pairs, axis=0)
                fresh = [r for r in map(tuple, found.tolist()) if r not in told]
                if len(told) > 500_000:
                    told.clear()
                told.update(fresh)
                if fresh:
                    a, b, c, e = zip(*fresh, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(a + a), pa.array(b + a), pa.array(c + e)], names=["pivot", "d", "n"])

    dealt = rows.select("s", F.floor(F.ln("n") / F.lit(width)).cast("long").alias("band"), "d", "n").repartition(parts, "s").sortWithinPartitions("s", "band", "d")
    return dealt.mapInArrow(run, "pivot long, d long, n long").distinct()


def thinned(member: DataFrame, own: DataFrame, parts: int, percent: int) -> DataFrame:
    """member without the sets that cannot link with any other of their region; for regions that are not wide."""

    def run(it):
        import pyarrow as pa

        key, rows = None, []

        def out(some):
            p, d, n = ([r[i] for r in some] for i in range(3))
            return pa.RecordBatch.from_arrays([pa.array(p, pa.int64()), pa.array(d, pa.int64()), pa.array(n, pa.int64())], names=["pivot", "d", "n"])

        def flush():
            if not rows:
                return []
            return [r for r, k in zip(rows, may_link([r[2] for r in rows], [r[3] for r in rows], percent), strict=True) if k]

        for batch in it:
            kept = []
            for r in zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True):
                if r[0] != key:
                    kept += flush()
                    key, rows = r[0], []
                rows.append(r)
            if kept:
                yield out(kept)
        if kept := flush():
            yield out(kept)

    bits = own.where("d is not null").select("d", "bits").dropDuplicates(["d"])
    dealt = member.join(bits, "d").repartition(parts, "pivot").sortWithinPartitions("pivot", "d")
    return dealt.select("pivot", "d", "n", "bits").mapInArrow(run, "pivot long, d long, n long")


def voronoi(wide: DataFrame, arrays: DataFrame, percent: int, seed: int, pivots: int = PIVOTS, share: int = SHARE) -> DataFrame:
    """One round over wide regions (region, d): cell, its pivot, d, dist to that pivot, whether they link, and what it is there: core, rest or copy.

    Shares of a region are dealt over tasks with all its pivots; a set's row in its own cell comes with copies in the earlier cells
    whose pivot is at most twice the threshold farther than its own.
    """
    keyed = wide.withColumn("h", F.xxhash64("d", F.lit(seed)))
    first = keyed
    for by in (["region", F.pmod("h", F.lit(64))], ["region"]):  # within shares of a region before within the region
        first = first.withColumn("k", F.row_number().over(W.partitionBy(*by).orderBy("h", "d"))).where(F.col("k") <= pivots)
    first = materialise(first.select("region", "d").join(arrays, "d"))
    shares = keyed.groupBy("region").agg(F.count(F.lit(1)).alias("n")).select("region", F.ceil(F.col("n") / share).cast("int").alias("shares"))
    rows = keyed.join(shares, "region").withColumn("share", F.pmod("h", F.col("shares")).cast("int")).select("region", "share", "d").join(arrays, "d")
    every = first.join(shares, "region").select("region", F.explode(F.sequence(F.lit(0), F.col("shares") - 1)).alias("share"), F.lit(0).alias("kind"), "d", "x")
    dealt = every.unionByName(rows.select("region", "share", F.lit(1).alias("kind"), "d", "x"))
    parts = max(int(wide.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    eps = 1 - percent / 100

    def run(it):
        import numpy as np
        import pyarrow as pa

        kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.string())

        def flush(region, heads, xs, ds, rows):
            """The rows of one share against its pivots."""
            size = np.array([len(x) for x in rows])
            flat, start = np.concatenate(rows), np.cumsum(size) - size
            common = np.stack([np.add.reduceat(p[np.minimum(np.searchsorted(p, flat), len(p) - 1)] == flat, start, dtype=np.int64) for p in xs], 1)
            union = np.array([len(p) for p in xs]) + size[:, None] - common
            dist, hit = 1 - common / union, 100 * common >= percent * union
            out = []
            for d, t, h in zip(ds, dist.tolist(), hit.tolist(), strict=True):
                own = t.index(min(t))
                out.append((region, own, heads[own], d, t[own], h[own], "core" if h[own] else "rest"))
                # a link across cells is found in the earlier one
                out += [(region, i, heads[i], d, t[i], h[i], "copy") for i in range(own) if t[i] <= t[own] + 2 * eps + 1e-12]
            return out

        key, heads, xs = None, [], []
        for batch in slices(it):
            out, ds, rows = [], [], []
            for region, part, kind, d, x in zip(*(batch.column(c).to_pylist() for c in range(5)), strict=True):
                if (region, part) != key:
                    if ds:
                        out += flush(key[0], heads, xs, ds, rows)
                    key, heads, xs, ds, rows = (region, part), [], [], [], []
                if kind == 0:
                    heads.append(d)
                    xs.append(np.frombuffer(x, dtype=np.uint64))
                else:
                    ds.append(d)
                    rows.append(np.frombuffer(x, dtype=np.uint64))
            if ds:
                out += flush(key[0], heads, xs, ds, rows)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names=["region", "i", "pivot", "d", "dist", "hit", "what"])

    got = dealt.repartition(parts * 4, "region", "share").sortWithinPartitions("region", "share", "kind", "d").select("region", "share", "kind", "d", "x").mapInArrow(run, "region long, i int, pivot long, d long, dist double, hit boolean, what string")
    return got.withColumn("cell", F.xxhash64("region", "i", F.lit(seed))).drop("region", "i")


def cut_wide(wide: DataFrame, arrays: DataFrame, percent: int, small: int = SMALL, rounds: int = ROUNDS):
    """(links, boundary cells as pivot, i, j, d, regions that are left as region, d) of wide regions."""
    eps = 1 - percent / 100
    links, cells, left = [], [], []
    block = lambda n: F.pmod(F.xxhash64("d", F.lit(3)), F.greatest(F.lit(1), F.ceil(F.col(n) / SHARE))).cast("int")
    for seed in range(rounds):
        before = wide.count()
        if not before:
            return links, cells, left
        got = materialise(voronoi(wide, arrays, percent, seed))
        links.append(got.where("hit and d <> pivot").select(F.col("pivot").alias("a"), F.col("d").alias("b")))
        # the boundary of a cell meets the points that were linked to its pivot, block by block
        near = got.where((F.col("what") != "core") & (F.col("dist") <= 2 * eps + 1e-12)).select("cell", "pivot", "d")
        core = got.where("what = 'core' and d <> pivot").select("cell", "pivot", "d")
        sizes = near.groupBy("cell").agg(F.count(F.lit(1)).alias("nb")).join(core.groupBy("cell").agg(F.count(F.lit(1)).alias("nc")), "cell")
        a = near.join(sizes, "cell").withColumn("i", block("nb")).withColumn("j", F.explode(F.sequence(F.lit(0), F.greatest(F.lit(1), F.ceil(F.col("nc") / SHARE)).cast("int") - 1)))
        b = core.join(sizes, "cell").withColumn("j", block("nc")).withColumn("i", F.explode(F.sequence(F.lit(0), F.greatest(F.lit(1), F.ceil(F.col("nb") / SHARE)).cast("int") - 1)))
        pair = materialise(a.select("cell", "pivot", "i", "j", "d").unionByName(b.select("cell", "pivot", "i", "j", "d")))
        heads = pair.select("cell", "pivot", "i", "j").distinct().withColumn("d", F.col("pivot"))
        cells.append(pair.unionByName(heads))
        rest = got.where("what <> 'core'").select(F.col("cell").alias("region"), "d", "what").distinct()
        sizes = rest.groupBy("region").agg(F.count(F.lit(1)).alias("k"), F.count_if(F.col("what") == "rest").alias("own")).where("own > 0 and k > 1")
        rest = materialise(rest.join(sizes, "region").select("region", "d", "k"))
        left.append(rest.where(F.col("k") <= small).select("region", "d"))
        wide = rest.where(F.col("k") > small).select("region", "d")
        if wide.count() > 0.9 * before:
            break
    left.append(wide)
    return links, cells, left


class Classes:
    """Union-find over positions."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, a: int) -> int:
        while self.up[a] != a:
            self.up[a] = self.up[self.up[a]]
            a = self.up[a]
        return a

    def join(self, a: int, b: int) -> bool:
        a, b = self.find(a), self.find(b)
        self.up[max(a, b)] = min(a, b)
        return a != b


def join_region(points: list, percent: int) -> list[tuple[int, int]]:
    """Edges that connect exactly the classes of linked sets among points (sorted hash arrays; the first is the pivot)."""
    import numpy as np

    size = np.array([len(p) for p in points])
    eps = 1 - percent / 100
    found, edges = Classes(len(points)), []

    def overlap(one: int, many):
        flat = np.concatenate([points[i] for i in many])
        p = points[one]
        hit = p[np.minimum(np.searchsorted(p, flat), len(p) - 1)] == flat
        return np.add.reduceat(hit, np.concatenate([[0], np.cumsum(size[many])[:-1]]), dtype=np.int64)

    def near(one: int, many):
        """Of many, those whose size allows a link with one."""
        lo, hi = percent * size[one], 100 * size[one]
        return many[(100 * size[many] >= lo) & (percent * size[many] <= hi)]

    def link(a: int, b: int) -> None:
        if found.join(a, b):
            edges.append((a, b))

    todo = [np.arange(len(points))]
    while todo:
        part = todo.pop()
        if len(part) < 2:
            continue
        pivot, rest = int(part[0]), part[1:]
        common = overlap(pivot, rest)
        union = size[pivot] + size[rest] - common
        dist = 1 - common / union
        core = 100 * common >= percent * union
        for i in rest[core]:
            link(pivot, int(i))
        inner, inner_dist = rest[core], dist[core]
        # the boundary against its window of the class around the pivot
        edge = np.flatnonzero(~core & (dist <= 2 * eps + 1e-12))
        for e in edge if len(inner) else ():
            x = int(rest[e])
            if found.find(x) == found.find(pivot):
                continue
            window = near(x, inner[inner_dist >= dist[e] - eps - 1e-12])
            for at in range(0, len(window), 64):
                some = window[at : at + 64]
                c = overlap(x, some)
                ok = 100 * c >= percent * (size[x] + size[some] - c)
                if ok.any():
                    link(x, int(some[np.argmax(ok)]))
                    break
        todo.append(rest[~core])
    return edges


def links(docs: DataFrame, own: DataFrame, text_col: str = "text", k: int = WORDS, percent: int = PERCENT, weight: int = WEIGHT, most_common: int = MOST_COMMON, small: int = SMALL) -> DataFrame:
    """a, b (digests): links that connect exactly the classes of linked sets. own: sets(docs)."""
    import numpy as np

    spark = docs.sparkSession
    rows = materialise(prefixes(docs, text_col, k, percent, common_shingles(docs, text_col, k, most_common)))
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows.count() // 2_000_000))
    every = materialise(regions(rows, parts, percent))
    discard(rows)
    many = every.groupBy("pivot").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") > small).select("pivot")
    wide = materialise(every.join(many, "pivot", "left_semi").select("pivot", "d"))
    member = materialise(thinned(every.join(many, "pivot", "left_anti"), own, parts, percent))
    discard(every)
    # sets in some region, as one bit of a sketch each: two megabytes whatever their number
    bit = F.shiftrightunsigned(F.xxhash64("d"), 40)
    words = member.select("d").union(wide.select("d")).select(bit.alias("bit")).groupBy(F.expr("bit div 64").alias("w")).agg(F.expr("bit_or(shiftleft(1L, cast(bit % 64 as int)))").alias("b")).toArrow()
    present = np.zeros(1 << 18, dtype=np.int64)
    present[words["w"].to_numpy()] = words["b"].to_numpy()
    arrays = _arrays(docs, text_col, k, present)
    found, pieces = [], []
    if not wide.isEmpty():
        arrays = materialise(arrays)
        found, boundary, left = cut_wide(wide.withColumnRenamed("pivot", "region"), arrays, percent, small)
        sized = own.where("d is not null").select("d", "n").dropDuplicates(["d"])
        for one in left:  # a region's first set is its pivot now
            one = one.join(one.groupBy("region").agg(F.min("d").alias("pivot")), "region").join(sized, "d")
            member = member.unionByName(one.select("pivot", "d", "n")).distinct()
        pieces = [c.select("pivot", F.col("cell").alias("region"), "i", "j", "d") for c in boundary]
    sizes = member.groupBy("pivot").agg(F.sum("n").alias("w")).withColumn("blocks", F.ceil(F.col("w") / F.lit(weight)).cast("int"))
    dealt = member.join(sizes, "pivot").withColumn("own", F.pmod(F.xxhash64("d"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    # the pivot goes to every pair of blocks, any other set to the pairs that hold its block
    pairs = F.when(F.col("d") == F.col("pivot"), F.transform(F.sequence(F.lit(0), F.col("other")), lambda i: F.struct(i.alias("i"), F.col("other").alias("j")))).otherwise(F.array(F.struct(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))))
    cells = dealt.withColumn("cell", F.explode(pairs)).select("pivot", F.col("pivot").alias("region"), "cell.i", "cell.j", "d")
    for one in pieces:
        cells = cells.unionByName(one)
    full = cells.join(arrays, "d").repartition(parts, "region", "pivot", "i", "j").sortWithinPartitions("region", "pivot", "i", "j", "d")
    out = full.select("pivot", "region", "i", "j", "d", "x").mapInArrow(_joiner(percent), "a long, b long")
    for one in found:
        out = out.unionByName(one)
    return out


def _arrays(docs: DataFrame, text_col: str, k: int, present) -> DataFrame:
    """d, x: the sets (hashes as bytes) of all digests that may be present, once each."""
    sent = docs.sparkSession.sparkContext.broadcast(present)

    def each(state, s, d):
        at = xx_bit(d)
        if int(sent.value[at >> 6]) >> (at & 63) & 1:
            return [d], [s.tobytes()]
        return None

    return _per_set(docs, text_col, k, "d long, x binary", lambda: None, each).dropDuplicates(["d"])


def xx_bit(d: int) -> int:
    """The 24 leading bits of Spark's xxhash64 of one long (its public definition: seed 42)."""
    import struct

    import xxhash

    return xxhash.xxh64_intdigest(struct.pack("<q", d), seed=42) >> 40


def _joiner(percent: int):
    def run(it):
        import numpy as np
        import pyarrow as pa

        key, ids, xs = None, [], []

        def done():
            if len(ids) < 2:
                return None
            if key[0] in ids:  # the pivot first
                p = ids.index(key[0])
                ids[0], ids[p], xs[0], xs[p] = ids[p], ids[0], xs[p], xs[0]
            pairs = join_region([np.frombuffer(x, dtype=np.uint64) for x in xs], percent)
            return pa.RecordBatch.from_arrays([pa.array([ids[a] for a, _ in pairs], pa.int64()), pa.array([ids[b] for _, b in pairs], pa.int64())], names=["a", "b"]) if pairs else None

        for batch in slices(it):
            for p, region, i, j, d, x in zip(*(batch.column(c).to_pylist() for c in range(6)), strict=True):
                if (p, region, i, j) != key:
                    if (got := done()) is not None:
                        yield got
                    key, ids, xs = (p, region, i, j), [], []
                if not ids or ids[-1] != d:
                    ids.append(d)
                    xs.append(x)
        if (got := done()) is not None:
            yield got

    return run


def components(edges: DataFrame) -> DataFrame:
    """node, comp (smallest node reachable) for every node of edges a, b: labels spread and paths are halved until nothing moves."""
    both = materialise(edges.where("a <> b").select("a", "b").union(edges.where("a <> b").select(F.col("b"), F.col("a"))).distinct())
    label = old = materialise(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("comp")))
    while True:
        near = both.join(label.select(F.col("node").alias("b"), "comp"), "b").groupBy(F.col("a").alias("node")).agg(F.min("comp").alias("m"))
        step = label.join(near, "node").select("node", F.col("comp").alias("was"), F.least("comp", "m").alias("to"))
        # the label of the label: the path to the smallest node is halved
        jump = label.select(F.col("node").alias("to"), F.col("comp").alias("far"))
        now = materialise(step.join(jump, "to", "left").select("node", F.least("to", F.coalesce("far", "to")).alias("comp"), "was"))
        moved = now.where("comp <> was").limit(1).count()
        discard(old)
        label, old = now.select("node", "comp"), now
        if not moved:
            discard(both)
            return label


def join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = WORDS, percent: int = PERCENT, **sizes) -> DataFrame:
    """id, n_shingles and component_id (smallest id reachable by links) of every row."""
    own = materialise(sets(docs, id_col, text_col, k))
    first = own.where("d is not null").groupBy("d").agg(F.min("id").alias("first"))
    label = components(materialise(links(docs, own, text_col, k, percent, **sizes)))
    named = first.join(label.withColumnRenamed("node", "d"), "d", "left").withColumn("comp", F.coalesce("comp", "d"))
    least = named.groupBy("comp").agg(F.min("first").alias("least"))
    ids = named.join(least, "comp").select("d", "least")
    return own.join(ids, "d", "left").select(F.col("id").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("least", "id").alias("component_id"))


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, percent: int = 80, broadcast_at_most: int = 1_000_000, **sizes) -> DataFrame:
    """docs without the documents whose class has a smaller id. Rows that share an id are one document and stay together.

    The ids to drop are broadcast if there are at most broadcast_at_most of them; beyond that the join shuffles.
    """
    gone = materialise(join(docs, id_col, text_col, k, percent, **sizes).where(F.col("component_id") < F.col(id_col)).select(id_col).distinct())
    return docs.join(F.broadcast(gone) if gone.count() <= broadcast_at_most else gone, id_col, "left_anti").select(*docs.columns)


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return join(table(spark, sf_dir, "documents"))
