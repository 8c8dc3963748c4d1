"""Language-model scoring with a hierarchical Pitman-Yor process over words, beside a smoothed unigram base.

Every word that precedes another has a restaurant of its own; all of them share the restaurant of words as parent, whose own
parent spells a new word byte by byte. A customer is a word of the training text, and a table of a context's restaurant is a customer of
the parent. The spelling base is taken as diffuse: a word has one table in the parent's restaurant.

Seatings are sampled by Gibbs in blocks whose conditionals are exact:

* the parent's measure given its customers m_w: Dirichlet(m_w - d0, theta0 + d0 V), drawn as keyed gammas;
* for each context u with t_u tables a Gamma(theta/d + t_u) variable x_u, which makes the words of its restaurant independent;
* the tables of word w among the c customers of u, drawn at once from weights S_d(c, t) (d x_u beta_w)^t with generalised Stirling numbers
  S_d; beyond `EXACT` customers S_d follows from the limit law of the number of tables, c^-d t, read off the last computed row;
* the strengths, from beta and Bernoulli variables of the restaurants that one task holds.

Discounts follow from the numbers of pairs (of words) met once and twice. The predictive probabilities of the sampled states are
averaged, not the seatings. All draws are keyed by round, part and word, so a lost task draws the same again, and a state
is never stored: a part replays its draws from the parent counts of the rounds before.

Nothing is gathered on the driver but sums, and no table is capped. Texts are read once: a task turns them into pieces of some
millions of tokens (word numbers, compressed), and from then on only pieces, counts and answers move, as compressed arrays:
pieces ask the parts of the vocabulary for the counts of their distinct words, then the parts of the restaurants for their distinct
pairs. Words and pairs are dealt by hash, and a context with many customers is dealt over parts, so a hot word costs a part one entry a piece.
Memory per task follows from the piece and part sizes, which do not depend on the corpus.

Null and empty texts are their end mark alone. Without training rows all counts are 0 and every word is spelled. Repeated
rows are counted and scored as often as they occur. An empty table gives an empty result. A document is never cut, so a very long one makes
a piece of its own. The names of other columns do not matter.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import crc, discard, freeing, lower_words, materialise, slices

#: Tokens of a piece, bytes of text for each part of the vocabulary and of the restaurants, customers a part holds of one context.
PIECE, WORD_BYTES, PAIR_BYTES, HOT = 1_000_000, 32 << 20, 8 << 20, 500_000
#: Customers up to which Stirling numbers are computed; rounds before samples are taken, and samples.
EXACT, BURN, SAMPLES = 512, 2, 3
END = b"\n"
_FINE = 1 << 13  # logarithms travel as whole numbers of this share
_SPELL = 1 << 20  # weights of spelling are whole numbers of this share, so sums do not depend on their order


# ---- arrays as compressed bytes


def put(*arrays) -> bytes:
    """Arrays of whole numbers from 0 on: byte planes of the least width, compressed."""
    import struct

    import numpy as np
    import zstandard

    out = [struct.pack("<B", len(arrays))]
    for a in arrays:
        a = np.ascontiguousarray(a, dtype="<u8")
        width = max(1, (int(a.max(initial=0)).bit_length() + 7) // 8)
        out += [struct.pack("<QB", len(a), width), a.view(np.uint8).reshape(len(a), 8)[:, :width].T.tobytes()]
    return zstandard.ZstdCompressor(level=1).compress(b"".join(out))


def get(blob: bytes) -> list:
    import struct

    import numpy as np
    import zstandard

    raw = zstandard.ZstdDecompressor().decompress(blob)
    at, out = 1, []
    for _ in range(raw[0]):
        n, width = struct.unpack_from("<QB", raw, at)
        at += 9
        a = np.zeros((n, 8), np.uint8)
        a[:, :width] = np.frombuffer(raw, np.uint8, n * width, at).reshape(width, n).T
        out.append(a.reshape(-1).view("<i8") if n else np.zeros(0, np.int64))
        at += n * width
    return out


def steps(a):
    import numpy as np

    return np.diff(a, prepend=0)


def put_pairs(u, w, n) -> bytes:
    """Pairs in rising order and a number for each."""
    import numpy as np

    du = steps(u)
    dw = np.where(du == 0, np.diff(w, prepend=0), w) if len(w) else w
    return put(du, dw, n)


def get_pairs(blob: bytes):
    import numpy as np

    du, dw, n = get(blob)
    u = np.cumsum(du)
    w = np.cumsum(dw)
    first = np.flatnonzero(np.concatenate([[True], du[1:] != 0])) if len(du) else np.zeros(0, np.int64)
    before = np.concatenate([[0], w])[first]  # what the sum holds of earlier contexts
    return u, w - np.repeat(before, np.diff(np.append(first, len(du)))), n


# ---- keyed draws


def _mix(x):
    """A 64-bit finaliser (public constants) over unsigned numbers."""
    import numpy as np

    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def uniforms(ids, key: int, lane: int):
    """Numbers in (0, 1) that depend on id, key and lane alone."""
    import numpy as np

    with np.errstate(over="ignore"):
        x = np.asarray(ids).astype(np.uint64) + _mix(np.uint64((key * 0x9E3779B97F4A7C15 + lane * 0xD6E8FEB86659FD93 + 1) % (1 << 64)))
    return (_mix(_mix(x)) >> np.uint64(11)) * 2.0**-53 + 2.0**-54


def keyed_gamma(shape, ids, key: int):
    """Gamma draws (shape > 0), the same wherever an id is met: rejection from a cubed normal, with the boost of shapes below 1."""
    import numpy as np

    shape = np.broadcast_to(np.asarray(shape, dtype=np.float64), np.shape(ids))
    d = shape + 2 / 3
    c = 1 / np.sqrt(9 * d)
    out, todo, lane = np.zeros(len(d)), np.arange(len(d)), 0
    while len(todo):
        a, b, e = (uniforms(ids[todo], key, lane + i) for i in range(3))
        x = np.sqrt(-2 * np.log(a)) * np.cos(2 * np.pi * b)
        v = (1 + c[todo] * x) ** 3
        with np.errstate(invalid="ignore", divide="ignore"):
            ok = (v > 0) & (np.log(e) < 0.5 * x * x + d[todo] * (1 - v + np.log(np.maximum(v, 1e-300))))
        out[todo[ok]] = (d[todo] * v)[ok]
        todo, lane = todo[~ok], lane + 3
    return out * uniforms(ids, key, 1 << 20) ** (1 / shape)


_STIRLING: dict = {}


def log_stirling(d: float, most: int):
    """log S_d(c, t) for c, t up to `most`: S(c + 1, t) = S(c, t - 1) + (c - d t) S(c, t)."""
    import numpy as np

    if (d, most) not in _STIRLING:
        _STIRLING.clear()
        out = np.full((most + 1, most + 1), -np.inf)
        out[1, 1:2] = 0.0
        t = np.arange(most + 1)
        for c in range(1, most):
            with np.errstate(divide="ignore", invalid="ignore"):
                beside = out[c] + np.log(np.maximum(c - d * t, 1e-300))
                out[c + 1, 1:] = np.logaddexp(out[c, :-1], beside[1:])
            out[c + 1, c + 2 :] = -np.inf
        _STIRLING[d, most] = out
    return _STIRLING[d, most]


def draw_tables(c, z, d: float, rng, exact: int = EXACT):
    """Tables of pairs with c customers, from weights S_d(c, t) z^t."""
    import numpy as np

    out = np.minimum(c, 1)
    order = np.argsort(c, kind="stable")
    sizes, first = np.unique(c[order], return_index=True)
    log_z, s = np.log(np.maximum(z, 1e-300)), log_stirling(d, exact) if len(sizes) and sizes[-1] > 1 else None
    for k, (size, at) in enumerate(zip(sizes.tolist(), first.tolist(), strict=True)):
        own = order[at : first[k + 1] if k + 1 < len(first) else len(order)]
        if size > exact:
            break
        if size > 1:
            for lo in range(0, len(own), 1 + 2_000_000 // size):
                some = own[lo : lo + 1 + 2_000_000 // size]
                out[some] = 1 + _pick(s[size, 1 : size + 1] + log_z[some, None] * np.arange(1, size + 1), rng)
    big = order[c[order] > exact]
    for lo in range(0, len(big), 1000):
        some = big[lo : lo + 1000]
        out[some] = _draw_many(c[some].astype(np.float64), log_z[some], d, s[exact, 1:], rng)
    return out


def _pick(log_p, rng):
    """For each row a column, with chances in proportion to the exponentials."""
    import numpy as np

    p = np.cumsum(np.exp(log_p - log_p.max(1, keepdims=True)), axis=1)
    return (p < rng.random(len(p))[:, None] * p[:, -1:]).sum(1)


def log_factorial(n):
    import numpy as np

    x = n + 1.0
    shift = np.log(x) + np.log(x + 1) + np.log(x + 2)  # Stirling's series at x + 3
    y = x + 3
    return (y - 0.5) * np.log(y) - y + 0.5 * math.log(2 * math.pi) + 1 / (12 * y) - 1 / (360 * y**3) - shift


def _draw_many(c, log_z, d: float, last, rng, points: int = 512):
    """Tables among many customers. last: log S_d of 1, 2, ... tables among the most customers that are computed."""
    import numpy as np

    most = len(last)
    n = np.arange(1, most + 1)
    law = last + (n - 1) * math.log(d) + log_factorial(n - 1.0)  # log chance of n tables at strength 0, but for a constant

    def log_p(t):
        near = t * ((most / c) ** d)[:, None]
        at = np.clip(near, 1, most)
        return t * log_z[:, None] - (t - 1) * math.log(d) - log_factorial(t - 1) + np.interp(at, n, law) - 50.0 * (near > most)

    low, high = np.ones(len(c)), np.minimum(c, 64 + 8 * np.exp(np.minimum(log_z, 40)) / d)
    grid = np.linspace(0, 1, points)
    for _ in range(4):  # the place of the maximum
        t = np.rint(low[:, None] + (high - low)[:, None] * grid)
        best = log_p(t).argmax(1)
        rows = np.arange(len(c))
        low, high = t[rows, np.maximum(best - 1, 0)], t[rows, np.minimum(best + 1, points - 1)]
    mid = (low + high) / 2
    low, high = np.maximum(1, np.floor(mid - 16 - 10 * np.sqrt(mid))), np.minimum(c, np.ceil(mid + 16 + 10 * np.sqrt(mid)))
    # every whole number near the maximum, or evenly spread ones that stand for their surroundings
    width = np.maximum(1.0, (high - low + 1) / points)
    t = low[:, None] + np.floor((np.arange(points) + 0.5) * width[:, None])
    weight = log_p(np.minimum(t, c[:, None]))
    got = t[np.arange(len(c)), _pick(np.where(t <= high[:, None], weight, -np.inf), rng)]
    return np.clip(np.rint(got + (rng.random(len(c)) - 0.5) * (width - 1)), 1, c).astype(np.int64)


# ---- texts to pieces


def pieces(docs: DataFrame, id_col: str, text_col: str, held: Column, word_parts: int, size: int = PIECE) -> DataFrame:
    """piece, part, blob, words, ids: for every piece one row with its texts (part -1) and one with the words it asks of each part."""

    def run(it):
        import numpy as np
        import pyarrow as pa
        import xxhash
        import zstandard
        from pyspark import TaskContext

        class Numbers(dict):
            def __missing__(self, w):
                self[w] = n = len(self)
                return n

        task, made = TaskContext.get().partitionId(), 0
        known, idx, lens, marks, ids, total = Numbers(), [], [], [], [], 0

        def row(part, blob, words=None, who=None):
            return pa.RecordBatch.from_arrays([pa.array([(task << 32) + made], pa.int64()), pa.array([part], pa.int32()), pa.array([blob], pa.binary()), pa.array([words], pa.binary()), pa.array([who], pa.list_(id_type))], names=["piece", "part", "blob", "words", "ids"])

        def flush():
            flat, n = np.concatenate(idx), np.array(lens)
            words = list(known)
            uses = np.bincount(flat, minlength=len(words))
            # numbers by falling use compress best
            by = np.argsort(-uses, kind="stable")
            new = np.empty(len(by), np.int64)
            new[by] = np.arange(len(by))
            words, flat = [words[i] for i in by], new[flat]
            train = np.bincount(flat, np.repeat(1 - np.array(marks), n), len(words)).astype(np.int64)
            h = np.array([xxhash.xxh3_64_intdigest(w) for w in words], dtype=np.uint64)
            part = ((h >> np.uint64(32)) % np.uint64(word_parts)).astype(np.int64)
            order = np.lexsort((h, part))
            stop = np.searchsorted(part[order], np.arange(word_parts), side="right")
            for p in range(word_parts):
                own = order[stop[p - 1] if p else 0 : stop[p]]
                if len(own):
                    yield row(p, put(np.diff(h[own], prepend=np.uint64(0)), train[own]))

            yield row(-1, put(n, np.array(marks), flat, order, np.array([new[known[END]]])), zstandard.ZstdCompressor(level=1).compress(b" ".join(words)), [x for a in ids for x in a.to_pylist()])

        for batch in slices(it):
            id_type = batch.schema.field(0).type
            fresh = []
            for text in batch.column(1).to_pylist():
                words = lower_words(text)
                words.append(END)
                fresh.append(np.fromiter(map(known.__getitem__, words), dtype=np.int32, count=len(words)))
            idx += fresh
            lens += map(len, fresh)
            marks += [int(bool(x)) for x in batch.column(2).to_pylist()]
            ids.append(batch.column(0))
            total += sum(map(len, fresh))
            if total >= size:
                yield from flush()
                known, idx, lens, marks, ids, total, made = Numbers(), [], [], [], [], 0, made + 1
        if lens:
            yield from flush()

    return docs.select(F.col(id_col), F.col(text_col), F.coalesce(held, F.lit(False)).alias("__held")).mapInArrow(run, f"piece long, part int, blob binary, words binary, ids array<{dict(docs.dtypes)[id_col]}>").withColumn("kind", F.when(F.col("part") < 0, "text").otherwise("ask"))


class Piece:
    """A piece with the numbers and counts of its words: its distinct pairs, in the order in which they are asked."""

    def __init__(self, blob: bytes, words: bytes, answers: list, pair_parts: int, hot: int):
        """answers: for each part that was asked, in order, its numbers and counts."""
        import numpy as np
        import zstandard

        self.lens, self.held, self.flat, order, end = get(blob)
        self.words = zstandard.ZstdDecompressor().decompress(words).split(b" ")
        own = [get(a) for a in answers]
        number, self.count = np.empty(len(order), np.int64), np.empty(len(order), np.int64)
        number[order], self.count[order] = (np.concatenate([a[i] for a in own]) for i in range(2))
        self.starts = np.cumsum(self.lens) - self.lens
        before = np.concatenate([end, self.flat[:-1]])
        before[self.starts] = end[0]
        ids, label = np.unique(number, return_inverse=True)
        self.key, self.at = np.unique(label[before] << 32 | label[self.flat], return_inverse=True)
        self.u, self.w = ids[self.key >> 32], ids[self.key & 0xFFFFFFFF]
        # a context of many customers is dealt over parts by its words
        many = np.zeros(len(ids), np.int64)
        np.maximum.at(many, label, np.where(number > 0, self.count, 0))
        salts = (1 + many // hot)[self.key >> 32].astype(np.uint64)
        self.part = (_mix(self.u.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + _mix(self.w.astype(np.uint64)) % salts) % np.uint64(pair_parts)).astype(np.int64)
        self.order = np.argsort(self.part, kind="stable")
        self.hot = (many >= hot)[self.key >> 32]

    def asks(self):
        """(part, blob) for each part that has some of the pairs: contexts, words, training counts and which contexts are dealt."""
        import numpy as np

        train = np.bincount(self.at, np.repeat(1 - self.held, self.lens), len(self.key)).astype(np.int64)
        parts, first = np.unique(self.part[self.order], return_index=True)
        for p, a, b in zip(parts.tolist(), first, [*first[1:], len(self.order)], strict=True):
            own = self.order[a:b]
            yield p, put_pairs(self.u[own], self.w[own], train[own] * 2 + self.hot[own])

    def spelling(self):
        """Byte triples of the distinct training words; each word weighs 1 / its count for each time it occurs here, 1 over all pieces."""
        import numpy as np

        n = np.bincount(self.flat, np.repeat(1 - self.held, self.lens), len(self.words))
        weight = np.where(n > 0, np.rint(n / np.maximum(self.count, 1) * _SPELL), 0)
        weight[self.words.index(END)] = 0
        gram, at = triples(self.words)
        # bytes that occur, numbered without gaps, so that triples are counted in a small table
        seen = np.flatnonzero(np.bincount(gram & 255, minlength=256))
        code = np.zeros(256, np.int64)
        code[seen] = np.arange(len(seen))
        k = len(seen)
        total = np.bincount((code[gram >> 16] * k + code[gram >> 8 & 255]) * k + code[gram & 255], weight[at], k**3).astype(np.int64)
        got = np.flatnonzero(total)
        return seen[got // (k * k)] << 16 | seen[got // k % k] << 8 | seen[got % k], total[got]


def triples(words: list[bytes]):
    """(two bytes before and the byte, word number) for every byte of words and the space that ends each; spaces stand before a word."""
    import numpy as np

    if not words:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    b = np.frombuffer(b"  " + b" ".join(words) + b" ", dtype=np.uint8)
    ends = b[2:] == 32
    first = np.where(b[1:-1] == 32, 32, b[:-2]).astype(np.int64)
    return first << 16 | b[1:-1].astype(np.int64) << 8 | b[2:], np.cumsum(ends) - ends


class Spelling:
    """Bytes of a new word given the two before: absolute discounts, interpolated down to one byte and a uniform base."""

    def __init__(self, gram, weight, d: float = 0.75):
        import numpy as np

        prob = np.full((1, 256), 1 / 256)
        ctx = np.zeros(1, np.int64)
        for k in range(3):
            key = gram & ((1 << (8 * (k + 1))) - 1)
            u, inv = np.unique(key, return_inverse=True)
            n = np.bincount(inv, weight / _SPELL, len(u)) + 1e-9
            own, of = np.unique(u >> 8, return_inverse=True)
            up = prob[np.searchsorted(ctx, own & ((1 << (8 * max(k - 1, 0))) - 1))] if k else np.repeat(prob, len(own), 0)
            cut = np.minimum(n, d)
            total, back = np.bincount(of, n, len(own)), np.bincount(of, cut, len(own))
            now = up * ((back + 1e-3) / (total + 1e-3))[:, None]
            now[of, u & 255] += ((n - cut) / (total[of] + 1e-3))
            if len(own):
                prob, ctx = now, own
            self.__dict__[f"level{k}"] = (own, np.log10(now).astype(np.float32))

    def log10(self, words: list[bytes]):
        import numpy as np

        gram, at = triples(words)
        out, done = np.zeros(len(gram), np.float64), np.zeros(len(gram), bool)
        for k in (2, 1, 0):
            own, rows = self.__dict__[f"level{k}"]
            if len(own):
                ctx = (gram >> 8) & ((1 << (8 * k)) - 1)
                pos = np.minimum(np.searchsorted(own, ctx), len(own) - 1)
                hit = ~done & (own[pos] == ctx)
                out[hit] = rows[pos[hit], gram[hit] & 255]
                done |= hit
        out[~done] = -math.log10(256)
        return np.bincount(at, out, len(words))


# ---- restaurants


class Part:
    """The restaurants (or shares of dealt ones) that one part holds."""

    def __init__(self, blob: bytes, word_parts: int):
        import numpy as np

        u, self.w, n = get_pairs(blob)
        self.c, dealt = n >> 1, (n & 1).astype(bool)
        first = np.diff(u, prepend=-1) != 0  # contexts come in order
        self.ids, self.iu = u[first], np.cumsum(first) - 1
        self.hot = np.zeros(len(self.ids), bool)
        self.hot[self.iu] = dealt
        self.words, self.iw = np.unique(self.w, return_inverse=True)
        self.customers = np.bincount(self.iu, self.c, len(self.ids))
        # only pairs of several customers can have several tables: their contexts and words
        self.live = np.flatnonzero(self.c > 1)
        self.live_u, self.live_iu = np.unique(self.iu[self.live], return_inverse=True)
        self.live_w, self.live_iw = np.unique(self.iw[self.live], return_inverse=True)
        # words and dealt contexts in the order in which they are sent to the parts of the vocabulary
        self.sent = self._dealt(np.flatnonzero(self.words > 0), self.words, word_parts)
        self.sent_hot = self._dealt(np.flatnonzero(self.hot), self.ids, word_parts)

    @staticmethod
    def _dealt(at, ids, parts):
        """part -> positions, by rising id."""
        import numpy as np

        p = (ids[at] - 1) % parts
        return {int(k): at[p == k] for k in np.unique(p)}

    def message(self, t, word_parts: int):
        """(part of the vocabulary, blob): tables of its words, customers and tables of its dealt contexts."""
        import numpy as np

        m = np.bincount(self.iw, t, len(self.words)).astype(np.int64)
        k = np.bincount(self.iu, t, len(self.ids)).astype(np.int64)
        none = np.zeros(0, np.int64)
        for p in sorted(self.sent.keys() | self.sent_hot.keys()):
            a, b = self.sent.get(p, none), self.sent_hot.get(p, none)
            yield p, put(steps((self.words[a] - 1) // word_parts), m[a], steps((self.ids[b] - 1) // word_parts), self.customers[b].astype(np.int64), k[b])

    def replies(self, got: dict):
        """Per word the parent's customers, and per context customers and tables, of one round's replies (part -> blob)."""
        import numpy as np

        m = np.zeros(len(self.words))
        c, k = self.customers.copy(), np.zeros(len(self.ids))
        for p, blob in got.items():
            own, c_hot, k_hot = get(blob)
            if p in self.sent:
                m[self.sent[p]] = own
            if p in self.sent_hot:
                c[self.sent_hot[p]], k[self.sent_hot[p]] = c_hot, k_hot
        return m, c, k

    def tables_of(self, t, k_dealt):
        """Tables of each context; those of dealt ones as the replies told."""
        import numpy as np

        own = np.bincount(self.iu, t, len(self.ids))
        return np.where(self.hot, k_dealt, own)

    def replay(self, replies: list[dict], told: list[dict], part: int, seed: int):
        """The seatings of every round: tables of each pair, with that round's parent customers and context totals."""
        import numpy as np

        t = np.minimum(self.c, 1)
        for r, got in enumerate(replies):
            m, c, k = self.replies(got)
            k = self.tables_of(t, k)
            yield t, m, c, k
            now = told[r]
            if self.live.size:
                x = keyed_gamma(now["theta"] / now["d"] + k[self.live_u], self.ids[self.live_u], seed * 1000 + 2 * r)
                beta = parent(m[self.live_w], self.words[self.live_w], now, r, seed)
                z = now["d"] * x[self.live_iu] * beta[self.live_iw]
                t = t.copy()
                t[self.live] = draw_tables(self.c[self.live], z, now["d"], np.random.Generator(np.random.Philox(key=[seed, part * 1000 + r])))
        yield t, None, None, None

    def strength(self, t, theta: float, d: float, rng):
        """Sums of the Bernoulli and log beta variables that the strength depends on, over the contexts held whole."""
        import numpy as np

        c, k = self.customers, np.bincount(self.iu, t, len(self.ids)).astype(np.int64)
        own = np.flatnonzero((c > 1) & ~self.hot)
        if not len(own):
            return 0.0, 0.0
        n = np.maximum(k[own] - 1, 0)
        i = np.arange(1, n.sum() + 1) - np.repeat(np.cumsum(n) - n, n)
        return float((rng.random(len(i)) < theta / (theta + d * i)).sum()), float(np.log(rng.beta(theta + 1, c[own] - 1)).sum())


def parent(m, ids, now: dict, r: int, seed: int):
    """The parent's measure on its words: drawn given their customers; in the first round its mean."""
    import numpy as np

    if not r:
        return np.maximum(m - now["d0"], 1e-9) / (now["theta0"] + now["m"])
    return np.where(m > 0, keyed_gamma(np.maximum(m - now["d0"], 1e-9), ids, seed * 1000 + 2 * r + 1), 0) / max(now["z"], 1e-300)


def _discount(once: int, twice: int) -> float:
    return min(0.95, max(0.05, once / max(1, once + 2 * twice)))


def _sum(df: DataFrame, *cols: str) -> dict:
    row = df.agg(*(F.sum(c).alias(c) for c in cols)).first().asDict()
    return {c: row[c] or 0 for c in cols}


def score(docs: DataFrame, held: Column, id_col: str = "doc_id", text_col: str = "text", piece: int = PIECE, word_bytes: int = WORD_BYTES, pair_bytes: int = PAIR_BYTES, hot: int = HOT, burn: int = BURN, samples: int = SAMPLES, seed: int = 11) -> DataFrame:
    """id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row; rows with held are not learned from."""
    spark = docs.sparkSession
    id_type = dict(docs.dtypes)[id_col]
    size = docs.agg(F.sum(F.octet_length(F.coalesce(F.col(text_col), F.lit(""))).cast("long") + 2).alias("b")).first()["b"] or 0
    wp, pp = max(1, -(-size // word_bytes)), max(1, -(-size // pair_bytes))

    def spread(df: DataFrame, by: str, groups: int) -> DataFrame:
        """df dealt by a key of so many values: one task for each, up to a bound."""
        return df.repartition(max(1, min(groups, 20_000)), by)

    texts = materialise(pieces(docs, id_col, text_col, held, wp, piece), "kind")
    n_pieces = max(1, texts.where("kind = 'text'").count())

    # 1. counts of words
    def count_words(t):
        import numpy as np
        import pyarrow as pa

        part, who = t["part"][0].as_py(), t["piece"].to_pylist()
        own = [get(b) for b in t["blob"].to_pylist()]
        h = [np.cumsum(a.view(np.uint64)) for a, _ in own]
        u, inv = np.unique(np.concatenate(h), return_inverse=True)
        total = np.bincount(inv, np.concatenate([n for _, n in own]), len(u)).astype(np.int64)
        by = np.lexsort((u, -total))
        rank = np.empty(len(by), np.int64)
        rank[by] = np.arange(len(by))
        number = np.where(total > 0, 1 + rank * wp + part, 0)  # 0: no training text has it
        rows, at = [(None, part, int((total > 0).sum()), int(total.sum()), None)], 0
        for p, x in zip(who, h, strict=True):
            i = inv[at : at + len(x)]
            at += len(x)
            rows.append((p, part, None, None, put(number[i], total[i])))
        return pa.table(dict(zip(("piece", "part", "v", "n", "blob"), (pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)), strict=True)))

    answers = materialise(spread(texts.where("kind = 'ask'").select("piece", "part", "blob"), "part", wp).groupBy("part").applyInArrow(freeing(count_words), "piece long, part int, v long, n long, blob binary"))
    discard(texts, folder="kind=ask")
    all_ = _sum(answers.where("piece is null"), "v", "n")
    v, n = all_["v"], all_["n"]

    stream = lambda: spread(texts.where("kind = 'text'").select("piece", "blob", "words", "ids"), "piece", n_pieces).groupBy("piece")
    replies = lambda: spread(answers.where("piece is not null").select("piece", "part", "blob"), "piece", n_pieces).groupBy("piece")

    def open_piece(own, told):
        by = sorted(zip(told["part"].to_pylist(), told["blob"].to_pylist(), strict=True))
        return Piece(own["blob"][0].as_py(), own["words"][0].as_py(), [b for _, b in by], pp, hot)

    # 2. pairs that the pieces ask for, and how their words are spelled
    def ask(own, told):
        import pyarrow as pa

        p = open_piece(own, told)
        who = own["piece"][0].as_py()
        gram, weight = p.spelling()
        rows = [(who, q, b) for q, b in p.asks()] + [(who, -1, put(gram, weight))]
        a, b, c = zip(*rows, strict=True)
        return pa.table({"piece": pa.array(a, pa.int64()), "q": pa.array(b, pa.int32()), "blob": pa.array(c, pa.binary())})

    asked = materialise(stream().cogroup(replies()).applyInArrow(freeing(ask), "piece long, q int, blob binary"))

    def spelt(it):
        import numpy as np
        import pyarrow as pa

        seen = np.zeros(1 << 24, np.int64)  # all byte triples there can be
        for batch in it:
            for blob in batch.column(0).to_pylist():
                gram, weight = get(blob)
                seen[gram] += weight
        own = np.flatnonzero(seen)
        yield pa.RecordBatch.from_arrays([pa.array(own), pa.array(seen[own])], names=["gram", "n"])

    # at most 2^24 rows whatever the corpus, in practice the triples that words are made of
    grams = asked.where("q < 0").select("blob").mapInArrow(spelt, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).orderBy("gram").toArrow()
    spelling = spark.sparkContext.broadcast(Spelling(grams["gram"].to_numpy(), grams["n"].to_numpy()))

    # 3. the restaurants
    def seat(t):
        import numpy as np
        import pyarrow as pa

        q, who = t["q"][0].as_py(), t["piece"].to_pylist()
        own = [get_pairs(b) for b in t["blob"].to_pylist()]
        u, w, c = (np.concatenate([x[i] for x in own]) for i in range(3))
        iu, ju = np.unique(u, return_inverse=True)
        most = int(w.max(initial=0)) + 1
        iw, jw = (range(most), w) if most * len(iu) < 1 << 62 else np.unique(w, return_inverse=True)
        key, inv = np.unique(ju * len(iw) + jw, return_inverse=True)
        total = np.bincount(inv, c >> 1, len(key)).astype(np.int64)
        dealt = np.zeros(len(key), np.int64)
        dealt[inv] = c & 1
        rows, at = [(None, q, int((total == 1).sum()), int((total == 2).sum()), put_pairs(iu[key // len(iw)], key % len(iw) if isinstance(iw, range) else iw[key % len(iw)], total * 2 + dealt))], 0
        for p, x in zip(who, own, strict=True):
            rows.append((p, q, None, None, put(steps(inv[at : at + len(x[0])]))))
            at += len(x[0])
        return pa.table(dict(zip(("piece", "q", "once", "twice", "blob"), (pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)), strict=True)))

    rooms = materialise(spread(asked.where("q >= 0"), "q", pp).groupBy("q").applyInArrow(freeing(seat), "piece long, q int, once long, twice long, blob binary"))
    discard(asked)
    ones = _sum(rooms.where("piece is null"), "once", "twice")
    d = _discount(ones["once"], ones["twice"])

    def up(told: list[dict]):
        """Pairs' side of a round: messages to the vocabulary after as many draws as rounds have been told."""

        def run(own, got):
            import numpy as np
            import pyarrow as pa

            q, p = own["q"][0].as_py(), Part(own["blob"][0].as_py(), wp)
            heard = [{} for _ in told]
            for r, part, blob in zip(got["r"].to_pylist(), got["part"].to_pylist(), got["blob"].to_pylist(), strict=True):
                heard[r][part] = blob
            t = [x for x, *_ in p.replay(heard, told, q, seed)][-1]
            now = told[-1] if told else {"theta": 1.0, "d": d}
            y, x = p.strength(t, now["theta"], d, np.random.Generator(np.random.Philox(key=[seed + 1, q * 1000 + len(told)])))
            rows = [(q, part, 0.0 if i else y, 0.0 if i else x, b) for i, (part, b) in enumerate(p.message(t, wp))]
            if not rows:
                return pa.table({"q": pa.array([], pa.int32()), "part": pa.array([], pa.int32()), "y": pa.array([], pa.float64()), "x": pa.array([], pa.float64()), "blob": pa.array([], pa.binary())})
            return pa.table(dict(zip(("q", "part", "y", "x", "blob"), (pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.binary()), strict=True)), strict=True)))

        return run

    def down(r: int, d0: float):
        """The vocabulary's side: sums for each word and dealt context, back to those who sent a share."""

        def run(t):
            import numpy as np
            import pyarrow as pa

            part, who = t["part"][0].as_py(), t["q"].to_pylist()
            own = [get(b) for b in t["blob"].to_pylist()]
            at = [np.cumsum(x[0]) for x in own]
            m = np.bincount(np.concatenate(at), np.concatenate([x[1] for x in own])).astype(np.int64)
            hot_at = [np.cumsum(x[2]) for x in own]
            some = np.concatenate(hot_at)
            c, k = (np.bincount(some, np.concatenate([x[i] for x in own])).astype(np.int64) for i in (3, 4))
            seen = np.flatnonzero(m)
            z = float(keyed_gamma(m[seen] - d0, 1 + seen * wp + part, seed * 1000 + 2 * r + 1).sum()) if r and len(seen) else 0.0
            rows = [(None, part, int(m.sum()), len(seen), int((m == 1).sum()), int((m == 2).sum()), z, sum(t["y"].to_pylist()), sum(t["x"].to_pylist()), None)]
            rows += [(q, part, *[None] * 7, put(m[a], c[b], k[b])) for q, a, b in zip(who, at, hot_at, strict=True)]
            kinds = (pa.int32(), pa.int32(), *[pa.int64()] * 4, *[pa.float64()] * 3, pa.binary())
            return pa.table(dict(zip(("q", "part", "m", "v", "once", "twice", "z", "y", "x", "blob"), (pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)), strict=True)))

        return run

    import numpy as np

    told, tables, d0 = [], [], 0.75
    heard = spark.createDataFrame([], "q int, part int, r int, blob binary")
    pairs = lambda: spread(rooms.where("piece is null").select("q", "blob"), "q", pp).groupBy("q")
    rng = np.random.default_rng(seed)
    for r in range(burn + samples):
        sent = pairs().cogroup(spread(heard, "q", pp).groupBy("q")).applyInArrow(freeing(up(list(told))), "q int, part int, y double, x double, blob binary")
        sums = materialise(spread(sent, "part", wp).groupBy("part").applyInArrow(freeing(down(r, d0)), "q int, part int, m long, v long, once long, twice long, z double, y double, x double, blob binary"))
        tables.append(sums)
        now = _sum(sums.where("q is null"), "m", "v", "once", "twice", "z", "y", "x")
        if not r:
            d0 = _discount(now["once"], now["twice"])
        before = told[-1] if told else {"theta": 1.0, "theta0": 1.0}
        theta0 = _strength_of_one(before["theta0"], d0, now["m"], now["v"], rng)
        theta = rng.gamma(1 + now["y"], 1 / (1 - now["x"])) if r else before["theta"]
        z = now["z"] + rng.gamma(theta0 + d0 * now["v"])
        told.append({"theta": float(theta), "theta0": float(theta0), "d": d, "d0": d0, "m": now["m"], "v": now["v"], "z": float(z)})
        heard = heard.union(sums.where("q is not null").select("q", "part", F.lit(r).alias("r"), "blob"))

    # 4. averaged predictive probabilities of the pairs, back to the pieces
    def predict(own, got):
        import numpy as np
        import pyarrow as pa

        q, main, asks = own["q"][0].as_py(), None, []
        for p, blob in zip(own["piece"].to_pylist(), own["blob"].to_pylist(), strict=True):
            if p is None:
                main = blob
            else:
                asks.append((p, blob))
        rest = Part(main, wp)
        told_of = [{} for _ in told]
        for r, part, blob in zip(got["r"].to_pylist(), got["part"].to_pylist(), got["blob"].to_pylist(), strict=True):
            told_of[r][part] = blob
        total = np.zeros(len(rest.c))
        for r, (t, m, c, k) in enumerate(rest.replay(told_of, told, q, seed)):
            if m is None or r < burn:
                continue
            now = told[r]
            mean = np.where(rest.words > 0, np.maximum(m - now["d0"], 0), now["theta0"] + now["d0"] * now["v"]) / (now["theta0"] + now["m"])
            back = np.where(c > 0, (now["theta"] + d * k) / (now["theta"] + np.maximum(c, 1)), 1.0)
            total += np.where(rest.c > 0, rest.c - d * t, 0) / (now["theta"] + np.maximum(c, 1))[rest.iu] + back[rest.iu] * mean[rest.iw]
        out = np.rint(-np.log10(np.clip(total / samples, 1e-300, 1)) * _FINE).astype(np.int64)
        rows = [(p, q, put(out[np.cumsum(get(b)[0])])) for p, b in asks]
        a, b, c = zip(*rows, strict=True)
        return pa.table({"piece": pa.array(a, pa.int64()), "q": pa.array(b, pa.int32()), "blob": pa.array(c, pa.binary())})

    known = materialise(spread(rooms.select("q", "piece", "blob"), "q", pp).groupBy("q").cogroup(spread(heard, "q", pp).groupBy("q")).applyInArrow(freeing(predict), "piece long, q int, blob binary"))
    discard(rooms, *tables)

    # 5. sums for each text
    less = math.log10(n + 0.1 * (v + 1))
    both = known.select("piece", F.col("q").alias("part"), "blob", F.lit(True).alias("pairs")).union(answers.where("piece is not null").select("piece", "part", "blob", F.lit(False)))

    def total(own, got):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        p = open_piece(own, got.filter(pc.invert(got["pairs"])))
        by = got.filter(got["pairs"])
        by = sorted(zip(by["part"].to_pylist(), by["blob"].to_pylist(), strict=True))
        value = np.empty(len(p.key))
        value[p.order] = np.concatenate([get(b)[0] for _, b in by]) / -_FINE
        spelled = np.zeros(len(p.words))
        new = np.flatnonzero(p.count == 0)
        spelled[new] = spelling.value.log10([p.words[i] for i in new])
        spelled[p.words.index(END)] = 0  # no word that is spelled
        per = value[p.at] + spelled[p.flat]
        c = p.count[p.flat]
        sums = [np.add.reduceat(x, p.starts) for x in (c > 0, np.log10(c + 0.1), per)]
        ids = own["ids"].combine_chunks()
        return pa.table({"id": ids.flatten(), "held_out": pa.array(p.held.astype(bool)), "n_tokens": pa.array(p.lens), "n_known": pa.array(sums[0].astype(np.int64)), "base_score": pa.array(sums[1] - p.lens * less), "score": pa.array(sums[2])})

    got = stream().cogroup(spread(both, "piece", n_pieces).groupBy("piece")).applyInArrow(freeing(total), f"id {id_type}, held_out boolean, n_tokens long, n_known long, base_score double, score double")
    return got.select(F.col("id").alias(id_col), "held_out", "n_tokens", "n_known", F.lit(n).cast("long").alias("train_tokens"), "base_score", "score")


def _strength_of_one(theta: float, d: float, customers: int, tables: int, rng) -> float:
    """The strength of one restaurant, by the same variables as those of the contexts."""
    import numpy as np

    if customers < 2:
        return theta
    near = np.arange(1, min(tables, 1_000_000))
    y = (rng.random(len(near)) < theta / (theta + d * near)).sum()
    if tables > 1_000_000:
        y += rng.poisson(theta / d * math.log(tables / 1e6))
    return float(rng.gamma(1 + y, 1 / (1 - math.log(rng.beta(theta + 1, customers - 1)))))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return score(table(spark, sf_dir, "documents"), crc(F.col("doc_id")) % 10 == 0)
