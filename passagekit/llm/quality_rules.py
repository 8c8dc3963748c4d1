"""Quality rules: a decision list learned by sequential covering, applied as one ordered Spark conditional.

Everything runs as DataFrame expressions: text statistics, the counts that learning needs, and the rules themselves.
Learning: statistics of all labelled documents are cut at approximate quantiles; a rule starts empty and grows by the
threshold condition with the largest information gain over what no earlier rule covers; a hash-chosen third of
the labelled rows is kept apart to prune its last conditions; the rule is kept if it is precise there. Each step is one
aggregate that returns at most features x cuts rows, whatever the size of the input.

Null texts count as empty. Rows without a label are not learned from; without any labels there are no rules and only the
base rule rejects. Repeated rows are counted as often as they occur, and answered each. Other columns are not looked at.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import SPACE, let, materialise

WHITE = " \t\n\x0b\x0c\r"
STATS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
#: What thresholds are learned on, made from the statistics.
FEATURES = ["word_length", "symbol_share", "dup_line_share", "repeat_share", "distinct_share", "upper_share", "digit_share", "mark_share"]


def _repeats(words: Column) -> Column:
    """Words that lie in a three-word window found at least twice."""

    def positions(h: Column) -> Column:
        windows = F.transform(F.sequence(F.lit(0), F.size(h) - 3), lambda i: F.struct(F.xxhash64(F.get(h, i), F.get(h, i + 1), F.get(h, i + 2)).alias("g"), i.alias("i")))
        twice = let(F.array_sort(windows), lambda s: F.filter(s, lambda x, k: (x["g"] == F.get(s, k - 1)["g"]) | (x["g"] == F.get(s, k + 1)["g"])))
        return F.array_sort(F.transform(twice, lambda x: x["i"]))

    def covered(pos: Column) -> Column:
        start = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("n"))
        return F.aggregate(pos, start, lambda acc, p: F.struct(p.alias("last"), (acc["n"] + F.least(F.lit(3), p - acc["last"])).alias("n")), lambda acc: acc["n"])

    return F.when(F.size(words) < 4, F.lit(0).cast("long")).otherwise(let(F.transform(words, lambda w: F.xxhash64(w)), lambda h: covered(positions(h))))


def statistics(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, the five statistics, and the features of each row."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    lines = F.filter(F.split(F.col("_t"), "\n", -1), lambda x: F.length(F.translate(x, WHITE, "")) > 0)
    count = lambda chars: F.length("_t") - F.length(F.translate("_t", chars, ""))
    share = lambda a, b: F.coalesce(F.try_divide(a.cast("double"), b), F.lit(0.0))
    n = F.col("n_words")
    per_lines = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))
    split = F.filter(F.split("_t", f"{SPACE}+"), lambda w: w != "")
    out = docs.select(F.col(id_col), text.alias("_t")).select(
        id_col,
        let(split, lambda w: F.struct(F.size(w).cast("long").alias("n_words"), _repeats(w).alias("n_repeat_words"), F.size(F.array_distinct(w)).cast("long").alias("n_distinct"))).alias("_w"),
        per_lines.alias("_l"),
        F.length(F.translate("_t", WHITE, "")).cast("long").alias("word_chars"),
        count("#*$%&|<>").cast("long").alias("n_symbols"),
        count(".,;:!?()\"'").cast("long").alias("n_marks"),
        count("0123456789").cast("long").alias("n_digits"),
        F.length(F.regexp_replace("_t", r"[^\p{Lu}]+", "")).cast("long").alias("n_upper"),
    )
    out = out.select(id_col, "_w.*", "_l.*", "word_chars", "n_symbols", "n_marks", "n_digits", "n_upper")
    features = {
        "word_length": share(F.col("word_chars"), n), "symbol_share": share(F.col("n_symbols"), F.col("word_chars")), "dup_line_share": share(F.col("n_dup_lines"), F.col("n_lines")),
        "repeat_share": share(F.col("n_repeat_words"), n), "distinct_share": share(F.col("n_distinct"), n), "upper_share": share(F.col("n_upper"), F.col("word_chars")),
        "digit_share": share(F.col("n_digits"), F.col("word_chars")), "mark_share": share(F.col("n_marks"), F.col("word_chars")),
    }
    return out.select(id_col, *STATS, *(v.alias(k) for k, v in features.items()))


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


class Rule:
    """A conjunction of (feature, '>' or '<=', threshold) that rejects."""

    def __init__(self, conditions: list[tuple[str, str, float]], good: int = 0, bad: int = 0):
        self.conditions, self.good, self.bad = conditions, good, bad

    def column(self) -> Column:
        out = F.lit(True)
        for name, side, cut in self.conditions:
            out = out & (F.col(name) > cut if side == ">" else F.col(name) <= cut)
        return out

    def __str__(self) -> str:
        return " and ".join(f"{n} {s} {c:.6g}" for n, s, c in self.conditions) or "always"


def decision(rules: list[Rule]) -> Column:
    """The number of the first rule that holds (from 1), 0 if none: the list as one ordered conditional."""
    out = None
    for k, rule in enumerate(rules, 1):
        out = F.when(rule.column(), F.lit(k)) if out is None else out.when(rule.column(), F.lit(k))
    return F.lit(0) if out is None else out.otherwise(F.lit(0))


def _gain(p: int, n: int, p0: int, n0: int) -> float:
    return p * (math.log2(p / (p + n)) - math.log2(p0 / (p0 + n0))) if p and p0 else 0.0


def learn(rows: DataFrame, reject: str, id_col: str = "doc_id", features: list[str] | None = None, cuts: int = 24, most_rules: int = 8, most_conditions: int = 3, precise: float = 0.97, least: int = 5) -> list[Rule]:
    """Rules that reject, best first. rows: labelled statistics, `reject` (boolean) the class to cover.

    least: fewest rows to reject that a rule covers; precise: share of rejected among what it covers, on the rows
    grown on and on those kept for pruning.
    """
    names = features or FEATURES
    data = rows.where(F.col(reject).isNotNull()).select(*names, F.col(reject).alias("_bad"), (F.pmod(F.xxhash64(id_col, F.lit("prune")), F.lit(3)) == 0).alias("_prune"))
    points = data.agg(*(F.percentile_approx(n, [k / cuts for k in range(1, cuts)], 10_000).alias(n) for n in names)).first()
    # thresholds lie between neighbouring quantiles too, so a class that begins just above a common value is met
    grid = {n: sorted(set(points[n] or [])) for n in names}
    grid = {n: sorted({*v, *((a + b) / 2 for a, b in zip(v, v[1:], strict=False))}) for n, v in grid.items()}
    code = {n: sum((F.when(F.col(n) > c, F.lit(1)).otherwise(F.lit(0)) for c in v), F.lit(0)) for n, v in grid.items()}
    # equal rows of the binned table are counted once; every later step reads these counts
    binned = materialise(data.select("_bad", "_prune", *(code[n].alias(n) for n in names)).groupBy("_bad", "_prune", *names).agg(F.count(F.lit(1)).alias("_n")))

    def holds(conditions) -> Column:
        out = F.lit(True)
        for n, side, k in conditions:
            out = out & (F.col(n) > k if side == ">" else F.col(n) <= k)
        return out

    bad, good = F.sum(F.when(F.col("_bad"), F.col("_n")).otherwise(0)), F.sum(F.when(F.col("_bad"), 0).otherwise(F.col("_n")))
    found: list[list] = []
    out: list[Rule] = []
    for _ in range(most_rules):
        left = binned
        for c in found:
            left = left.where(~holds(c))
        grow: list[tuple[str, str, int]] = []
        while len(grow) < most_conditions:
            at = left.where(~F.col("_prune")).where(holds(grow)) if grow else left.where(~F.col("_prune"))
            by = at.select(F.explode(F.array(*(F.struct(F.lit(n).alias("f"), F.col(n).alias("k")) for n in names))).alias("x"), "_bad", "_n").groupBy("x.f", "x.k").agg(bad.alias("p"), good.alias("n")).collect()
            table: dict[str, dict[int, tuple[int, int]]] = {}
            for r in by:
                table.setdefault(r["f"], {})[r["k"]] = (r["p"], r["n"])
            best = None
            p0 = sum(p for p, _ in next(iter(table.values()), {}).values())
            n0 = sum(n for _, n in next(iter(table.values()), {}).values())
            if not p0 or not n0 and grow:
                break
            for f, cells in table.items():
                p = n = 0
                for k in range(len(grid[f])):
                    p, n = p + cells.get(k, (0, 0))[0], n + cells.get(k, (0, 0))[1]
                    for side, (a, b) in (("<=", (p, n)), (">", (p0 - p, n0 - n))):
                        if a >= least and (g := _gain(a, b, p0, n0)) > 0 and (best is None or g > best[0] + 1e-9):
                            best = (g, (f, side, k), a, b)
            if not best:
                break
            grow.append(best[1])
            if not best[3]:
                break
        if not grow:
            break
        heads = left.agg(*(F.sum(F.when(holds(grow[:k]) & (F.col("_prune") == side) & (F.col("_bad") == b), F.col("_n")).otherwise(0)).alias(f"{'h' if side else 'g'}{'p' if b else 'n'}{k}") for k in range(1, len(grow) + 1) for side in (True, False) for b in (True, False))).first()
        # the shortest head that is as good on the rows kept apart as the best one
        value = {k: (heads[f"hp{k}"] - heads[f"hn{k}"]) / max(1, heads[f"hp{k}"] + heads[f"hn{k}"]) for k in range(1, len(grow) + 1)}
        k = min(value, key=lambda k: (-round(value[k], 2), k))
        p, n = heads[f"gp{k}"], heads[f"gn{k}"]
        hp, hn = heads[f"hp{k}"], heads[f"hn{k}"]
        if p < least or p < precise * (p + n) or hp < precise * (hp + hn):
            k = len(grow)
            p, n, hp, hn = (heads[f"{x}{k}"] for x in ("gp", "gn", "hp", "hn"))
            if p < least or p < precise * (p + n) or hp < precise * (hp + hn):
                break
        found.append(grow[:k])
        out.append(Rule([(f, s, float(grid[f][c]) if c < len(grid[f]) else math.inf) for f, s, c in grow[:k]], good=n, bad=p))
    return out


def judge(stats: DataFrame, rules: list[Rule]) -> DataFrame:
    """stats with base_failed, the rule that fired, and kept."""
    return stats.withColumn("base_failed", base_failed()).withColumn("rule", decision(rules)).withColumn("kept", ~F.col("base_failed") & (F.col("rule") == 0))


def query(spark, sf_dir: str) -> DataFrame:
    from .common import table

    stats = materialise(statistics(table(spark, sf_dir, "documents")))
    labels = table(spark, sf_dir, "labels").where("quality is not null").select("doc_id", (F.col("quality") == 0).alias("bad"))
    rules = learn(stats.join(labels, "doc_id"), "bad")
    return judge(stats, rules).select("doc_id", *STATS, "base_failed", "kept", "rule")
