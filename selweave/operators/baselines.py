"""Classical estimators over long queries (qid, attr, lo, hi), as DataFrame plans.

All answer with (qid, est_rows). ``tuples`` are compact code rows with ``mult``.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from selweave.functions.draws import uniform

from .query import Queries
from .relation import Dictionary
from .truth import true_counts, true_counts_grouped


def _product(column: Column) -> Column:
    """Product over a group; a zero factor gives zero."""
    return F.when(F.min(column) <= 0, F.lit(0.0)).otherwise(F.exp(F.sum(F.log(column))))


# --- full joint table, independence, samples ---


def joint_points(tuples: DataFrame, preds: DataFrame, attrs: list[str]) -> DataFrame:
    return true_counts_grouped(tuples, preds, attrs).select("qid", F.col("true_rows").cast("double").alias("est_rows"))


def independence(dic: Dictionary, preds: DataFrame) -> DataFrame:
    """Product of the attributes' own shares; each share is a sum over the interval."""
    n = dic.rows
    parts = preds.join(dic.frame.select("attr", "code", "freq"), "attr").where(F.col("code").between(F.col("lo"), F.col("hi"))).groupBy("qid", "attr").agg((F.sum("freq") / F.lit(float(n))).alias("p"))
    every = preds.select("qid", "attr").distinct().join(parts, ["qid", "attr"], "left").withColumn("p", F.coalesce("p", F.lit(0.0)))
    return every.groupBy("qid").agg((_product(F.col("p")) * F.lit(float(n))).alias("est_rows"))


def md5_sample(codes: DataFrame, attrs: list[str], share: float = 0.01, seed: int = 42) -> DataFrame:
    """Bernoulli sample that any engine repeats: equal rows are numbered, and each row's md5 draw decides."""
    key = F.concat_ws("|", *(F.col(a).cast("string") for a in attrs))
    numbered = codes.groupBy(*attrs).agg(F.sum("mult").alias("mult") if "mult" in codes.columns else F.count("*").alias("mult"))
    step = F.lit(1 << 16)  # a tuple of many copies is numbered in blocks, so no array grows with the data
    blocks = numbered.select(*attrs, "mult", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("mult") - 1) / step))).alias("block"))
    rows = blocks.select(*attrs, F.explode(F.sequence(F.col("block") * step + 1, F.least(F.col("mult"), (F.col("block") + 1) * step))).alias("copy"))
    return rows.where(uniform(seed, key, F.col("copy")) < share).groupBy(*attrs).agg(F.count("*").alias("mult"))


def sample_estimate(sample: DataFrame, q: Queries, rows: int, on_empty: str = "zero") -> DataFrame:
    """Sample counts scaled up. ``on_empty='constant'`` gives a tenth for each equality and a third for each range."""
    size = sample.agg(F.coalesce(F.sum("mult"), F.lit(0))).first()[0]
    scaled = true_counts(sample, q).withColumn("est_rows", F.col("true_rows") * F.lit(rows / max(size, 1)))
    if on_empty == "constant":
        guess = [(int(i), float(rows * np.prod(np.where(b, np.where(lo == hi, 0.1, 1 / 3), 1.0)))) for i, b, lo, hi in zip(q.qid, q.bound, q.low, q.high)]
        magic = q_frame(sample.sparkSession, guess, "guess")
        scaled = scaled.join(magic, "qid").withColumn("est_rows", F.when(F.col("true_rows") > 0, F.col("est_rows")).otherwise(F.col("guess")))
    return scaled.select("qid", "est_rows")


def q_frame(spark: SparkSession, rows: list[tuple], *names: str) -> DataFrame:
    return spark.createDataFrame(rows, "qid long, " + ", ".join(f"{n} double" for n in names))


# --- histograms ---


def bucket_bounds(dic: Dictionary, attr: str, buckets: int, kind: str) -> list[int]:
    """First code of each bucket; equal width in codes, or equal depth in rows."""
    values = dic.values(attr)
    if kind == "width":
        return sorted({len(values) * k // buckets for k in range(buckets)})
    total, seen, out, k = sum(f for _, f in values), 0, [0], 1
    for code, (_, f) in enumerate(values):
        while k < buckets and seen >= total * k / buckets and code > out[-1]:
            out.append(code)
            k += 1
        while k < buckets and seen >= total * k / buckets:
            k += 1
        seen += f
    return sorted(set(out))


def histogram(dic: Dictionary, attr: str, buckets: int, kind: str = "width") -> list[tuple[int, int, int]]:
    """(first code, last code, rows) of each bucket."""
    starts = bucket_bounds(dic, attr, buckets, kind)
    ends = [s - 1 for s in starts[1:]] + [dic.cards[attr] - 1]
    values = dic.values(attr)
    return [(s, e, sum(f for _, f in values[s : e + 1])) for s, e in zip(starts, ends)]


def grid_histogram(tuples: DataFrame, dic: Dictionary, attrs: list[str], budget_bytes: int, kind: str = "width") -> tuple[DataFrame, dict[str, list[tuple[int, int]]]]:
    """Counts of a grid over some attributes with at most budget / 8 cells: (frame of b_<attr>, count; buckets by attribute)."""
    per = max(1, int((budget_bytes / 8) ** (1 / len(attrs)) + 1e-9))
    bounds = {a: [(s, e) for s, e, _ in histogram(dic, a, min(per, dic.cards[a]), kind)] for a in attrs}
    cols = [sum((F.col(a) >= s).cast("int") for s, _ in bounds[a][1:]) if len(bounds[a]) > 1 else F.lit(0) for a in attrs]
    return tuples.groupBy(*(c.cast("int").alias(f"b_{a}") for a, c in zip(attrs, cols))).agg(F.sum("mult").alias("count")), bounds


def grid_estimate(grid: DataFrame, bounds: dict[str, list[tuple[int, int]]], preds: DataFrame) -> DataFrame:
    """Each cell counts by the share of it that the query covers (uniform within buckets)."""
    spark = grid.sparkSession
    rows = [(a, k, s, e) for a, own in bounds.items() for k, (s, e) in enumerate(own)]
    buckets = F.broadcast(spark.createDataFrame(rows, "attr string, b int, s int, e int"))
    ends = F.broadcast(spark.createDataFrame([(a, own[-1][1]) for a, own in bounds.items()], "attr string, last int"))
    asked = preds.select("qid").distinct().join(ends, F.lit(True)).join(preds.select("qid", "attr", "lo", "hi"), ["qid", "attr"], "left").select("qid", "attr", F.coalesce("lo", F.lit(0)).alias("lo"), F.coalesce("hi", "last").alias("hi"))
    share = asked.join(buckets, "attr").withColumn("f", F.greatest(F.lit(0), F.least("hi", "e") - F.greatest("lo", "s") + 1) / (F.col("e") - F.col("s") + 1)).where("f > 0")
    out = preds.select("qid").distinct().join(grid, F.lit(True))  # bounded: a grid of a few KB
    for a in bounds:
        own = share.where(F.col("attr") == a).select("qid", F.col("b").alias(f"b_{a}"), F.col("f").alias(f"f_{a}"))
        out = out.join(own, ["qid", f"b_{a}"])
    product = F.col("count").cast("double")
    for a in bounds:
        product = product * F.col(f"f_{a}")
    found = out.groupBy("qid").agg(F.sum(product).alias("est_rows"))
    return preds.select("qid").distinct().join(found, "qid", "left").select("qid", F.coalesce("est_rows", F.lit(0.0)).alias("est_rows"))


def grid_for_sets(tuples: DataFrame, dic: Dictionary, preds: DataFrame, budget_bytes: int, kind: str = "width") -> DataFrame:
    """One grid an asked attribute set, the budget shared equally."""
    sets = preds.groupBy("qid").agg(F.concat_ws(",", F.sort_array(F.collect_list("attr"))).alias("attrs"))
    asked = [r["attrs"] for r in sets.select("attrs").distinct().orderBy("attrs").collect()]
    out = None
    for s in asked:
        own = preds.join(F.broadcast(sets.where(F.col("attrs") == s)), "qid", "left_semi")
        one = grid_estimate(*grid_histogram(tuples, dic, s.split(","), max(8, budget_bytes // len(asked)), kind), own)
        out = one if out is None else out.unionByName(one)
    return out


# --- multi-column statistics ---


def common_tuples(tuples: DataFrame, attrs: list[str], top: int) -> DataFrame:
    """The most frequent value combinations of some attributes."""
    return tuples.groupBy(*attrs).agg(F.sum("mult").alias("freq")).orderBy(F.col("freq").desc(), *attrs).limit(top)


def dependency_degree(tuples: DataFrame, a: str, b: str) -> Column | float:
    """Share of rows whose value of ``a`` goes with a single value of ``b``."""
    r = tuples.groupBy(a).agg(F.min(b).alias("x"), F.max(b).alias("y"), F.sum("mult").alias("n")).agg(F.sum(F.when(F.col("x") == F.col("y"), F.col("n")).otherwise(0)), F.sum("n")).first()
    return float(r[0]) / float(r[1]) if r[1] else 0.0


def multicolumn_estimate(tuples: DataFrame, dic: Dictionary, pair: tuple[str, str], preds: DataFrame, top: int = 50) -> DataFrame:
    """Two equality predicates: a common combination's own count, else P(a) (d + (1 - d) P(b)) with the dependency degree d."""
    a, b = pair
    n, d = float(dic.rows), dependency_degree(tuples, a, b)
    wide = preds.groupBy("qid").agg(F.max(F.when(F.col("attr") == a, F.col("lo"))).alias("va"), F.max(F.when(F.col("attr") == b, F.col("lo"))).alias("vb"))
    freq = lambda x, name: dic.frame.where(F.col("attr") == x).select(F.col("code").alias(f"v{name}"), F.col("freq").alias(f"f{name}"))
    common = F.broadcast(common_tuples(tuples, [a, b], top).select(F.col(a).alias("va"), F.col(b).alias("vb"), "freq"))
    joined = wide.join(freq(a, "a"), "va", "left").join(freq(b, "b"), "vb", "left").join(common, ["va", "vb"], "left")
    blend = F.col("fa") * (F.lit(d) + F.lit(1 - d) * F.col("fb") / F.lit(n))
    return joined.select("qid", F.coalesce(F.col("freq").cast("double"), blend, F.lit(0.0)).alias("est_rows"))


# --- Haar wavelets ---


def _levels(card: int) -> int:
    return max(0, math.ceil(math.log2(card))) if card > 1 else 0


def haar_coefficients(tuples: DataFrame, dic: Dictionary, attrs: list[str]) -> DataFrame:
    """(c_<attr>..., value): normalised coefficients of the standard decomposition.

    A one-dimensional basis function is numbered 0 (average) or 2**l + block for
    detail level l. A tuple touches one a level and dimension; its share of a
    coefficient is the product of signed norms.
    """
    out = tuples.groupBy(*attrs).agg(F.sum("mult").alias("mult"))
    value = F.col("mult").cast("double")
    for a in attrs:
        depth = _levels(dic.cards[a])
        size = float(1 << depth)
        parts = [F.struct(F.lit(0).alias("c"), F.lit(1 / math.sqrt(size)).alias("v"))]
        for level in range(depth):
            width = 1 << (depth - level)
            sign = F.when(F.shiftright(F.col(a), depth - level - 1).bitwiseAND(F.lit(1)) == 0, 1.0).otherwise(-1.0)
            parts.append(F.struct((F.lit(1 << level) + F.shiftright(F.col(a), depth - level)).cast("int").alias("c"), (sign / F.lit(math.sqrt(width))).alias("v")))
        out = out.withColumn("x", F.explode(F.array(*parts))).withColumn(f"c_{a}", F.col("x.c")).withColumn(f"v_{a}", F.col("x.v")).drop("x")
        value = value * F.col(f"v_{a}")
    return out.groupBy(*(f"c_{a}" for a in attrs)).agg(F.sum(value).alias("value"))


def haar_top(coefficients: DataFrame, attrs: list[str], keep: int) -> DataFrame:
    """The overall average and the largest magnitudes."""
    average = None
    for a in attrs:
        one = F.col(f"c_{a}") == 0
        average = one if average is None else average & one
    return coefficients.orderBy(average.desc(), F.round(F.abs("value"), 6).desc(), *(f"c_{a}" for a in attrs)).limit(keep)


def _interval_sum(c: Column, lo: Column, hi: Column, depth: int) -> Column:
    """Sum of a basis function over a closed interval of codes."""
    overlap = lambda s, e: F.greatest(F.lit(0), F.least(hi, e) - F.greatest(lo, s) + 1)
    level = F.floor(F.log2(F.greatest(c, F.lit(1)).cast("double")) + 1e-9).cast("int")
    width = F.pow(F.lit(2.0), F.lit(depth) - level).cast("int")
    start = (c - F.pow(F.lit(2.0), level).cast("int")) * width
    half = (width / 2).cast("int")
    detail = (overlap(start, start + half - 1) - overlap(start + half, start + width - 1)) / F.sqrt(width.cast("double"))
    return F.when(c == 0, overlap(F.lit(0), F.lit((1 << depth) - 1)) / F.lit(math.sqrt(1 << depth))).otherwise(detail)


def haar_estimate(kept: DataFrame, dic: Dictionary, attrs: list[str], preds: DataFrame) -> DataFrame:
    """Sum of kept coefficients times the query's sums of their basis functions; negative results become 0."""
    wide = preds.groupBy("qid").agg(*(F.coalesce(F.max(F.when(F.col("attr") == a, F.col("lo"))), F.lit(0)).alias(f"lo_{a}") for a in attrs), *(F.coalesce(F.max(F.when(F.col("attr") == a, F.col("hi"))), F.lit(dic.cards[a] - 1)).alias(f"hi_{a}") for a in attrs))
    value = F.col("value")
    for a in attrs:
        value = value * _interval_sum(F.col(f"c_{a}"), F.col(f"lo_{a}"), F.col(f"hi_{a}"), _levels(dic.cards[a]))
    return wide.join(F.broadcast(kept), F.lit(True)).groupBy("qid").agg(F.greatest(F.lit(0.0), F.sum(value)).alias("est_rows"))  # bounded: the budget


# --- Bayesian networks ---


def entropy_bins(frequencies: list[tuple[int, int]], most: int) -> list[int]:
    """First codes of bins: split the bin whose halves gain most weighted entropy, until ``most`` bins."""
    counts = np.array([f for _, f in sorted(frequencies)], float)
    starts = [0]

    def best(s: int, e: int) -> tuple[float, int]:
        own = counts[s:e]
        total = own.sum()
        if e - s < 2 or total == 0:
            return 0.0, -1
        left = np.cumsum(own)[:-1]
        p = left / total
        with np.errstate(divide="ignore", invalid="ignore"):
            h = -(np.where(p > 0, p * np.log2(p), 0) + np.where(p < 1, (1 - p) * np.log2(1 - p), 0))
        k = int(np.argmax(h))
        return float(h[k] * total), s + k + 1

    while len(starts) < most:
        ends = starts[1:] + [len(counts)]
        gain, at = max(best(s, e) for s, e in zip(starts, ends))
        if at < 0 or gain <= 0:
            break
        starts = sorted([*starts, at])
    return starts


def spanning_tree(mi: list[tuple[str, str, float]], attrs: list[str]) -> list[tuple[str, str]]:
    """(parent, child) edges of the maximum spanning tree, rooted at the first attribute."""
    inside, edges = [attrs[0]], []
    weight = {frozenset(x[:2]): x[2] for x in mi}
    while len(inside) < len(attrs):
        _, p, c = max((round(weight.get(frozenset((p, c)), 0.0), 9), p, c) for p in inside for c in attrs if c not in inside)
        edges.append((p, c))
        inside.append(c)
    return edges


class BayesNet:
    """Discrete network over (possibly binned) attributes, inference by elimination along its order.

    ``tree``: maximum spanning tree on mutual information. ``greedy``: each
    attribute takes up to two earlier parents while the description length falls.
    """

    def __init__(self, attrs: list[str], cards: dict[str, int], bins: dict[str, list[int]], parents: dict[str, tuple[str, ...]], tables: dict[str, np.ndarray], rows: int) -> None:
        self.attrs, self.cards, self.bins, self.parents, self.tables, self.rows = attrs, cards, bins, parents, tables, rows

    @classmethod
    def fit(cls, tuples: DataFrame, dic: Dictionary, structure: str = "tree", most_bins: int = 64, smooth: float = 0.0) -> "BayesNet":
        bins = {}
        for a in dic.attrs:
            bins[a] = list(range(dic.cards[a])) if dic.cards[a] <= most_bins else entropy_bins([(k, f) for k, (_, f) in enumerate(dic.values(a))], most_bins)
        binned = tuples.select(*((sum((F.col(a) >= s).cast("int") for s in bins[a][1:]) if 1 < len(bins[a]) < dic.cards[a] else F.col(a) if len(bins[a]) > 1 else F.lit(0)).alias(a) for a in dic.attrs), "mult").groupBy(*dic.attrs).agg(F.sum("mult").alias("mult")).persist()
        n = {a: len(bins[a]) for a in dic.attrs}
        pairs = [(a, b) for k, a in enumerate(dic.attrs) for b in dic.attrs[k + 1 :]]
        counts = cls._pair_counts(binned, pairs, n)
        parents: dict[str, tuple[str, ...]] = {dic.attrs[0]: ()}
        order = [dic.attrs[0]]
        mi = [(a, b, _mi(counts[a, b])) for a, b in pairs]
        if structure == "tree":
            for p, c in spanning_tree(mi, dic.attrs):
                parents[c] = (p,)
                order.append(c)
        else:
            strength = {frozenset((a, b)): v for a, b, v in mi}
            rows = counts[pairs[0]].sum() if pairs else dic.rows
            left = [a for a in dic.attrs if a not in order]
            while left:
                c = max(left, key=lambda x: (max(strength[frozenset((x, p))] for p in order), x))
                ranked = sorted(order, key=lambda p: -strength[frozenset((c, p))])[:4]
                options: list[tuple[str, ...]] = [(), *((p,) for p in ranked), *((p, q) for k, p in enumerate(ranked) for q in ranked[k + 1 :])]
                tables = cls._tables(binned, c, options, n)
                cost = {o: _description(t, rows) for o, t in tables.items()}
                parents[c] = min(options, key=lambda o: cost[o])
                order.append(c)
                left.remove(c)
        tables = {}
        for a in order:
            t = cls._tables(binned, a, [parents[a]], n)[parents[a]] + smooth
            total = t.sum(axis=-1, keepdims=True)
            tables[a] = np.divide(t, total, out=np.zeros_like(t), where=total > 0)
        binned.unpersist()
        return cls(order, dict(dic.cards), bins, parents, tables, dic.rows)

    @staticmethod
    def _pair_counts(binned: DataFrame, pairs: list[tuple[str, str]], n: dict[str, int]) -> dict[tuple[str, str], np.ndarray]:
        out = {p: np.zeros((n[p[0]], n[p[1]])) for p in pairs}
        if not pairs:
            return out
        cells = F.array(*(F.struct(F.lit(k).alias("p"), F.col(a).alias("x"), F.col(b).alias("y")) for k, (a, b) in enumerate(pairs)))
        for r in binned.select("mult", F.explode(cells).alias("c")).groupBy("c.p", "c.x", "c.y").agg(F.sum("mult").alias("m")).collect():  # bounded: pairs x bins squared
            out[pairs[r["p"]]][r["x"], r["y"]] = r["m"]
        return out

    @staticmethod
    def _tables(binned: DataFrame, a: str, options: list[tuple[str, ...]], n: dict[str, int]) -> dict[tuple[str, ...], np.ndarray]:
        """Counts of an attribute with each of some parent sets, up to two parents, in one pass."""
        out = {o: np.zeros([n[x] for x in (*o, a)]) for o in options}
        at = lambda o, k: F.col(o[k]) if k < len(o) else F.lit(0)
        cells = F.array(*(F.struct(F.lit(k).alias("o"), at(o, 0).alias("x"), at(o, 1).alias("y"), F.col(a).alias("z")) for k, o in enumerate(options)))
        for r in binned.select("mult", F.explode(cells).alias("c")).groupBy("c.o", "c.x", "c.y", "c.z").agg(F.sum("mult").alias("m")).collect():  # bounded: bins to the power of three at most, an option
            o = options[r["o"]]
            out[o][(*(r["x"], r["y"])[: len(o)], r["z"])] = r["m"]
        return out

    def evidence(self, attr: str, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """queries x bins: share of each bin inside the interval (uniform within bins)."""
        s = np.array(self.bins[attr])
        e = np.append(s[1:] - 1, self.cards[attr] - 1)
        return np.maximum(0, np.minimum(hi[:, None], e) - np.maximum(lo[:, None], s) + 1) / (e - s + 1)

    def estimate(self, q: Queries) -> np.ndarray:
        """Rows of each query: variables are summed out in reverse order, queries side by side."""
        position = {a: k for k, a in enumerate(q.attrs)}
        evidence = {a: self.evidence(a, q.low[:, position[a]], q.high[:, position[a]]) for a in self.attrs}
        letters = {a: chr(ord("a") + k) for k, a in enumerate(self.attrs)}
        out = np.empty(len(q))
        step = 512
        for lo in range(0, len(q), step):
            rows = slice(lo, lo + step)
            factors = [("".join(letters[x] for x in (*self.parents[a], a)), self.tables[a]) for a in self.attrs]
            factors += [("Z" + letters[a], evidence[a][rows]) for a in self.attrs]
            for a in reversed(self.attrs):
                x = letters[a]
                near = [f for f in factors if x in f[0]]
                rest = [f for f in factors if x not in f[0]]
                keep = "".join(sorted(set("".join(f[0] for f in near)) - {x}))
                factors = [*rest, (keep, np.einsum(",".join(f[0] for f in near) + "->" + keep, *(f[1] for f in near), optimize=True))]
            p = np.ones(len(out[rows]))
            for name, value in factors:
                p = p * value if name in ("Z", "") else p
            out[rows] = p
        return out * self.rows

    def size_bytes(self) -> int:
        return 8 * sum(t.size for t in self.tables.values()) + 4 * sum(len(b) for b in self.bins.values())


def _mi(counts: np.ndarray) -> float:
    p = counts / max(counts.sum(), 1)
    with np.errstate(divide="ignore", invalid="ignore"):
        return float(np.nansum(np.where(p > 0, p * np.log2(p / (p.sum(1, keepdims=True) * p.sum(0, keepdims=True))), 0)))


def _description(t: np.ndarray, rows: float) -> float:
    """Code length of an attribute given its parents, with half a log of the rows for each free number."""
    total = t.sum(axis=-1, keepdims=True)
    with np.errstate(divide="ignore", invalid="ignore"):
        fit = -np.nansum(np.where(t > 0, t * np.log2(t / total), 0))
    return float(fit + 0.5 * math.log2(max(rows, 2)) * (t.shape[-1] - 1) * np.prod(t.shape[:-1]))


# --- the engine's own estimate ---


def catalyst_rows(frame: DataFrame) -> int | None:
    """Rows that the optimizer expects of a plan, if it has statistics."""
    found = frame._jdf.queryExecution().optimizedPlan().stats().rowCount()
    return int(str(found.get())) if found.isDefined() else None
