"""Query workloads: test logs by attribute sets, training queries from data, and augmentation of a log.

Queries are long rows (qid, attr, lo, hi) in codes. All draws are md5 uniforms,
so a workload depends on its seed alone.
"""

from __future__ import annotations

from itertools import combinations
from math import comb

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from selweave.functions.draws import uniform

from .relation import Dictionary


def _cards(spark: SparkSession, dic: Dictionary) -> DataFrame:
    """(attr, no, card), one row an attribute."""
    return F.broadcast(spark.createDataFrame([(a, k, dic.cards[a]) for k, a in enumerate(dic.attrs)], "attr string, no int, card int"))


def ladder(tuples: DataFrame, attrs: list[str], size: Column, seed: int, digits: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """Tuples laid end to end in md5 order: (bucket, tuple's ``_start`` and ``_size``), (bucket, its start and stop), and the whole length.

    A bucket is a prefix of the md5 text, long enough that one holds some thousands
    of tuples; only the buckets' sums are ordered as a whole, so no task sees all tuples.
    """
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), *(F.col(a).cast("string") for a in attrs)))
    if digits is None:
        digits = 1
        while 16**digits * 4096 < tuples.count():
            digits += 1
    keyed = tuples.select(*attrs, size.cast("long").alias("_size"), key.alias("_key")).withColumn("bucket", F.substring("_key", 1, digits))
    sums = keyed.groupBy("bucket").agg(F.sum("_size").alias("total"))
    upto = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)  # one row a bucket
    bounds = sums.withColumn("stop", F.sum("total").over(upto)).select("bucket", (F.col("stop") - F.col("total")).alias("base"), "stop").persist()
    inside = Window.partitionBy("bucket").orderBy("_key").rowsBetween(Window.unboundedPreceding, 0)
    placed = keyed.withColumn("up", F.sum("_size").over(inside)).join(bounds.select("bucket", "base"), "bucket")
    whole = bounds.agg(F.max("stop")).first()[0] or 0
    return placed.select("bucket", *attrs, (F.col("base") + F.col("up") - F.col("_size")).alias("_start"), "_size"), bounds, int(whole)


def pick(draws: DataFrame, placed: DataFrame, bounds: DataFrame, whole: int, cells: int = 4096) -> DataFrame:
    """Draws (``at``) with the tuple that each falls on, by equal keys alone: first the cell of the place, then the bucket."""
    cell = lambda x: F.floor(x * F.lit(cells) / F.lit(max(1, whole)))
    spread = bounds.where("stop > base").select("bucket", "base", "stop", F.explode(F.sequence(cell(F.col("base")), cell(F.col("stop") - 1))).alias("cell"))
    routed = draws.withColumn("cell", cell(F.col("at"))).join(spread, "cell").where("at >= base and at < stop").drop("cell", "base", "stop")
    return routed.join(placed, "bucket").where("at >= _start and at < _start + _size").drop("bucket", "_start", "_size")


def single_predicate(dic: Dictionary) -> DataFrame:
    """Every (attribute, value) as a query."""
    order = Window.orderBy("attr", "code")  # at most one row a dictionary entry
    return dic.frame.select((F.row_number().over(order) - 1).cast("long").alias("qid"), "attr", F.col("code").alias("lo"), F.col("code").alias("hi"))


def attribute_sets(attrs: list[str], total: int, most: int | None = None) -> list[tuple[int, str, int]]:
    """(k, comma-joined attributes, quota): each predicate count gets an equal share, split equally over its sets."""
    most = most or len(attrs)
    out = []
    for k in range(1, most + 1):
        share, sets = total // most, comb(len(attrs), k)
        for n, s in enumerate(combinations(sorted(attrs), k)):
            out.append((k, ",".join(s), share // sets + (n < share % sets)))
    return out


def combo_workload(spark: SparkSession, dic: Dictionary, total: int = 10_000, seed: int = 42, values: str = "uniform", tuples: DataFrame | None = None, tries: int = 3) -> DataFrame:
    """(qid, k, attrs, attr, lo, hi): quotas over all attribute sets, values without replacement.

    ``uniform`` draws values from the domains, ``anchored`` copies them from an
    md5-chosen tuple (never empty). Quotas beyond what a set holds, or what
    ``tries`` draws a query find, fall short; compare with ``attribute_sets``.
    """
    sets = spark.createDataFrame(attribute_sets(dic.attrs, total), "k int, attrs string, quota int")
    drawn = F.broadcast(sets).where("quota > 0").select("k", "attrs", "quota", F.explode(F.sequence(F.lit(1), F.col("quota") * tries)).alias("draw"))
    if values == "anchored":
        placed, bounds, n = ladder(tuples, list(dic.attrs), F.lit(1), seed)
        picked = pick(drawn.withColumn("at", F.floor(uniform(seed, F.col("attrs"), F.col("draw")) * n).cast("long")), placed, bounds, n)
        cells = F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("code")) for a in dic.attrs))
        long = picked.select("k", "attrs", "quota", "draw", F.explode(F.filter(cells, lambda x: F.array_contains(F.split("attrs", ","), x["attr"]))).alias("x")).select("k", "attrs", "quota", "draw", "x.attr", "x.code")
    else:
        long = drawn.select("k", "attrs", "quota", "draw", F.explode(F.split("attrs", ",")).alias("attr")).join(_cards(spark, dic), "attr")
        long = long.withColumn("code", F.floor(uniform(seed, F.col("attrs"), F.col("draw"), F.col("attr")) * F.col("card")).cast("int"))
    whole = long.groupBy("k", "attrs", "quota", "draw").agg(F.concat_ws(",", F.transform(F.sort_array(F.collect_list(F.struct("attr", "code"))), lambda x: x["code"].cast("string"))).alias("cell"))
    first = whole.groupBy("k", "attrs", "quota", "cell").agg(F.min("draw").alias("draw"))
    kept = first.withColumn("place", F.row_number().over(Window.partitionBy("attrs").orderBy("draw"))).where("place <= quota")
    ids = kept.withColumn("qid", (F.row_number().over(Window.orderBy("k", "attrs", "place")) - 1).cast("long"))  # bounded: a workload
    pairs = F.arrays_zip(F.split("attrs", ",").alias("attr"), F.split("cell", ",").alias("code"))
    return ids.select("qid", "k", "attrs", F.explode(pairs).alias("x")).select("qid", "k", "attrs", F.col("x.attr").alias("attr"), F.col("x.code").cast("int").alias("lo"), F.col("x.code").cast("int").alias("hi"))


def range_workload(spark: SparkSession, dic: Dictionary, attrs: list[str], total: int, seed: int = 7) -> DataFrame:
    """(qid, k, attr, lo, hi): up to len(attrs) intervals a query; both ends drawn from the domain."""
    rows = [(q, 1 + q * len(attrs) // total) for q in range(total)]
    base = spark.createDataFrame(rows, "qid long, k int")
    own = base.select("qid", "k", F.explode(F.array(*map(F.lit, attrs))).alias("attr")).join(_cards(spark, dic), "attr")
    ranked = own.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy(uniform(seed, F.col("qid"), F.col("attr"), "pick"), "attr"))).where("r <= k")
    a, b = (F.floor(uniform(seed, F.col("qid"), F.col("attr"), x) * F.col("card")).cast("int") for x in ("a", "b"))
    return ranked.select("qid", "k", "attr", F.least(a, b).alias("lo"), F.greatest(a, b).alias("hi"))


def random_training(spark: SparkSession, dic: Dictionary, tuples: DataFrame, budget: int = 10_000, seed: int = 42) -> DataFrame:
    """(qid, attr, lo, hi): first all one-predicate queries (the most frequent values if they exceed the budget),
    then random attribute subsets with the values of a tuple drawn by its frequency; distinct queries only."""
    singles = dic.frame.select("attr", "code", "freq")
    n_single = sum(dic.cards.values())
    if n_single > budget:
        singles = singles.orderBy(F.col("freq").desc(), "attr", "code").limit(budget)
    m, rest = len(dic.attrs), max(0, budget - n_single)
    first = singles.select(F.concat("attr", F.lit("="), F.col("code").cast("string")).alias("canon"), F.lit(0).alias("draw"))
    placed, bounds, total = ladder(tuples, list(dic.attrs), F.col("mult"), seed)
    draws = spark.range(1, rest * 2 + 1).withColumnRenamed("id", "draw")
    draws = draws.withColumn("at", F.floor(uniform(seed, F.col("draw"), "tuple") * total).cast("long")).withColumn("_take", (2 + F.floor(uniform(seed, F.col("draw"), "size") * (m - 1))).cast("int"))
    hit = pick(draws, placed, bounds, total)
    chosen = F.slice(F.array_sort(F.array(*(F.struct(uniform(seed, F.col("draw"), a).alias("u"), F.lit(a).alias("attr"), F.col(a).alias("code")) for a in dic.attrs))), 1, F.col("_take"))
    more = hit.select("draw", F.concat_ws(",", F.sort_array(F.transform(chosen, lambda x: F.concat(x["attr"], F.lit("="), x["code"].cast("string"))))).alias("canon"))
    distinct = more.groupBy("canon").agg(F.min("draw").alias("draw")).orderBy("draw").limit(rest)
    every = first.unionByName(distinct.select("canon", F.col("draw").cast("int").alias("draw")))
    ids = every.withColumn("qid", (F.row_number().over(Window.orderBy("draw", "canon")) - 1).cast("long"))
    return _from_canon(ids)


def naive_training(spark: SparkSession, dic: Dictionary, budget: int = 10_000, seed: int = 42) -> DataFrame:
    """(qid, attr, lo, hi): random attribute subsets with values drawn evenly from the domains, so most are empty; the control of ``random_training``."""
    m = len(dic.attrs)
    draws = spark.range(budget).withColumnRenamed("id", "qid").withColumn("k", (1 + F.floor(uniform(seed, F.col("qid"), "size") * m)).cast("int"))
    each = draws.select("qid", "k", F.explode(F.array(*map(F.lit, dic.attrs))).alias("attr")).join(_cards(spark, dic), "attr")
    place = Window.partitionBy("qid").orderBy(uniform(seed, F.col("qid"), F.col("attr"), "pick"), "attr")
    code = F.floor(uniform(seed, F.col("qid"), F.col("attr"), "value") * F.col("card")).cast("int")
    return each.withColumn("r", F.row_number().over(place)).where("r <= k").select("qid", "attr", code.alias("lo"), code.alias("hi"))


def _from_canon(ids: DataFrame) -> DataFrame:
    parts = ids.select("qid", F.explode(F.split("canon", ",")).alias("x"))
    code = F.element_at(F.split("x", "="), -1).cast("int")
    return parts.select("qid", F.element_at(F.split("x", "="), 1).alias("attr"), code.alias("lo"), code.alias("hi"))


# --- a log's own distributions, and augmentation by them ---


def attribute_weights(preds: DataFrame, dic: Dictionary) -> DataFrame:
    """(attr, weight): share of predicates on each attribute."""
    counts = preds.groupBy("attr").agg(F.count("*").alias("c"))
    total = preds.count()
    return _cards(preds.sparkSession, dic).join(counts, "attr", "left").select("attr", (F.coalesce("c", F.lit(0)) / F.lit(max(total, 1))).alias("weight"))


def value_weights(preds: DataFrame, dic: Dictionary) -> DataFrame:
    """(attr, code, weight): occurrences in the log, one for values that it lacks, normalised by attribute."""
    counts = preds.groupBy("attr", F.col("lo").alias("code")).agg(F.count("*").alias("c"))
    raised = dic.frame.select("attr", "code").join(counts, ["attr", "code"], "left").withColumn("c", F.greatest(F.coalesce("c", F.lit(1)), F.lit(1)))
    return raised.withColumn("weight", F.col("c") / F.sum("c").over(Window.partitionBy("attr"))).select("attr", "code", "weight")


def predicate_count_distribution(preds: DataFrame) -> DataFrame:
    """(k, n, share) of predicate counts."""
    ks = preds.groupBy("qid").agg(F.count("*").cast("int").alias("k")).groupBy("k").agg(F.count("*").alias("n"))
    return ks.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))


def augment(preds: DataFrame, dic: Dictionary, target: int, seed: int = 42) -> DataFrame:
    """(qid, attr, lo, hi, in_workload): the log and new queries drawn from its weights.

    A new query takes its predicate count from the log's histogram, attributes
    without replacement by an exponential race on their weights, and values by
    inverse transform of theirs. New queries are distinct from the log and from
    each other; fewer come back if ``3 * target`` draws don't hold enough.
    """
    spark = preds.sparkSession
    own = preds.select("qid", "attr", "lo", "hi").withColumn("in_workload", F.lit(True))
    log = preds.groupBy("qid").agg(F.concat_ws(",", F.sort_array(F.collect_list(F.concat("attr", F.lit("="), F.col("lo").cast("string"))))).alias("canon"))
    n_log = log.count()
    want = max(0, target - n_log)
    if not want:
        return own
    steps = Window.orderBy("k").rowsBetween(Window.unboundedPreceding, 0)
    histogram = F.broadcast(predicate_count_distribution(preds).withColumn("up", F.sum("share").over(steps)))  # one row a count
    draws = spark.range(1, 3 * want + 1).withColumnRenamed("id", "draw").withColumn("u", uniform(seed, F.col("draw"), "k"))
    sized = draws.join(histogram, (F.col("u") >= F.col("up") - F.col("share")) & (F.col("u") < F.col("up"))).select("draw", "k")
    raced = sized.join(F.broadcast(attribute_weights(preds, dic).where("weight > 0")), F.lit(True))
    key = -F.log(F.greatest(uniform(seed, F.col("draw"), F.col("attr"), "race"), F.lit(1e-12))) / F.col("weight")
    picked = raced.withColumn("r", F.row_number().over(Window.partitionBy("draw").orderBy(key, "attr"))).where("r <= k").select("draw", "attr")
    ladder = value_weights(preds, dic).withColumn("up", F.sum("weight").over(Window.partitionBy("attr").orderBy("code").rowsBetween(Window.unboundedPreceding, 0)))
    valued = picked.withColumn("v", uniform(seed, F.col("draw"), F.col("attr"), "value")).join(ladder, "attr").where((F.col("v") >= F.col("up") - F.col("weight")) & (F.col("v") < F.col("up")))
    new = valued.groupBy("draw").agg(F.concat_ws(",", F.sort_array(F.collect_list(F.concat("attr", F.lit("="), F.col("code").cast("string"))))).alias("canon"))
    fresh = new.join(log, "canon", "left_anti").groupBy("canon").agg(F.min("draw").alias("draw")).orderBy("draw").limit(want)
    last = preds.agg(F.max("qid")).first()[0]
    ids = fresh.withColumn("qid", (F.row_number().over(Window.orderBy("draw")) + F.lit(int(last))).cast("long"))
    return own.unionByName(_from_canon(ids).withColumn("in_workload", F.lit(False)))


def query_weights(augmented: DataFrame) -> DataFrame:
    """(qid, in_workload, weight): one for the log's queries, size(log) / size(all) for new ones."""
    ids = augmented.select("qid", "in_workload").distinct()
    n, own = ids.agg(F.count("*"), F.sum(F.col("in_workload").cast("int"))).first()
    return ids.withColumn("weight", F.when(F.col("in_workload"), F.lit(1.0)).otherwise(F.lit(float(own) / max(n, 1))))


def dependency_workload(preds: DataFrame, pair: tuple[str, str]) -> DataFrame:
    """Queries that bind both sides of a dependency."""
    both = preds.where(F.col("attr").isin(*pair)).groupBy("qid").agg(F.count_distinct("attr").alias("n")).where("n = 2")
    return preds.join(both.select("qid"), "qid", "left_semi")
