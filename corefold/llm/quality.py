"""Quality rules with risk-controlled cutoffs (operator 8). DataFrame functions only.

Measures are taken once from each whole text, without a shuffle. Two rules are fixed
(`base_failed`). The others are cutoffs on further measures, chosen and certified on the
labelled documents (`labels.quality`) that pass the fixed ones, in each stratum (language):

* One labelled document in TUNE (by a hash of its id) only serves to propose: for each
  measure the mildest cutoff of nearly the most worth among quantiles of good documents
  and one beyond, and the order of the measures, those of more worth first.
* The others, never looked at before, certify. The bound is on what all chosen cutoffs of
  a stratum reject together: a prefix of the order that rejects k of n good documents is
  certified if P(Bin(n, risk) <= k) <= error / strata, exactly. Prefixes are tested in
  turn and the first that fails ends it (a fixed sequence needs no further correction),
  strata are corrected for by Bonferroni. So, with confidence 1 - error, no stratum loses
  more than a share of `risk` of its good documents to the cutoffs.

A stratum needs n >= log(error / strata) / log(1 - risk) good documents that certify (217
for four strata, so about 290 with a label); with fewer it rejects nothing beyond the base
rules.

Null texts have no words (and fail the base rules). Null languages are a stratum of
their own. Repeated rows are judged each. Labels that are null, or whose doc_id is
null or unknown, take no part; several labels of one document count as the worst.
Columns of the input stay together in one struct, so none can clash with a measure.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from corefold.llm.common import text_or_empty, written

WHITE = "[ \\t-\\r]+"
#: Documents measured with fewer words fail.
LEAST_WORDS = 10
#: Bound on the share of good documents that the cutoffs of a stratum reject, and on the chance that any stratum exceeds it.
RISK, ERROR = 0.02, 0.05
#: One labelled document in so many proposes cutoffs; the others certify them.
TUNE = 4
#: Shares of good documents that a proposed cutoff leaves.
LEVELS = (0.9, 0.95, 0.98, 0.99, 0.995, 0.998, 0.999, 1.0)
#: Bad documents that a cutoff must catch for each good one that it rejects; share of the best worth that a milder cutoff may have.
COST, NEARLY = 20, 0.8


def measure(docs: DataFrame, window: int = 5) -> DataFrame:
    """row (all columns of docs), and n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_shouts, n_distinct."""
    out = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), text_or_empty().alias("_t"))
    out = out.withColumn("_w", F.array_remove(F.split("_t", WHITE), ""))
    out = out.withColumn("_n", F.size("_w"))
    grams = [F.slice("_w", i + 1, F.greatest(F.col("_n") - (window - 1), F.lit(0))) for i in range(window)]
    zipped = F.arrays_zip(*[g.alias(f"w{i}") for i, g in enumerate(grams)])
    out = out.withColumn("_g", F.transform(zipped, lambda z: F.xxhash64(z)))
    # only texts with a repeated window need its places
    out = out.withColumn("_r", F.size(F.array_distinct("_g")) < F.size("_g"))
    out = out.withColumn("_s", F.when(F.col("_r"), F.sort_array(F.transform("_g", lambda g, i: F.struct(g.alias("g"), i.alias("i"))))))
    m = F.size("_s")
    same = F.zip_with(F.slice("_s", F.lit(1), m - 1), F.slice("_s", F.lit(2), m - 1), lambda a, b: F.when(a["g"] == b["g"], F.array(a["i"], b["i"])))
    out = out.withColumn("_p", F.when(F.col("_r"), F.sort_array(F.array_distinct(F.flatten(F.filter(same, lambda x: x.isNotNull()))))))
    q = F.size("_p")
    steps = F.zip_with(F.slice("_p", F.lit(1), q - 1), F.slice("_p", F.lit(2), q - 1), lambda a, b: F.least(F.lit(window), b - a))
    repeat = F.when(F.col("_r"), F.aggregate(steps, F.lit(window), lambda a, x: a + x)).otherwise(0)
    lines = F.filter(F.split("_t", "\\n"), lambda x: x.rlike("[^ \\t-\\r]"))
    out = out.withColumn("_l", lines)
    joined = F.array_join("_w", "")
    return out.select(
        "row",
        F.col("_n").cast("long").alias("n_words"),
        F.char_length(joined).cast("long").alias("word_chars"),
        (F.octet_length("_t") - F.octet_length(F.regexp_replace("_t", "[#*$%&|<>]+", ""))).cast("long").alias("n_symbols"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        repeat.cast("long").alias("n_repeat_words"),
        F.size("_l").cast("long").alias("n_lines"),
        (F.octet_length("_t") - F.octet_length(F.regexp_replace("_t", "!+", ""))).cast("long").alias("n_shouts"),
        F.size(F.array_distinct("_w")).cast("long").alias("n_distinct"),
    )


def rates() -> dict[str, Column]:
    """Measures to cut on, all "more is worse" and 0 where there is no word."""
    words = F.greatest(F.col("n_words"), F.lit(1))
    return {
        "symbols": F.col("n_symbols") / words,
        "shouts": F.col("n_shouts") / words,
        "dup_lines": F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1)),
        "repeats": F.col("n_repeat_words") / words,
        "long_words": F.col("word_chars") / words,
        "short_words": -F.col("word_chars") / words,
    }


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(Bin(n, p) <= k), summed term by term in logarithms, at any size."""
    import math

    step = math.log(p) - math.log1p(-p)
    start = F.struct(F.lit(0.0).alias("total"), (n * math.log1p(-p)).alias("term"))
    terms = F.aggregate(
        F.sequence(F.lit(0).cast("long"), k.cast("long")),
        start,
        lambda acc, i: F.struct((acc["total"] + F.exp(acc["term"])).alias("total"), (acc["term"] + F.log((n - i) / (i + 1)) + step).alias("term")),
        lambda acc: F.least(acc["total"], F.lit(1.0)),
    )
    return F.when((n <= 0) | (k >= n), 1.0).otherwise(terms)


def base_failed() -> Column:
    return (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def holdout(measured: DataFrame, labels: DataFrame, stratum: str) -> DataFrame:
    """stratum, good, tune, and one column for each measure, of the labelled documents that pass the base rules."""
    worst = labels.filter("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy(F.col("doc_id").cast("long").alias("_id")).agg((F.min("quality") == 1).alias("good"))
    own = measured.filter(F.col("row.doc_id").isNotNull() & ~base_failed())
    own = own.select(F.col("row.doc_id").cast("long").alias("_id"), F.col(f"row.`{stratum}`").alias("stratum"), *[c.alias(name) for name, c in rates().items()])
    return own.join(worst, "_id").withColumn("tune", F.pmod(F.xxhash64("_id"), F.lit(TUNE)) == 0)


def proposed(held: DataFrame) -> DataFrame:
    """stratum, rule, cutoff, place: at most one cutoff for each rule, those of more worth first; from the tuning documents."""
    names = list(rates())
    tuning = held.filter("tune")
    quantiles = [F.percentile(F.when(F.col("good"), F.col(n)), F.array(*map(F.lit, LEVELS))).alias(n) for n in names]  # exact: the same in every run
    # and one that is milder than all seen: as far beyond the last as that is beyond the first
    milder = [F.array_distinct(F.concat(n, F.array(2 * F.element_at(n, -1) - F.element_at(n, 1)))).alias(n) for n in names]
    grid = _few(tuning.groupBy("stratum").agg(*quantiles).select("stratum", *milder)).alias("g")
    same = F.col("t.stratum").eqNullSafe(F.col("g.stratum"))

    def cuts(n: str) -> Column:
        return F.transform(f"g.{n}", lambda c: F.struct(F.lit(n).alias("rule"), c.alias("cutoff"), (F.col(f"t.{n}") > c).alias("hit")))

    tried = [cuts(n) for n in names]
    hits = tuning.alias("t").join(grid, same).select("t.stratum", "t.good", F.explode(F.concat(*[F.coalesce(t, F.array().cast("array<struct<rule:string,cutoff:double,hit:boolean>>")) for t in tried])).alias("x"))
    counts = hits.filter("x.hit").groupBy("stratum", "x.rule", "x.cutoff").agg(F.count_if("good").alias("k"), F.count_if(~F.col("good")).alias("caught"))
    worth = F.col("caught") - COST * F.col("k")
    one = Window.partitionBy("stratum", "rule")
    worthy = counts.withColumn("worth", worth).filter("worth > 0").withColumn("best", F.max("worth").over(one)).filter(F.col("worth") >= NEARLY * F.col("best"))
    chosen = worthy.withColumn("o", F.row_number().over(one.orderBy(F.desc("cutoff")))).filter("o = 1")
    return chosen.select("stratum", "rule", "cutoff", F.row_number().over(Window.partitionBy("stratum").orderBy(F.desc("worth"), "rule")).alias("place"))


def certified(held: DataFrame, chosen: DataFrame, risk: float = RISK, error: float = ERROR) -> DataFrame:
    """chosen with k, n, p (of each prefix), level, and whether it is certified; from the documents that certify."""
    chosen = _few(chosen)
    by_stratum = _few(chosen.groupBy("stratum").agg(F.map_from_entries(F.collect_list(F.struct("rule", F.struct("cutoff", "place")))).alias("own")))  # at most one entry for each measure
    good = held.filter("good AND NOT tune").alias("t").join(by_stratum.alias("s"), F.col("t.stratum").eqNullSafe(F.col("s.stratum")))
    rule = lambda n: F.try_element_at("s.own", F.lit(n))
    first = F.least(*[F.when(F.col(f"t.{n}") > rule(n)["cutoff"], rule(n)["place"]) for n in rates()])
    counts = good.groupBy(F.col("t.stratum").alias("stratum"), F.coalesce(first, F.lit(0)).alias("first")).agg(F.count("*").alias("m"))
    counts = counts.groupBy("stratum").agg(F.sum("m").alias("n"), F.collect_list(F.struct("first", "m")).alias("firsts"))  # at most one for each measure
    k = F.aggregate("firsts", F.lit(0).cast("long"), lambda a, x: a + F.when((x["first"] > 0) & (x["first"] <= F.col("place")), x["m"]).otherwise(0))
    tested = chosen.alias("c").join(counts.alias("n"), F.col("c.stratum").eqNullSafe(F.col("n.stratum"))).select("c.*", k.alias("k"), "n.n")
    level = error / max(by_stratum.count(), 1)
    tested = tested.withColumn("p", binomial_tail(F.col("k"), F.col("n"), risk))
    so_far = Window.partitionBy("stratum").orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    return tested.withColumn("level", F.lit(level)).withColumn("certified", F.max("p").over(so_far) <= level)


def cutoffs(measured: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = RISK, error: float = ERROR) -> DataFrame:
    """stratum, rule, cutoff, k, n, p: the certified ones (reject what is above the cutoff), at most one for each rule and stratum."""
    held = written(holdout(measured, labels, stratum))
    return certified(held, proposed(held), risk, error).filter("certified").select("stratum", "rule", "cutoff", "place", "k", "n", "p")


def _few(df: DataFrame, most: int = 10_000) -> DataFrame:
    """Broadcast a table by strata if it is as small as strata should be; else leave the join to Spark."""
    df = written(df)
    return F.broadcast(df) if df.count() <= most else df


def judge(docs: DataFrame, labels: DataFrame, stratum: str = "lang", risk: float = RISK, error: float = ERROR, window: int = 5, columns: list[str] | None = None) -> DataFrame:
    """row (a struct of `columns` of docs, by default all), the measures, base_failed, failed_rules (of the certified cutoffs), kept."""
    measured = measure(docs, window)
    if columns is not None:
        kept = dict.fromkeys([*columns, "doc_id", stratum])
        measured = measured.withColumn("row", F.struct(*[F.col(f"row.`{c}`") for c in kept]))
    measured = written(measured)
    limits = cutoffs(measured, labels, stratum, risk, error).groupBy("stratum").agg(F.map_from_entries(F.collect_list(F.struct("rule", "cutoff"))).alias("limits"))
    out = measured.alias("d").join(_few(limits).alias("s"), F.col(f"d.row.`{stratum}`").eqNullSafe(F.col("s.stratum")), "left").select("d.*", "s.limits")
    failed = F.array_compact(F.array(*[F.when(value > F.coalesce(F.try_element_at("limits", F.lit(name)), F.lit(float("inf"))), F.lit(name)) for name, value in rates().items()]))
    out = out.withColumn("base_failed", base_failed()).withColumn("failed_rules", failed).drop("limits")
    return out.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))
