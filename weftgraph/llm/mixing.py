"""Mixing sources to target weights by Poisson replication.

Each source has a mean repetition rate, its target share of the output over
its share of the input. Each document gets a uniform number from a hash of a
seed and its id, and the count at which the Poisson distribution function of
its source's rate first reaches that number: found by halving in a table around
the rate. Documents are exploded by their
count and put into the global order of another hash. The same seed gives the
same mixture on any cluster.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from weftgraph.plans.common import checked_broadcast, cut

SEED = 20240101


def hash_uniform(*parts: Column) -> Column:
    """A number in (0, 1) from 52 bits of an MD5 of the parts as text, joined by a colon."""
    key = F.concat_ws(":", *[F.coalesce(p.cast("string"), F.lit("null")) for p in parts])
    return (F.conv(F.substring(F.md5(key), 1, 13), 16, 10).cast("double") + 0.5) / float(1 << 52)


def source_rates(docs: DataFrame, targets: dict[str, float] | None = None, size: float | None = None, source_col: str = "source") -> DataFrame:
    """(source, n, rate): mean repetitions of a document of each source.

    ``targets`` gives weights by source; sources it does not name get none.
    Without it all sources weigh the same. ``size`` is the expected number of
    documents of the mixture, by default as many as there are.
    """
    counted = cut(docs.groupBy(F.col(source_col).alias("_source")).agg(F.count("*").alias("n")))
    if targets is None:
        weighed = counted.withColumn("w", F.lit(1.0))
    else:
        if any(w < 0 for w in targets.values()):
            raise ValueError("weights must not be negative")
        names = [F.lit(x) for pair in targets.items() for x in pair]
        weighed = counted.withColumn("w", F.coalesce(F.element_at(F.create_map(*names), F.col("_source")), F.lit(0.0)) if names else F.lit(0.0))
    total = weighed.agg(F.sum("w").alias("w"), F.sum("n").alias("n")).head()
    whole, n = float(total["w"] or 0.0), float(size if size is not None else total["n"] or 0.0)
    rate = F.col("w") / F.lit(whole) * F.lit(n) / F.col("n") if whole > 0 else F.lit(0.0)
    return weighed.select("_source", "n", rate.alias("rate"))


def _log_factorial(k: Column) -> Column:
    """log k! by a series, exact to a double for k of 100 or more; smaller ones are summed."""
    x = k.cast("double")
    series = (x + 0.5) * F.log(x) - x + 0.5 * math.log(2 * math.pi) + 1 / (12 * x) - 1 / (360 * x * x * x) + 1 / (1260 * x * x * x * x * x)
    return F.when(k >= 100, series).otherwise(F.aggregate(F.sequence(F.lit(1).cast("long"), F.greatest(k, F.lit(1))), F.lit(0.0), lambda acc, i: acc + F.log(i.cast("double"))))


def distributions(rates: DataFrame) -> DataFrame:
    """(_source, _first, _cdf): the Poisson distribution function of each source's rate, from the count ``_first`` on.

    Counts reach nine deviations and thirty around the rate; what lies below
    has a chance under 2^-53. The work is linear in the width of that range,
    which grows with the root of the rate.
    """
    reach = 9 * F.sqrt("rate") + 30
    first = F.greatest(F.floor(F.col("rate") - reach), F.lit(0)).cast("long")
    base = rates.withColumns({"_first": first, "_last": F.ceil(F.col("rate") + reach).cast("long")})
    start = F.when(F.col("_first") == 0, -F.col("rate")).otherwise(F.col("_first") * F.log("rate") - F.col("rate") - _log_factorial(F.col("_first")))
    each = base.withColumn("_start", start).select("_source", "_first", "_start", "rate", F.explode(F.sequence("_first", "_last")).alias("k"))
    # log of the chance of each count, summed up from the first; rates are told apart by their source
    step = F.when(F.col("k") == F.col("_first"), F.col("_start")).otherwise(F.log("rate") - F.log(F.col("k").cast("double")))
    so_far = Window.partitionBy("_source").orderBy("k").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    summed = each.withColumn("_log", F.sum(step).over(so_far)).withColumn("c", F.sum(F.exp("_log")).over(so_far))
    return summed.groupBy("_source").agg(F.first("_first").alias("_first"), F.transform(F.array_sort(F.collect_list(F.struct("k", "c"))), lambda x: x["c"]).alias("_cdf"))


def _below(cdf: Column, u: Column, most: int) -> Column:
    """How many entries of a rising array lie under ``u``, by halving."""
    powers = [1 << i for i in reversed(range(max(1, most.bit_length())))]
    found = F.lit(0)
    return F.aggregate(F.array(*[F.lit(p) for p in powers]), found, lambda low, p: F.when((low + p <= F.size(cdf)) & (F.get(cdf, low + p - 1) < u), low + p).otherwise(low))


def mix_sources(docs: DataFrame, targets: dict[str, float] | None = None, size: float | None = None, seed: int = SEED, id_col: str = "doc_id", source_col: str = "source", shuffle: bool = True) -> DataFrame:
    """The input rows, each as often as its Poisson count says, with copy (from 0) and order_key.

    A null source is a source of its own. Rows that repeat an id get the same
    count each; a null id is hashed like the text ``null``. Rates of zero give
    no rows; an empty table gives an empty result. Columns of the input named
    copy or order_key are replaced. With ``shuffle`` the result is sorted by
    ``order_key`` over all partitions.
    """
    rates = source_rates(docs, targets, size, source_col).where("rate > 0")
    found = cut(distributions(rates))
    most = found.agg(F.max(F.size("_cdf"))).head()[0] or 1
    table = checked_broadcast(found, 10_000)
    rows = docs.drop("copy", "order_key")
    met = rows.join(table, rows[source_col].eqNullSafe(table["_source"]))
    u = hash_uniform(F.lit(seed), F.col(id_col))
    # no count lies under the first one that has a chance
    count = F.col("_first") + _below(F.col("_cdf"), u, most)
    out = met.withColumn("_n", count).where("_n > 0").withColumn("copy", F.explode(F.sequence(F.lit(0), (F.col("_n") - 1).cast("int"))))
    keyed = out.withColumn("order_key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.coalesce(F.col(id_col).cast("string"), F.lit("null")), F.col("copy").cast("string")))).drop("_source", "_first", "_cdf", "_n")
    if not shuffle:
        return keyed
    return keyed.orderBy("order_key")


def expected_counts(rate: float, u: float) -> int:
    """The count for one uniform number, for tests and small plans."""
    k, term = 0, math.exp(-rate)
    total = term
    while total < u and k < rate + 9 * math.sqrt(rate) + 30:
        k += 1
        term *= rate / k
        total += term
    return k
