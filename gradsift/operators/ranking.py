"""Global ranks and percentiles without a one-partition sort.

Scores are dealt into bins between approximate quantiles, bins are counted, and a row's rank
is its rank within the bin plus the rows of the bins before. The number of bins follows the
number of rows, so a task's sort doesn't grow with the corpus; only the bins' counts reach
the driver. A bin that one score fills is dealt again by quantiles of the id, so a score that
a third of the rows share doesn't end up in one task.

Defined results: rows without a score, null or NaN, come after all others, by id, whatever
the direction; equal scores are in the order of their ids, null ids first; an empty table has
no ranks. Columns named rank and pct are replaced, all others pass, whatever their names.
"""

from __future__ import annotations

import math

from pyspark.ml.feature import Bucketizer
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Rows that a task orders, about, and the most bins, whose bounds and counts the driver holds.
ROWS_A_BIN = 100_000
MAX_BINS = 20_000
#: Sampled ids for each part of a bin that one score fills.
_IDS_A_PART = 20


def bins_for(n: int, rows_a_bin: int = ROWS_A_BIN) -> int:
    return max(1, min(MAX_BINS, -(-n // rows_a_bin)))


def unused(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened until no column of the table has them."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name in taken:
            name += "_"
        taken.add(name)
        out.append(name)
    return out


def splitters(df: DataFrame, score: str, bins: int) -> list[float]:
    """Approximate quantiles of a score, without repeats."""
    if bins < 2:
        return []
    at, x = [i / bins for i in range(1, bins)], F.col(f"`{score}`").cast("double")
    row = df.select(F.percentile_approx(F.when(~F.isnan(x), x), at, max(10_000, 20 * bins)).alias("q")).first()
    return sorted({float(x) for x in (row["q"] or []) if x is not None and math.isfinite(x)})


def with_bin(df: DataFrame, score: str, cuts: list[float], out: str = "_bin") -> DataFrame:
    """The number of cuts at or below the score, found by binary search in the JVM; one more for NaN."""
    if not cuts:
        return df.withColumn(out, F.isnan(F.col(f"`{score}`")).cast("double"))
    return Bucketizer(splits=[-math.inf, *cuts, math.inf], inputCol=score, outputCol=out, handleInvalid="keep").transform(df)


def _number(score: str) -> Column:
    """The score as a double, NaN where there is none."""
    return F.coalesce(F.col(f"`{score}`").cast("double"), F.lit(float("nan")))


def rank_corpus(df: DataFrame, score: str, id_col: str, bins: int | None = None, descending: bool = True, rank_col: str = "rank", pct_col: str = "pct") -> DataFrame:
    """Adds rank (1 is the highest score, ties by id) and pct = (rank - 1) / N. bins: by default from the count.

    Small jobs come first: a count and, for several bins, their quantiles and counts.
    """
    key, bin_, sub, before, inside = unused(df, "_key", "_bin", "_sub", "_before", "_in")
    keyed = df.withColumn(key, _number(score))
    total, scored = keyed.agg(F.count(F.lit(1)), F.count_if(~F.isnan(key))).first()
    bins = bins or bins_for(total)
    by = F.col(key).desc() if descending else F.col(key).asc()
    order = [F.isnan(key).asc(), by, F.col(f"`{id_col}`").asc()]
    if bins == 1:
        place = F.row_number().over(Window.partitionBy(bin_).orderBy(*order))
        ranked = with_bin(keyed, key, [], bin_).withColumn(inside, place).withColumn(before, F.when(F.col(bin_) == 0, F.lit(0)).otherwise(F.lit(scored)))
    else:
        binned = with_bin(keyed, key, splitters(keyed, key, bins), bin_)
        found = binned.groupBy(F.col(bin_).alias("b")).agg(F.count(F.lit(1)).alias("n"), F.min(key).alias("lo"), F.max(key).alias("hi")).collect()
        target = max(1, total // bins)
        last = max((r["b"] for r in found), default=0.0) if any(r["lo"] is not None and math.isnan(r["lo"]) for r in found) else None
        parts = {r["b"]: -(-r["n"] // target) for r in found if r["n"] > 4 * target and (r["lo"] == r["hi"] or r["b"] == last)}
        counts = {(r["b"], 0): r["n"] for r in found}
        binned = _with_part(binned, bin_, sub, id_col, {r["b"]: r["n"] for r in found}, parts)
        if parts:
            split = binned.groupBy(F.col(bin_).alias("b"), F.col(sub).alias("s")).agg(F.count(F.lit(1)).alias("n"))
            counts = {(r["b"], r["s"]): r["n"] for r in split.collect()}
        offsets, upto = [], 0
        for b, s in sorted(counts, key=lambda k: (k[0] == last, -k[0] if descending else k[0], k[1])):
            offsets.append((b, s, upto))
            upto += counts[b, s]
        table = df.sparkSession.createDataFrame(offsets, f"`{bin_}` double, `{sub}` int, `{before}` long")
        place = F.row_number().over(Window.partitionBy(bin_, sub).orderBy(*order))
        ranked = binned.withColumn(inside, place).join(F.broadcast(table), [bin_, sub])
    return (
        ranked.withColumn(rank_col, (F.col(before) + F.col(inside)).cast("long"))
        .withColumn(pct_col, (F.col(rank_col) - 1) / F.lit(float(max(1, total))))
        .drop(key, bin_, sub, before, inside)
    )


def _with_part(binned: DataFrame, bin_: str, sub: str, id_col: str, rows: dict[float, int], parts: dict[float, int]) -> DataFrame:
    """Adds the part of a bin that one score fills: ids between quantiles of a sample of them, of any type that has an order."""
    if not parts:
        return binned.withColumn(sub, F.lit(0))
    ident, share = F.col(f"`{id_col}`"), F.lit(0.0)
    for b, k in parts.items():
        share = F.when(F.col(bin_) == b, F.lit(min(1.0, _IDS_A_PART * k / rows[b]))).otherwise(share)
    draw = F.pmod(F.xxhash64(F.lit("part"), ident), F.lit(1 << 30)) / float(1 << 30)
    sample = binned.where(F.col(bin_).isin(list(parts)) & (draw < share)).select(F.col(bin_).alias("b"), ident.alias("i")).where("i IS NOT NULL").collect()
    cuts = []
    for b, k in parts.items():
        own = sorted(r["i"] for r in sample if r["b"] == b)
        cuts.append((b, sorted({own[len(own) * j // k] for j in range(1, k)}) if own else []))
    known = unused(binned, "_cuts")[0]
    kind = binned.schema[id_col].dataType.simpleString()
    table = binned.sparkSession.createDataFrame(cuts, f"`{bin_}` double, `{known}` array<{kind}>")
    below = F.size(F.filter(F.col(known), lambda x: x <= ident))
    return binned.join(F.broadcast(table), bin_, "left").withColumn(sub, F.when(F.col(known).isNull(), F.lit(0)).otherwise(below)).drop(known)


def select_smallest(df: DataFrame, key: str, k: int, id_col: str, bins: int | None = None) -> DataFrame:
    """The k rows with the smallest keys, ties by id. k may be any share of the rows.

    Rows below the bin in which the k-th lies are kept unsorted; only that bin is ordered.
    """
    if k <= 0:
        return df.limit(0)
    total = df.count()
    if k > total:
        raise ValueError(f"{k} rows wanted of {total}")
    bins = bins or bins_for(total)
    own, bin_, nth, part = unused(df, "_key", "_bin", "_nth", "_part")
    if bins == 1:
        return rank_corpus(df, key, id_col, 1, descending=False, rank_col=nth, pct_col=part).where(F.col(nth) <= k).drop(nth, part)
    keyed = df.withColumn(own, _number(key))
    binned = with_bin(keyed, own, splitters(keyed, own, bins), bin_)
    before, cut = 0, None
    for b, n in sorted((r["b"], r["n"]) for r in binned.groupBy(F.col(bin_).alias("b")).agg(F.count(F.lit(1)).alias("n")).collect()):
        if before + n >= k:
            cut = b
            break
        before += n
    below = binned.where(F.col(bin_) < cut)
    edge = rank_corpus(binned.where(F.col(bin_) == cut).drop(bin_), own, id_col, descending=False, rank_col=nth, pct_col=part)
    return below.drop(bin_, own).unionByName(edge.where(F.col(nth) <= k - before).drop(own, nth, part))


def approx_percentile_of(df: DataFrame, score: str, cuts: list[float]) -> DataFrame:
    """pct from the cuts of an earlier snapshot; map-only, so it serves streams too. 1 without a score."""
    n = len(cuts) + 1
    key, bin_ = unused(df, "_key", "_bin")
    return with_bin(df.withColumn(key, _number(score)), key, cuts, bin_).withColumn(
        "pct", F.when(F.isnan(key), F.lit(1.0)).otherwise(F.lit(1.0) - (F.col(bin_) + 1) / F.lit(float(n)))
    ).drop(key, bin_)
