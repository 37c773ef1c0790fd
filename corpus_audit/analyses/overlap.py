"""Texts and URLs that corpora share."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Corpora that one bitmask can tell apart.
MAX_CORPORA = 62


def numbered(df: DataFrame) -> DataFrame:
    """corpus, bit: a number for each corpus (few rows)."""
    names = sorted(r[0] for r in df.select("corpus").distinct().filter(F.col("corpus").isNotNull()).limit(MAX_CORPORA + 1).collect())
    if len(names) > MAX_CORPORA:
        raise ValueError(f"more than {MAX_CORPORA} corpora")
    return df.sparkSession.createDataFrame([(n, i) for i, n in enumerate(names)], "corpus string, bit int")


def masks(df: DataFrame, column: str = "text") -> DataFrame:
    """mask, n: distinct values by the set of corpora that hold them, as bits. One shuffle of digests."""
    bits = numbered(df)
    one = F.expr("shiftleft(1L, bit)")
    keyed = df.filter(F.col(column).isNotNull()).select("corpus", F.unhex(F.md5(F.col(column).cast("binary"))).alias("digest"))
    per_value = keyed.join(F.broadcast(bits), "corpus").groupBy("digest").agg(F.bit_or(one).alias("mask"))
    return per_value.groupBy("mask").agg(F.count("*").alias("n"))


def _members(mask_counts: DataFrame, bits: DataFrame) -> DataFrame:
    """mask, n, members: the mask's corpora in order."""
    named = mask_counts.join(F.broadcast(bits), F.expr("(mask & shiftleft(1L, bit)) <> 0"))
    return named.groupBy("mask", "n").agg(F.array_sort(F.collect_list("corpus")).alias("members"))


def pairs(df: DataFrame, column: str = "text") -> DataFrame:
    """corpus_a, corpus_b, n, ratio_a, ratio_b: shared distinct values and their share of each corpus's distinct ones."""
    sets = _members(masks(df, column), numbered(df))
    own = sets.select("n", F.explode("members").alias("corpus")).groupBy("corpus").agg(F.sum("n").alias("own"))
    both = sets.select("n", F.col("members"), F.explode("members").alias("corpus_a")).select("n", "corpus_a", F.explode("members").alias("corpus_b")).filter("corpus_a < corpus_b")
    counted = both.groupBy("corpus_a", "corpus_b").agg(F.sum("n").alias("n"))
    a, b = (own.select(F.col("corpus").alias(f"corpus_{x}"), F.col("own").alias(f"own_{x}")) for x in "ab")
    joined = counted.join(F.broadcast(a), "corpus_a").join(F.broadcast(b), "corpus_b")
    return joined.select("corpus_a", "corpus_b", "n", F.round(F.col("n") / F.col("own_a"), 6).alias("ratio_a"), F.round(F.col("n") / F.col("own_b"), 6).alias("ratio_b"))


def subsets(df: DataFrame, column: str = "text", min_size: int = 3, k: int = 10, exclusive: bool = False) -> DataFrame:
    """members, n: values in all corpora of a set of any size, the k largest; inclusive counts, so a set counts its supersets' values.

    Only masks are combined. All sets of ``min_size`` corpora are counted, a number that is polynomial
    in a mask's width, and the k first of them are grown by later corpora. A grown set counts no more and
    its name sorts behind, so only sets among the k first known need be grown, at most k times.
    With ``exclusive`` each value counts for its full set of corpora alone.
    """
    bits = numbered(df)
    counted = masks(df, column).persist()
    sets = _members(counted, bits).filter(F.size("members") >= min_size)
    order = [F.desc("n"), "members"]
    if exclusive:
        counted.unpersist()
        return sets.groupBy(F.array_join("members", "+").alias("members")).agg(F.sum("n").alias("n")).orderBy(*order).limit(k)
    grow = F.aggregate("members", F.array(F.array().cast("array<string>")), lambda acc, c: F.concat(acc, F.transform(F.filter(acc, lambda s: F.size(s) < min_size), lambda s: F.concat(s, F.array(c)))))
    least = sets.select("n", F.explode(F.filter(grow, lambda s: F.size(s) == min_size)).alias("set")).groupBy("set").agg(F.sum("n").alias("n"))
    names = {r["bit"]: r["corpus"] for r in bits.collect()}
    bit_of = {name: bit for bit, name in names.items()}
    # (-n, name, mask, last corpus), in the order of the answer
    first = least.withColumn("members", F.array_join("set", "+")).orderBy(*order).limit(k).collect()
    known = sorted((-r["n"], r["members"], sum(1 << bit_of[c] for c in r["set"]), bit_of[r["set"][-1]]) for r in first)
    grown: set[int] = set()
    while new := [x for x in known if x[2] not in grown]:
        grown |= {x[2] for x in new}
        name_of = {mask: name for _, name, mask, _ in new}
        nodes = df.sparkSession.createDataFrame([(mask, last) for _, _, mask, last in new], "held long, last int")
        later = F.explode(F.sequence(F.col("last") + 1, F.lit(len(names)))).alias("bit")
        met = counted.join(F.broadcast(nodes.select("held", later)), F.expr("(mask & held) = held AND (mask & shiftleft(1L, bit)) <> 0"))
        for r in met.groupBy("held", "bit").agg(F.sum("n").alias("n")).collect():  # at most k nodes by the number of corpora
            known.append((-r["n"], f"{name_of[r['held']]}+{names[r['bit']]}", r["held"] | 1 << r["bit"], r["bit"]))
        known = sorted(known)[:k]
    counted.unpersist()
    return df.sparkSession.createDataFrame([(name, -n) for n, name, _, _ in known], "members string, n long").orderBy(*order)


def containment(overlaps: DataFrame) -> DataFrame:
    """corpus_a, corpus_b, share: the part of a's distinct values that b holds, both ways."""
    return overlaps.select("corpus_a", "corpus_b", F.col("ratio_a").alias("share")).union(overlaps.select(F.col("corpus_b").alias("corpus_a"), F.col("corpus_a").alias("corpus_b"), F.col("ratio_b").alias("share")))
