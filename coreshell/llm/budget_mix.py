"""Mixing sources to target weights as a subset-sum problem over document lengths.

Documents of one source and one length are interchangeable for a budget, so only
the counts by exact length enter the dynamic programme; which documents of a
length are taken follows from a seeded hash.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.llm.shared import stored

#: Sources are named groups (one row each on the driver); more are refused.
MOST_SOURCES = 100_000
#: Times the longest document's words that the proportional part leaves to the programme.
LEFT_LENGTHS = 16
#: Documents of one source and length are dealt into at most this many groups by their hash.
MOST_GROUPS = 4096
WORD = r"[^\x20\x09-\x0D]+"


def targets(sizes: dict[str | None, int], weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2.0) -> dict[str | None, float]:
    """Words to take from each source: ``share`` of all words by weight (sources by code point, null last, weights repeating), none above ``most`` times its size; what is above goes to the others by weight."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    out: dict[str | None, float] = {}
    left, free = share * sum(sizes.values()), list(names)
    while free:
        unit = left / sum(weight[s] for s in free)
        over = [s for s in free if weight[s] * unit > most * sizes[s]]
        if not over:
            return out | {s: weight[s] * unit for s in free}
        for s in over:
            out[s] = most * sizes[s]
            left -= out[s]
        free = [s for s in free if s not in out]
        left = max(0.0, left)
    return out


def fit(lengths: Sequence[int], counts: Sequence[int], budget: int) -> list[int]:
    """How many documents of each length to take (at most its count) for a sum as near below ``budget`` as can be.

    All but ``LEFT_LENGTHS`` times the longest length is taken in proportion, so that a mix keeps the source's lengths;
    what a length falls short of its share by is carried on to the next shorter one. The whole rest of the budget is
    filled by a bounded knapsack over reachable sums (one big integer as a bit set, each count split into powers of two),
    shorter lengths first, which stops as soon as the budget itself is reached. Documents of length 0 are taken in proportion.
    """
    total = sum(length * n for length, n in zip(lengths, counts, strict=True))
    if budget >= total:
        return list(counts)
    order = sorted((i for i in range(len(lengths)) if lengths[i] > 0), key=lambda i: -lengths[i])
    bulk = max(0, budget - LEFT_LENGTHS * lengths[order[0]])
    taken = [n * budget // total if not length else 0 for length, n in zip(lengths, counts, strict=True)]
    passed = used = 0
    for i in order:
        passed += lengths[i] * counts[i]
        taken[i] = min(counts[i], (bulk * passed // total - used) // lengths[i])
        used += taken[i] * lengths[i]
    unit = math.gcd(*(lengths[i] for i in order))
    left = (budget - used) // unit  # nothing but multiples of the lengths' common divisor can be reached
    sums, steps = [1], []
    mask = (1 << (left + 1)) - 1
    for i in reversed(order):
        length = lengths[i] // unit
        spare, power = min(counts[i] - taken[i], left // length), 1
        while spare > 0 and not sums[-1] >> left & 1:
            k = min(power, spare)
            steps.append((i, k))
            sums.append((sums[-1] | sums[-1] << k * length) & mask)
            spare, power = spare - k, power * 2
    at = sums[-1].bit_length() - 1
    for (i, k), before in zip(reversed(steps), reversed(sums[:-1]), strict=True):
        if not before >> at & 1:
            taken[i] += k
            at -= k * (lengths[i] // unit)
    return taken


def document_sizes(docs: DataFrame, seed: int) -> DataFrame:
    """``doc_id, source, size`` and the seeded hash that orders the documents of a length."""
    return docs.select(
        docs["doc_id"].cast("long").alias("doc_id"),
        docs["source"].cast("string").alias("source"),
        F.regexp_count(F.coalesce(docs["text"], F.lit("")), F.lit(WORD)).cast("long").alias("size"),
        F.xxhash64(F.lit(seed), docs["doc_id"].cast("long")).alias("order_hash"),
    )


def dealt_times(docs: DataFrame, weights: Sequence[float], share: float, most: float, seed: int) -> DataFrame:
    """The columns of ``mix``, and ``times``: how often each document is taken."""
    spark = docs.sparkSession
    sizes = stored(document_sizes(docs, seed), "sizes")
    by_source = sizes.groupBy("source").agg(F.sum("size").alias("n")).limit(MOST_SOURCES + 1).collect()
    if len(by_source) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    total = {r["source"]: r["n"] for r in by_source}
    goal = targets(total, weights, share, most)
    known = spark.createDataFrame([(s, n, float(goal[s])) for s, n in total.items()], "source string, source_size long, target double")

    def plan(pdf: pd.DataFrame) -> pd.DataFrame:
        s = pdf["source"].iloc[0]
        s = None if pd.isna(s) else s
        whole = min(int(goal[s] // total[s]), int(most)) if total[s] else 0
        lengths, counts = pdf["size"].tolist(), pdf["n"].tolist()
        k = fit(lengths, counts, max(0, int(round(goal[s])) - whole * total[s])) if whole < most else [0] * len(counts)
        return pdf.assign(whole=whole, k=k)

    counts = sizes.groupBy("source", "size").agg(F.count("*").alias("n"))
    plans = counts.groupBy("source").applyInPandas(plan, "source string, size long, n long, whole int, k long")
    plans = stored(plans.withColumnRenamed("source", "s").withColumnRenamed("size", "length"), "plan")
    same = F.col("source").eqNullSafe(F.col("s")) & (F.col("size") == F.col("length"))
    groups = F.greatest(F.lit(1), F.least(F.lit(MOST_GROUPS), F.ceil(F.col("n") / 64)))
    dealt = sizes.join(plans, same).withColumn("bucket", F.pmod(F.col("order_hash"), groups)).drop("s", "length")
    # the bucket in which a length's last document falls, and how many of it are taken
    filled = dealt.where("k > 0").groupBy("source", "size", "bucket").agg(F.count("*").alias("m"), F.first("k").alias("k"))
    before = F.sum("m").over(W.partitionBy("source", "size").orderBy("bucket").rowsBetween(W.unboundedPreceding, 0)) - F.col("m")
    last = filled.withColumn("before", before).where("before < k and k <= before + m")
    last = last.select(F.col("source").alias("s"), F.col("size").alias("length"), F.col("bucket").alias("cut"), (F.col("k") - F.col("before")).alias("rest"))
    rank = F.row_number().over(W.partitionBy("source", "size", "bucket").orderBy("order_hash", "doc_id"))
    chosen = dealt.join(last, same, "left").withColumn("rank", rank)
    once_more = (F.col("bucket") < F.col("cut")) | (F.col("bucket") == F.col("cut")) & (F.col("rank") <= F.col("rest"))
    times = F.col("whole") + F.coalesce(once_more, F.lit(False)).cast("int")
    known = F.broadcast(known.withColumnRenamed("source", "s"))  # at most MOST_SOURCES rows
    out = chosen.drop("s").join(known, F.col("source").eqNullSafe(F.col("s")))
    return out.select("doc_id", "size", "source_size", "target", (times * F.col("size")).cast("long").alias("taken"), times.alias("times"))


def mix(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2.0, seed: int = 17) -> DataFrame:
    """``doc_id, size, source_size, target, taken`` of every document; ``taken`` is 0, 1 or 2 times its size.

    A source whose target exceeds its size is taken whole first. Null texts have size 0; a null source is a source of
    its own, the last. Repeated rows are taken one by one. Among equal doc_ids of equal length any may be taken, which
    gives the same rows.
    """
    return dealt_times(docs, weights, share, most, seed).drop("times")


def mixed_documents(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2.0, seed: int = 17) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes them, with the columns of ``docs``.

    Rows of equal doc_id are taken by that id: as often as the mix takes words of it, dealt over its rows. Documents of
    size 0 cost nothing: they are taken in proportion like any length, and as often as a source that is taken whole.
    """
    ratio = F.when(F.sum("size") > 0, F.sum("taken") / F.sum("size")).otherwise(F.avg("times"))
    taken = dealt_times(docs, weights, share, most, seed).groupBy("doc_id").agg(ratio.alias("ratio"))
    taken = taken.select(F.col("doc_id").alias("__mixed_id"), F.round("ratio").cast("int").alias("__times")).where("__times > 0")
    joined = docs.join(taken, docs["doc_id"].cast("long").eqNullSafe(F.col("__mixed_id")))
    copies = joined.withColumn("__copy", F.explode(F.sequence(F.lit(1), F.col("__times"))))
    return copies.select(*[docs[c] for c in docs.columns])


