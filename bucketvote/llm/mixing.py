"""Mixes sources to target weights by balanced sampling with the cube method.

A source's target over its size says how often each of its documents is taken: whole times for all, and the fraction as
an inclusion probability. The cube method moves these probabilities along directions that keep the number of documents
and of tokens, until each is 0 or 1 but a few; here in blocks of bounded size, then among the blocks' leftovers, level
by level, and only the last two leftovers of a source are landed, by the choice of least token error. Random numbers
come from hashes, so reruns agree.

Edge cases: a null or empty text has size 0, and a source of size 0 has target 0; null is a source of its own, last in
order; a null doc_id is kept; repeated rows are drawn one by one; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import random

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, written

BLOCK, FAN, MOST = 256, 64, 3.0
_EPS = 1e-9


def size_of(text: Column) -> Column:
    """Runs of characters that are not ASCII white space."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def targets(sizes: DataFrame, most: float = MOST) -> DataFrame:
    """(source, source_size, target): one row a source. Sources, by code point, weigh 1, 2, 3, repeating.

    A share of l times the weight, cut at `most` times the size, must sum to all: with sources ordered by the share at
    which they are cut, l is the first rate that cuts none of the sources left.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weighed = per.withColumn("weight", (F.row_number().over(order) - 1) % 3 + 1).withColumn("cap", F.lit(most) * F.col("source_size"))
    by_rate = Window.orderBy((F.col("cap") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    rated = (
        weighed.withColumn("total", F.sum("source_size").over(everything).cast("double"))
        .withColumn("cut", F.coalesce(F.sum("cap").over(by_rate.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("open", F.sum("weight").over(by_rate.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("rate", (F.col("total") - F.col("cut")) / F.col("open"))
    )
    fits = rated.withColumn("rate", F.min(F.when(F.col("rate") * F.col("weight") <= F.col("cap"), F.struct(F.col("cut"), F.col("rate")))).over(everything)["rate"])
    share = F.coalesce(F.least(F.col("rate") * F.col("weight"), "cap"), "cap")
    return fits.select("source", "source_size", F.when(F.col("source_size") > 0, share).otherwise(0.0).alias("target"))


def flight(pi: list[float], size: list[float], rng: random.Random) -> list[float]:
    """Moves probabilities to 0 or 1, keeping their sum and that of pi * size, until at most two stay between."""
    pi = [0.0 if p < _EPS else 1.0 if p > 1 - _EPS else p for p in pi]
    open_: list[int] = []
    for i, p in enumerate(pi):
        if p in (0.0, 1.0):
            continue
        open_.append(i)
        while len(open_) == 3 or (len(open_) == 2 and size[open_[0]] == size[open_[1]]):
            if len(open_) == 3:
                a, b, c = (size[j] for j in open_)
                step = [c - b, a - c, b - a]
            else:
                step = [1.0, -1.0]
            if not any(step):
                step = [1.0, -1.0, 0.0]
            up = min((1 - pi[j]) / s if s > 0 else pi[j] / -s for j, s in zip(open_, step, strict=True) if s)
            down = min(pi[j] / s if s > 0 else (1 - pi[j]) / -s for j, s in zip(open_, step, strict=True) if s)
            move = up if rng.random() * (up + down) < down else -down
            for j, s in zip(open_, step, strict=True):
                x = pi[j] + move * s
                pi[j] = 0.0 if x < _EPS else 1.0 if x > 1 - _EPS else x
            open_ = [j for j in open_ if pi[j] not in (0.0, 1.0)]
    return pi


def landing(pi: list[float], size: list[float], start: list[float], flips: int = 3) -> list[float]:
    """Rounds the few open probabilities by the choice of least error in tokens, then in documents.

    start holds the probabilities before the flight: up to `flips` drawn units are turned while that brings tokens nearer.
    """
    open_ = [i for i, p in enumerate(pi) if p not in (0.0, 1.0)]
    want = sum(pi[i] * size[i] for i in open_)
    docs = sum(pi[i] for i in open_)
    best = min(range(1 << len(open_)), key=lambda m: (abs(want - sum(size[i] for k, i in enumerate(open_) if m >> k & 1)), abs(docs - m.bit_count()), m))
    out = list(pi)
    for k, i in enumerate(open_):
        out[i] = float(best >> k & 1)
    error = sum(out[i] * size[i] for i in open_) - want
    free = [i for i, p in enumerate(start) if _EPS < p < 1 - _EPS]
    for _ in range(flips):
        turn = min(free, key=lambda i: (abs(error + (1 - 2 * out[i]) * size[i]), i), default=None)
        if turn is None or abs(error + (1 - 2 * out[turn]) * size[turn]) >= abs(error):
            break
        error += (1 - 2 * out[turn]) * size[turn]
        out[turn] = 1 - out[turn]
    return out


def balanced(rows: DataFrame, levels_from: int, seed: int) -> DataFrame:
    """rows (key, source_key, size, pi, n) with pi moved to 0 or 1, balanced within each source.

    n is the source's number of rows; the largest sets the number of levels.
    """
    blocks = F.ceil(F.col("n") / F.lit(BLOCK))
    now = rows.withColumn("block", F.floor(F.pmod(F.xxhash64(F.lit(seed), "key"), F.lit(1 << 40)) / F.lit(float(1 << 40)) * blocks).cast("long"))
    most, level, done = -(-levels_from // BLOCK), 0, None

    def task_for(last: bool, level: int):
        def task(frame):
            frame = frame.sort_values(["key", "size"], kind="stable")
            pi, size = frame["pi"].tolist(), frame["size"].astype(float).tolist()
            rng = random.Random(f"{seed}/{level}/{frame['source_key'].iloc[0]}/{frame['block'].iloc[0]}")
            order = list(range(len(pi)))
            rng.shuffle(order)
            moved = flight([pi[i] for i in order], [size[i] for i in order], rng)
            if last:
                moved = landing(moved, [size[i] for i in order], [pi[i] for i in order])
            out = [0.0] * len(pi)
            for i, p in zip(order, moved, strict=True):
                out[i] = p
            return frame.assign(pi=out)

        return task

    while True:
        last = most <= 1
        now = written(now.groupBy("source_key", "block").applyInPandas(task_for(last, level), now.schema), "cube")
        settled = now if last else now.where("pi in (0.0, 1.0)")
        done = settled if done is None else done.unionByName(settled)
        if last:
            return done
        now = now.where("pi not in (0.0, 1.0)").withColumn("block", F.floor(F.col("block") / FAN))
        most, level = -(-most // FAN), level + 1


def mix(docs: DataFrame, most: float = MOST, seed: int = 23) -> DataFrame:
    """Per document row: doc_id, text_key, size, source_size, target, taken (words, repeats counted), times."""
    slim = written(docs.select("doc_id", "source", size_of(F.col("text")).alias("size"), F.xxhash64("text").alias("text_key")), "sizes")
    wanted = written(targets(slim.select("source", "size"), most), "targets")
    counts = slim.groupBy("source").agg(F.count("*").alias("n"))
    facts = written(wanted.join(counts.withColumnRenamed("source", "s"), F.col("source").eqNullSafe(F.col("s"))).drop("s").withColumn("ratio", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)), "source-facts")
    largest = facts.agg(F.max("n")).first()[0] or 0
    facts_side = facts.withColumnRenamed("source", "f_source")
    with_facts = slim.join(facts_side, F.col("source").eqNullSafe(F.col("f_source")))
    fraction = F.col("ratio") - F.floor("ratio")
    rows = with_facts.select(
        F.coalesce("doc_id", F.lit(NO_ID)).alias("id"), F.col("text_key"), F.xxhash64("doc_id", "text_key").alias("key"), F.coalesce(F.sha2("source", 256), F.lit("")).alias("source_key"),
        "size", "source_size", "target", "n", F.floor("ratio").cast("long").alias("whole"), F.when(F.col("size") > 0, fraction).otherwise(0.0).alias("pi"),
    )
    drawn = balanced(rows, int(largest), seed).withColumn("times", F.col("whole") + F.round("pi").cast("long"))
    return drawn.select(F.when(F.col("id") != NO_ID, F.col("id")).alias("doc_id"), "text_key", "size", "source_size", "target", (F.col("times") * F.col("size")).alias("taken"), "times")


def apply(docs: DataFrame, **options) -> DataFrame:
    """docs as the mix takes them: each row as many times as it is taken, in docs' columns whatever their names."""
    taken = mix(docs, **options).select(F.col("doc_id").alias("id"), "text_key", "times")
    # rows of one id and text are alike: their times are summed and dealt out evenly
    times = taken.groupBy("id", "text_key").agg(F.sum("times").alias("times"), F.count("*").alias("alike"))
    keyed = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").alias("own"), F.xxhash64("text").alias("own_key"))
    joined = keyed.join(times.where("times > 0"), F.col("own").eqNullSafe(F.col("id")) & (F.col("own_key") == F.col("text_key")))
    turn = F.row_number().over(Window.partitionBy("id", "text_key").orderBy("times"))
    each = F.floor(F.col("times") / F.col("alike")) + F.when(turn <= F.col("times") % F.col("alike"), 1).otherwise(0)
    dealt = joined.withColumn("each", each.cast("int")).where("each > 0")
    return dealt.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("each")))).select("row.*")
