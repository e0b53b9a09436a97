"""Mixing sources to target weights by weighted fair queueing.

Sources in code point order (null last) weigh 5, 2, 1, repeating. They share a budget of 150 % of all words by weight;
no target goes beyond `max_epochs` times its source's words, and what is above is shared anew by weight. Documents are
shuffled within their source by a hash; a document's virtual finish time is the words of its source up to and including
it, over all epochs, divided by the source's target. All copies are put in the order of finish time by a range sort, and
the queue is cut where the total budget is reached.

Both running sums are made task by task over ranges and shifted by the sums of the tasks before, so one source may hold
any share of the rows. The table of sources is small and the only thing joined without a range.

Defined cases: a null text has no words; documents without words are never taken; very long texts are counted whole; ties of the hash are
ordered by doc_id; repeated rows are queued one by one and reported one by one; an empty table gives an empty result; extra columns are
ignored by the report and kept by `mixed_documents`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkverdict.llm.common import hidden, materialise, ordered_positions, words

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MAX_EPOCHS = 2


def sizes(docs: DataFrame, source: str = "source") -> DataFrame:
    return docs.select("doc_id", F.col(source).alias("src"), F.size(words(F.col("text"))).cast("long").alias("size"))


def _weight(rank: Column) -> Column:
    return F.element_at(F.array(*[F.lit(w) for w in WEIGHTS]), (rank % len(WEIGHTS) + 1).cast("int"))


def targets(rows: DataFrame) -> DataFrame:
    """src, source_size, weight, target; one row per source, the windows below are over sources only."""
    total = rows.groupBy("src").agg(F.sum("size").alias("source_size"))
    ranked = total.withColumn("weight", _weight(F.row_number().over(Window.orderBy(F.col("src").asc_nulls_last())) - 1))
    cap = (MAX_EPOCHS * F.col("source_size")).cast("double")
    ranked = ranked.withColumn("cap", cap)
    # sources fill up in the order of cap / weight: with the first k at their caps, the level of the others follows
    order = Window.orderBy(F.col("cap") / F.col("weight"), F.col("src").asc_nulls_last())
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    budget = SHARE * F.sum("source_size").over(every)
    level = (budget - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0)))
    filled = ranked.withColumn("level", level).withColumn("full", F.col("level") * F.col("weight") >= F.col("cap"))
    final = F.min(F.when(~F.col("full"), F.struct(F.col("cap") / F.col("weight"), F.col("level").alias("level")))).over(every)["level"]
    return filled.withColumn("target", F.when(F.col("full"), F.col("cap")).otherwise(F.least(F.col("cap"), final * F.col("weight")))).select("src", "source_size", "weight", "target")


def queue(docs: DataFrame, source: str = "source") -> DataFrame:
    """doc_id, src, size, source_size, target and `copies`, how many times each row is taken."""
    rows = materialise(sizes(docs, source), "mix-sizes")
    goal = materialise(targets(rows), "mix-targets")
    hashed = rows.withColumn("turn", F.md5(F.col("doc_id").cast("string")))
    placed = ordered_positions(hashed, "src", ["turn", "doc_id", "size"], "size", "mix-order")
    placed = placed.withColumnsRenamed({"before": "src_before", "row_before": "src_row"})
    goal = goal.withColumnRenamed("src", "goal_src")
    timed = placed.join(goal, F.col("src").eqNullSafe(F.col("goal_src"))).drop("goal_src", "weight", "turn")
    timed = materialise(timed, "mix-timed")
    epochs = timed.filter(F.col("size") > 0).withColumn("epoch", F.explode(F.sequence(F.lit(0), F.lit(MAX_EPOCHS - 1))))
    words_before = F.col("epoch") * F.col("source_size") + F.col("src_before") + F.col("size")
    # the targets add up to the budget, so the cut falls near finish time 1
    queued = epochs.withColumn("finish", F.try_divide(words_before, F.col("target"))).withColumn("all", F.lit(0)).select("all", "finish", "src", "src_row", "epoch", "size")
    budget = F.floor(SHARE * F.sum("source_size"))
    cut = goal.agg(F.coalesce(budget, F.lit(0)).alias("budget"))
    served = ordered_positions(queued, "all", ["finish", "src", "src_row", "epoch"], "size", "mix-queue")
    # one row (an aggregate without keys) is broadcast
    taken = served.join(F.broadcast(cut), how="cross").filter(F.col("before") + F.col("size") <= F.col("budget"))
    copies = taken.groupBy(F.col("src").alias("t_src"), F.col("src_row").alias("t_row")).agg(F.count(F.lit(1)).alias("copies"))
    both = timed.join(copies, F.col("src").eqNullSafe(F.col("t_src")) & (F.col("src_row") == F.col("t_row")), "left")
    return both.select("doc_id", "src", "size", "source_size", "target", F.coalesce("copies", F.lit(0)).cast("long").alias("copies"))


def mix(docs: DataFrame, source: str = "source") -> DataFrame:
    return queue(docs, source).select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def mixed_documents(docs: DataFrame, source: str = "source") -> DataFrame:
    """The documents that the mix takes, each as many times as it takes them. doc_id must tell documents apart."""
    copies = queue(docs, source).filter(F.col("copies") > 0).select(F.col("doc_id").alias("_id"), F.col("copies").alias("_copies"))
    rows, (doc_id,) = hidden(docs, "doc_id")
    taken = rows.join(copies, F.col(doc_id).eqNullSafe(F.col("_id"))).withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int"))))
    return taken.select(*rows.columns).toDF(*docs.columns)
