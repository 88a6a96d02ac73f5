"""Bounded, documented training samples that don't depend on partitions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from modelsort.plans.durable import materialize


#: Groups whose bounds are sent to every task; with more of them the rows are shuffled.
BROADCAST_GROUPS = 10_000


def least_hashes(rows: DataFrame, hash_col: str, n: int, group_col: str) -> DataFrame:
    """Per group, one row for each of the ``n`` least hashes.

    Only hashes are ranked. The rows are then held against one bound a group,
    which every task gets if the groups are counted few, so that texts outside
    the sample stay where they are.
    """
    known = materialize(rows.select(group_col, hash_col).distinct(), "hashes")
    # Counts per leading bits of the hash show how far down a group's n least reach; only those hashes are ranked.
    top = F.shiftright(hash_col, 48)
    tally = known.groupBy(group_col, top.alias("__top")).agg(F.count("*").alias("__n"))
    along = Window.partitionBy(group_col).orderBy("__top").rowsBetween(Window.unboundedPreceding, -1)
    few = tally.withColumn("__before", F.coalesce(F.sum("__n").over(along), F.lit(0))).where(F.col("__before") < n)
    reach = materialize(few.groupBy(group_col).agg(F.max("__top").alias("__reach")), "hash-reach")
    small = reach.count() <= BROADCAST_GROUPS
    near = known.join(F.broadcast(reach) if small else reach, group_col).where(top <= F.col("__reach"))
    ranked = near.withColumn("__n", F.row_number().over(Window.partitionBy(group_col).orderBy(hash_col))).where(F.col("__n") <= n)
    bound = materialize(ranked.groupBy(group_col).agg(F.max(hash_col).alias("__most")), "hash-bounds")
    bound = F.broadcast(bound) if small else bound
    return rows.join(bound, group_col).where(F.col(hash_col) <= F.col("__most")).dropDuplicates([group_col, hash_col]).drop("__most")


def fold_of(id_col: str, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; null for a null id."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(parts))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, n: int, id_col: str = "doc_id", text_col: str = "text", parts: int = 5) -> DataFrame:
    """Columns ``text, label, fold`` of at most ``n`` labelled documents outside fold 0.

    The ids of least hash are taken from the labels and sent to every task (``n``
    longs), so no text is shuffled. An id with both labels counts as 1, null
    labels and ids teach nothing, a null text is empty. Other columns are not
    read; no labels or documents give no rows.
    """
    known = labels.select(F.col("doc_id").cast("long").alias("__id"), F.col(label).cast("int").alias("label")).where("__id is not null and label is not null").where(fold_of("__id", parts) != 0)
    chosen = known.groupBy("__id").agg(F.max("label").alias("label")).orderBy(F.xxhash64("__id"), "__id").limit(n)
    texts = docs.select(F.col(id_col).cast("long").alias("__id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    return texts.join(F.broadcast(chosen), "__id").select("text", "label", fold_of("__id", parts).cast("int").alias("fold"))


def free_name(df: DataFrame, name: str) -> str:
    """``name``, with underscores before it until no column of ``df`` has it in any case."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def quoted(df: DataFrame) -> list[str]:
    """Column names as they can be selected whatever they hold."""
    return [f"`{c.replace('`', '``')}`" for c in df.columns]
