"""A bounded sample of labelled documents, the same on every run."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def remainder(key: Column, modulus: int) -> Column:
    """crc32 of the key as text, by ``modulus``; null for a null key."""
    return F.crc32(key.cast("string").cast("binary")) % modulus


def sample_labelled(docs: DataFrame, labels: DataFrame, label: str, allowed: Column, per_class: int, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``key, text, label`` of at most ``per_class`` rows with label 0 and as many with label 1.

    The choice goes by a hash of the key. The chosen keys, two times ``per_class`` at most, are broadcast
    to one scan of the documents, so no text is shuffled. Null labels and keys take no part.
    """
    usable = labels.filter(F.col(label).isin(0, 1) & F.col(key).isNotNull() & allowed)
    usable = usable.groupBy(F.col(key).alias("key")).agg(F.max(label).cast("int").alias("label"))
    chosen = None
    for value in (0, 1):
        part = usable.filter(F.col("label") == value).orderBy(F.xxhash64("key"), "key").limit(per_class)
        chosen = part if chosen is None else chosen.union(part)
    texts = docs.select(F.col(f"`{key}`").alias("id"), F.col(f"`{text}`").cast("string").alias("text"))
    return texts.join(F.broadcast(chosen), texts["id"] == F.col("key")).select("key", "text", "label")


def class_weights(sample_sizes: dict[int, int], labels: DataFrame, label: str, allowed: Column, key: str = "doc_id") -> dict[int, float]:
    """How many allowed rows of the table stand behind one sampled row, per label."""
    usable = labels.filter(F.col(label).isin(0, 1) & F.col(key).isNotNull() & allowed)
    whole = {int(r[0]): r[1] for r in usable.groupBy(label).agg(F.countDistinct(key)).collect()}
    return {k: whole.get(k, n) / n for k, n in sample_sizes.items() if n}
