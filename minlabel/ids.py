"""Keys of any type as ordered integers, and back."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dense_ids(keys: DataFrame, key: str, partitions: int | None = None) -> DataFrame:
    """key and id 0..n-1 in the order of the keys: a range sort, one count for each partition to the driver, and offsets."""
    n = partitions or int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = keys.select(key).dropna().distinct().repartitionByRange(n, key).sortWithinPartitions(key)
    local = dealt.withColumn("_m", F.monotonically_increasing_id())
    from minlabel.session import checkpoint

    local = checkpoint(local).select(key, F.shiftright("_m", 33).cast("int").alias("_p"), F.col("_m").bitwiseAND(F.lit((1 << 33) - 1)).alias("_k"))
    counts = {r._p: r.n for r in local.groupBy("_p").agg(F.count("*").alias("n")).collect()}  # as many rows as partitions
    offsets, total = [], 0
    for p in range(max(counts, default=-1) + 1):
        offsets.append(total)
        total += counts.get(p, 0)
    base = F.array(*[F.lit(x).cast("bigint") for x in offsets]) if offsets else F.array(F.lit(0).cast("bigint"))
    return local.select(key, (F.get(base, F.col("_p")) + F.col("_k")).alias("id"))


def encode_ids(df: DataFrame, columns: dict[str, str], mode: str = "dense") -> tuple[DataFrame, DataFrame]:
    """df with each column (name -> kind) as id, and the vocabulary(id, kind, key).

    tagged: integer keys, id = key * kinds + position of the kind. dense: 0..n-1 over the sorted (kind, key). hashed: a 64-bit hash, with an error on a collision."""
    kinds = sorted(set(columns.values()))
    if mode == "tagged":
        ids = {c: F.col(c).cast("bigint") * len(kinds) + kinds.index(k) for c, k in columns.items()}
        vocabulary = None
        for c, k in columns.items():
            part = df.select(ids[c].alias("id"), F.lit(k).alias("kind"), F.col(c).cast("string").alias("key")).dropna()
            vocabulary = part if vocabulary is None else vocabulary.unionByName(part)
        return df.withColumns(ids), vocabulary.distinct()
    keyed = None
    for c, k in columns.items():
        part = df.select(F.concat_ws("\x00", F.lit(k), F.col(c).cast("string")).alias("kk")).where(F.col(c).isNotNull())
        keyed = part if keyed is None else keyed.unionByName(part)
    if mode == "hashed":
        known = keyed.distinct().select("kk", F.xxhash64("kk").alias("id"))
        if not known.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").isEmpty():
            raise ValueError("two keys have one hash; use dense ids")
    elif mode == "dense":
        known = dense_ids(keyed, "kk")
    else:
        raise ValueError(f"no mode {mode}")
    out = df
    for c, k in columns.items():
        mine = known.select(F.col("kk").alias(f"kk_{c}"), F.col("id").alias(f"id_{c}"))
        out = out.withColumn(f"kk_{c}", F.when(F.col(c).isNotNull(), F.concat_ws("\x00", F.lit(k), F.col(c).cast("string")))).join(mine, f"kk_{c}", "left").withColumn(c, F.col(f"id_{c}")).drop(f"kk_{c}", f"id_{c}")
    parts = F.split("kk", "\x00", 2)
    return out, known.select("id", parts[0].alias("kind"), parts[1].alias("key"))


def decode_labels(labels: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """kind, key, label_kind, label_key of each vertex."""
    named = vocabulary.select("id", "kind", "key")
    root = vocabulary.select(F.col("id").alias("label"), F.col("kind").alias("label_kind"), F.col("key").alias("label_key"))
    return labels.join(named, "id").join(root, "label").select("kind", "key", "label_kind", "label_key")
