"""Helpers that the training-data operators share."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.plans.storage import cut, cut_bucketed, release, shared_dir

__all__ = ["WHITE", "WHITE_CLASS", "col", "cut", "cut_bucketed", "fresh_names", "hash128", "hash_sample", "packed", "position_ids", "release", "row_key", "shared_dir", "unpacked"]

#: The white space of the contracts, [\x20\x09-\x0D].
WHITE = " \t\n\x0b\x0c\r"
WHITE_CLASS = r"[\x20\x09-\x0D]"


def hash128(name: str, *cols: Column) -> list[Column]:
    """Two independent 64-bit hashes of the columns, named <name>1 and <name>2; a null differs from any value by its flag."""
    parts = [x for c in cols for x in (c, c.isNull())]
    return [F.xxhash64(F.lit(17), *parts).alias(f"{name}1"), F.xxhash64(F.lit(40503), *reversed(parts)).alias(f"{name}2")]


def position_ids(df: DataFrame, *keys: Column | str) -> DataFrame:
    """Sort df by keys over range partitions; adds part (partition) and at (row within it). Cut before using the ids twice."""
    at = F.monotonically_increasing_id()
    ordered = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", at)
    return ordered.withColumn("part", F.shiftright("_at", 33)).withColumn("at", F.col("_at").bitwiseAND((1 << 33) - 1)).drop("_at")


def col(name: str) -> Column:
    """The column of exactly this name, dots and backticks in it included."""
    return F.col("`" + name.replace("`", "``") + "`")


def packed(df: DataFrame) -> Column:
    """All columns of df as one struct, so that no inner name can meet one of theirs."""
    return F.struct(*[col(c).alias(f"c{i}") for i, c in enumerate(df.columns)])


def unpacked(row: str, names: list[str]) -> list[Column]:
    """The columns that `packed` put into row, under their names."""
    return [F.col(f"{row}.c{i}").alias(n) for i, n in enumerate(names)]


def fresh_names(taken: list[str], names: tuple[str, ...]) -> list[str]:
    """For each name one that is not taken, whatever its case: the name itself or with underscores behind it."""
    held, out = {c.lower() for c in taken}, []
    for n in names:
        while n.lower() in held:
            n += "_"
        held.add(n.lower())
        out.append(n)
    return out


def row_key(df: DataFrame) -> list[Column]:
    """hash128 over all columns, so that only rows equal throughout share it."""
    return hash128("__k", *[F.to_json(F.struct(col(c))) if t.startswith(("map", "array", "struct")) else col(c) for c, t in df.dtypes])


def keep_rows(docs: DataFrame, decided: DataFrame) -> DataFrame:
    """The rows of docs that stay, columns as given. decided: row_key1, row_key2, kept, a row per row of docs; of rows that
    are equal throughout at most one is kept."""
    k1, k2 = row_key(docs)
    stays = decided.groupBy("row_key1", "row_key2").agg(F.max("kept").alias("stays"), F.count("*").alias("times")).where("stays").drop("stays")
    keyed = docs.select(k1.alias("row_key1"), k2.alias("row_key2"), packed(docs).alias("row"))
    met = keyed.join(stays, ["row_key1", "row_key2"])
    more = met.where("times > 1").groupBy("row_key1", "row_key2").agg(F.first("row").alias("row"))
    return met.where("times = 1").select("row").unionByName(more.select("row")).select(*unpacked("row", docs.columns))


def hash_sample(df: DataFrame, wanted: int, *keys: str) -> DataFrame:
    """At most `wanted` rows of df, those with the least hash of the keys. A threshold on the hash, from the number of rows,
    leaves about twice as many to sort, so that no partition hands more than its share to the driver."""
    df = df.withColumn("__h", F.xxhash64(F.lit(11), *keys))
    rows, bits = df.count(), 1 << 40
    low = F.pmod(F.col("__h"), F.lit(bits))
    if rows > 4 * wanted + 1000:
        df = df.where(low < int(bits * (2 * wanted + 500) / rows))
    return df.orderBy(low, *keys).limit(wanted).drop("__h")
