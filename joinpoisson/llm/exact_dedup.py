"""Exact dedup by deterministic block naming, in DataFrame functions only.

A text without white space is cut into blocks of a fixed number of code points. The distinct blocks are
sorted and numbered; then the numbers of adjacent blocks are paired and the distinct pairs sorted and
numbered, level after level, until a text has one number. Texts of one level with equal numbers are equal,
for a block's number is only shared by equal blocks: the 128-bit hash that stands for a block in the sort is
checked against the blocks themselves, and blocks that share a hash are sorted by their content as well.

Cases: a null text counts as empty, all empty texts form one group; of rows that tie in length and doc_id
the first stays; a null doc_id comes after all others; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.llm.common import WHITE_CLASS, cut, hash128, keep_rows, row_key

BLOCK = 4096


def squeezed(text: Column) -> Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), WHITE_CLASS + "+", "")


def _blocks(norm: str, block: int) -> Column:
    starts = F.sequence(F.lit(1), F.greatest(F.length(norm), F.lit(1)), F.lit(block))
    return F.transform(starts, lambda i: F.substring(F.col(norm), i, F.lit(block)))


def _hashed(block: Column, bits: int | None) -> list[Column]:
    """bits: keep only so many of each hash, to bring about collisions in tests."""
    cut_to = lambda c: c if bits is None else c.bitwiseAND((1 << bits) - 1)
    return [cut_to(c).alias(n) for c, n in zip(hash128("h", block), ("h1", "h2"), strict=True)]


def block_identities(docs: DataFrame, carry: list[Column], block: int = BLOCK, hash_bits: int | None = None) -> DataFrame:
    """One row per row of docs (column text): row, level, name and the carried columns. Equal (level, name): equal texts."""
    texts = docs.select(*carry, squeezed(F.col("text")).alias("norm"))
    kept = [c for c in texts.columns if c != "norm"]
    pieces = texts.withColumn("blocks", _blocks("norm", block))
    exploded = pieces.select(F.explode("blocks").alias("b")).select(*_hashed(F.col("b"), hash_bits), "b")
    # The only step that moves text; equal blocks meet before it.
    variants = cut(exploded.groupBy("h1", "h2", "b").agg(F.count("*").alias("n")).groupBy("h1", "h2").agg(F.count("*").alias("variants"), F.max(F.length("b")).alias("longest")), "blocks")
    ambiguous = variants.where("variants > 1").select("h1", "h2")
    lists = pieces.withColumn("hs", F.transform("blocks", lambda b: F.struct(*_hashed(b, hash_bits))))
    lists = lists.select(F.monotonically_increasing_id().alias("row"), *kept, F.size("hs").alias("n_blocks"), "hs", *([] if ambiguous.isEmpty() else ["blocks"]))
    rows = cut(lists, "rows")
    if "blocks" in rows.columns:
        flat = rows.select("row", F.posexplode(F.arrays_zip("hs", "blocks")).alias("pos", "x")).select("row", "pos", "x.hs.h1", "x.hs.h2", F.col("x.blocks").alias("b"))
        doubtful = flat.join(ambiguous.withColumn("seen", F.lit(True)), ["h1", "h2"], "left")
        flat = cut(doubtful.select("row", "pos", "h1", "h2", F.when(F.col("seen"), F.col("b")).otherwise("").alias("b")), "flat")
        keys = ["h1", "h2", "b"]
    else:
        flat, keys = rows.select("row", F.posexplode("hs").alias("pos", "x")).select("row", "pos", "x.h1", "x.h2"), ["h1", "h2"]
    named = _name(flat, keys, "level0")
    most = rows.agg(F.max("n_blocks")).first()[0] or 0
    done, level = named.where("pos = 0").select("row", F.lit(0).alias("level"), "name"), 0
    sizes = rows.select("row", "n_blocks")
    while 1 << level < most:
        level += 1
        if level == 1:
            named = named.join(sizes.where("n_blocks > 1"), "row", "left_semi")
        half = F.when(F.col("pos") % 2 == 0, F.col("name")), F.when(F.col("pos") % 2 == 1, F.col("name"))
        pairs = named.groupBy("row", F.expr("pos div 2").cast("int").alias("pos")).agg(F.max(half[0]).alias("a"), F.coalesce(F.max(half[1]), F.lit(-1)).alias("z"))
        named = _name(pairs, ["a", "z"], f"level{level}")
        ended = named.join(sizes.where(f"n_blocks > {1 << (level - 1)} and n_blocks <= {1 << level}"), "row", "left_semi")
        done = done.join(sizes.where("n_blocks <= 1"), "row", "left_semi") if level == 1 else done
        done = done.unionByName(ended.where("pos = 0").select("row", F.lit(level).alias("level"), "name"))
        if 1 << level < most:
            named = cut(named.join(sizes.where(f"n_blocks > {1 << level}"), "row", "left_semi"), f"open{level}")
    return rows.drop("hs", "blocks").join(done, "row")


def _name(flat: DataFrame, keys: list[str], label: str) -> DataFrame:
    """row, pos, name: the place of the row's key among the sorted distinct keys (gaps between partitions)."""
    order = F.monotonically_increasing_id()
    names = cut(flat.select(*keys).distinct().repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("name", order), label)
    return cut(flat.join(names, keys).select("row", "pos", "name"), f"{label}-rows")


def exact_dedup(docs: DataFrame, block: int = BLOCK, hash_bits: int | None = None) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 and row_key1/2 (hash of the whole input row) for every row of docs."""
    k1, k2 = row_key(docs)
    carry = [F.col("doc_id"), F.length(F.coalesce(F.col("text"), F.lit(""))).cast("long").alias("points"), k1.alias("row_key1"), k2.alias("row_key2"), F.sha2(squeezed(F.col("text")), 256).alias("text_sha256")]
    ids = cut(block_identities(docs, carry, block, hash_bits), "identities")
    place = F.struct("points", F.col("doc_id").isNotNull(), -F.coalesce(F.col("doc_id"), F.lit(0)), -F.col("row"))
    groups = ids.groupBy("level", "name").agg(F.count("*").alias("group_size"), F.max(F.struct(place.alias("place"), "doc_id", "row")).alias("best"))
    out = ids.join(groups, ["level", "name"])
    return out.select("doc_id", F.col("best.doc_id").alias("keep_id"), "group_size", (F.col("row") == F.col("best.row")).alias("kept"), "text_sha256", "row_key1", "row_key2")


def keep_one_of_each(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """docs without the dropped copies, columns as given. Of rows that are equal throughout one stays."""
    return keep_rows(docs, exact_dedup(docs, block))
