"""MinHash near-dedup with ProbMinHash signatures.

A text's shingles are its runs of five words, weighted by 1 + ln(count). Every shingle is a Poisson process whose
rate is its weight; each arrival falls on one of REGISTERS registers, a register keeps the earliest arrival, and a
shingle stops once its next arrival is later than the latest register. Two texts agree in a register with the
probability Jaccard similarity of their weights. All texts of a batch run through the rounds of arrivals together.

Texts that agree in a band of registers are candidates. First each is paired with the representative of its bucket, the
text that shares most buckets with others (the hub of a group of near copies), and the pairs are verified on the exact
Jaccard similarity of the two shingle sets. Then come the buckets that still hold several classes. A text of which less
than the asked share of shingles stands in texts of other classes has no link to them and is settled. Of the others all
outside the largest class of a bucket are compared with all texts of the bucket, in blocks of bounded size that hold
their shingles: pairs of different classes whose registers agree in at least DOUBTFUL of all are verified in place, and
only links leave a block. So every pair that shares a band and may be a link is decided, whatever the size of its bucket.
Equal texts meet before.

Cases: a null text counts as empty; a text of fewer than five words is one shingle; empty texts are equal and form
one class; repeated rows belong to one class; ties go to the smaller doc_id, nulls last; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from joinpoisson.llm.common import cut, keep_rows, release, row_key
from joinpoisson.llm.components import components

WORDS, SIMILAR, REGISTERS, BAND_ROWS = 5, 0.8, 100, 5
#: Two texts at 0.8 agree in so few registers with a probability under one in a million (five standard deviations).
DOUBTFUL, LEFT_BLOCK, RIGHT_BLOCK = 0.6, 512, 1024
SHINGLES_PER_CHUNK = 400_000


def text_id(text: Column) -> Column:
    return F.unhex(F.md5(F.coalesce(text, F.lit("")).cast("binary")))


def word_hashes(text: Column) -> Column:
    return F.transform(F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0)), lambda w: F.xxhash64(w))


def mixed(x: np.ndarray) -> np.ndarray:
    """A bijective mixing of 64-bit integers (the finaliser of splitmix64)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def shingles(words: np.ndarray, n: int = WORDS) -> np.ndarray:
    """Hashes of the runs of n words; of all words where there are fewer."""
    w = words.view(np.uint64)
    n = min(n, len(w)) or 1
    out = np.zeros(max(0, len(w) - n + 1), np.uint64)
    for i in range(n):
        out = mixed(out * np.uint64(0x9E3779B97F4A7C15) + w[i : len(w) - n + 1 + i])
    return out


def signatures(sets: list[tuple[np.ndarray, np.ndarray]], registers: int = REGISTERS) -> np.ndarray:
    """For each (shingles, weights) the shingle that arrives first in each register; 0 throughout for no shingles."""
    count = len(sets)
    sizes = np.array([len(s) for s, _ in sets])
    first, winner = np.full(count * registers, np.inf), np.zeros(count * registers, np.uint64)
    who = np.repeat(np.arange(count), sizes)
    s = np.concatenate([x for x, _ in sets]) if count else np.zeros(0, np.uint64)
    rate = np.concatenate([w for _, w in sets]) if count else np.zeros(0)
    time = np.zeros(len(s))
    turn = 0
    while len(s):
        turn += 1
        h = mixed(s + np.uint64(turn * 0xD1342543DE82EF95 & 0xFFFFFFFFFFFFFFFF))
        time = time - np.log(((h >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53) / rate
        at = who * registers + (mixed(h ^ np.uint64(0x5851F42D4C957F2D)) % np.uint64(registers)).astype(np.int64)
        np.minimum.at(first, at, time)
        won = time == first[at]
        winner[at[won]] = s[won]
        active, place = np.unique(who, return_inverse=True)
        latest = first.reshape(count, registers)[active].max(axis=1)
        go = time < latest[place]
        s, rate, time, who = s[go], rate[go], time[go], who[go]
    return winner.reshape(count, registers)


def weighted(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    s, n = np.unique(shingles(words), return_counts=True)
    return s, 1.0 + np.log(n)


def jaccard(x: np.ndarray, y: np.ndarray) -> float:
    """Of two sorted sets."""
    if not len(x) or not len(y):
        return float(len(x) == len(y))
    if len(x) > len(y):
        x, y = y, x
    at = np.searchsorted(y, x)
    both = int((y[np.minimum(at, len(y) - 1)] == x).sum())
    return both / (len(x) + len(y) - both)


def _lists(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    return column.flatten().to_numpy(zero_copy_only=False), np.concatenate([[0], np.cumsum(np.asarray(pa.compute.list_value_length(column)))])


def band_keys(docs: DataFrame, registers: int = REGISTERS, rows: int = BAND_ROWS) -> DataFrame:
    """tid, the keys of its bands, a byte of each register and the number of shingles for every row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, ends = _lists(b.column(1))
            start = 0
            while start < b.num_rows:
                stop = max(start + 1, int(np.searchsorted(ends, ends[start] + SHINGLES_PER_CHUNK, "right")) - 1)
                sets = [weighted(flat[ends[i] : ends[i + 1]]) for i in range(start, stop)]
                sig = signatures(sets, registers)
                key = np.zeros((stop - start, registers // rows), np.uint64)
                for i in range(rows):
                    key = mixed(key * np.uint64(0x9E3779B97F4A7C15) + sig[:, i::rows][:, : key.shape[1]])
                offsets = pa.array(np.arange(0, key.size + 1, key.shape[1]), pa.int32())
                short = [x.tobytes() for x in (mixed(sig) & np.uint64(255)).astype(np.uint8)]
                columns = [pa.ListArray.from_arrays(offsets, pa.array(key.ravel().view(np.int64))), pa.array(short, pa.binary()), pa.array([len(x) for x, _ in sets], pa.int32())]
                yield pa.RecordBatch.from_arrays([b.column(0).slice(start, stop - start), *columns], names=["tid", "bands", "sig", "n"])
                start = stop

    return docs.select(text_id(F.col("text")).alias("tid"), word_hashes(F.col("text")).alias("w")).mapInArrow(run, "tid binary, bands array<bigint>, sig binary, n int")


def shingle_sets(texts: DataFrame) -> DataFrame:
    """tid and the sorted set of shingles for every row of texts (tid, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, ends = _lists(b.column(1))
            sets = [np.unique(shingles(flat[ends[i] : ends[i + 1]])) for i in range(b.num_rows)]
            offsets = pa.array(np.concatenate([[0], np.cumsum([len(x) for x in sets])]), pa.int32())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.ListArray.from_arrays(offsets, pa.array(np.concatenate([*sets, np.zeros(0, np.uint64)]).view(np.int64)))], names=["tid", "set"])

    return texts.select("tid", word_hashes(F.col("text")).alias("w")).mapInArrow(run, "tid binary, set array<bigint>")


def verified(pairs: DataFrame, sets: DataFrame, similar: float = SIMILAR) -> DataFrame:
    """The pairs (a, b) of text ids whose shingle sets are similar, with jaccard. sets: tid, set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            (x, xe), (y, ye) = _lists(b.column(2)), _lists(b.column(3))
            x, y = x.view(np.uint64), y.view(np.uint64)
            found = [jaccard(x[xe[i] : xe[i + 1]], y[ye[i] : ye[i + 1]]) for i in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(found, pa.float64())], names=["a", "b", "jaccard"])

    one = pairs.select("a", "b").join(sets.select(F.col("tid").alias("a"), F.col("set").alias("sa")), "a")
    two = one.join(sets.select(F.col("tid").alias("b"), F.col("set").alias("sb")), "b")
    return two.select("a", "b", "sa", "sb").mapInArrow(run, "a binary, b binary, jaccard double").where(F.col("jaccard") >= similar)


def near_classes(docs: DataFrame, similar: float = SIMILAR, registers: int = REGISTERS, rows: int = BAND_ROWS) -> DataFrame:
    """(tid, root) for the texts of docs that are in a class with another text."""
    bands = cut(band_keys(docs, registers, rows), "bands")
    once = cut(bands.groupBy("tid").agg(*[F.first(c).alias(c) for c in ("bands", "sig", "n")]), "signatures")
    release(bands)
    members = once.select("tid", "n", F.posexplode("bands").alias("band", "key"))
    crowded = members.groupBy("band", "key").agg(F.count("*").alias("held")).where("held > 1")
    met = cut(members.join(crowded, ["band", "key"]), "crowded")
    hubs = met.groupBy("tid").agg(F.sum("held").alias("weight"))
    open_ = cut(met.join(hubs, "tid"), "members")
    release(met)
    texts = docs.select(text_id(F.col("text")).alias("tid"), F.coalesce("text", F.lit("")).alias("text")).join(open_.select("tid"), "tid", "left_semi")
    sets = cut(shingle_sets(texts.dropDuplicates(["tid"])), "shingles")
    lead = F.max(F.struct("weight", F.xxhash64("tid").alias("h"), "tid", "n")).alias("lead")
    heads = open_.groupBy("band", "key").agg(lead).select("band", "key", F.col("lead.tid").alias("b"), F.col("lead.n").alias("nb"))
    alike = F.least("n", "nb") >= F.greatest("n", "nb") * similar  # else the sizes alone forbid the similarity
    pairs = cut(open_.join(heads, ["band", "key"]).where((F.col("tid") != F.col("b")) & alike).select(F.greatest("tid", "b").alias("a"), F.least("tid", "b").alias("b")).distinct(), "pairs")
    links = cut(verified(pairs, sets, similar).select("a", "b"), "links")
    roots = components(links)
    more = cut(links_between_classes(open_, once, sets, roots, registers, rows, similar), "links")
    out = roots if more.isEmpty() else components(links.unionByName(more))
    release(open_, once, sets, pairs)
    return out


def _in_other_classes(rooted: DataFrame, sets: DataFrame, similar: float) -> DataFrame:
    """tid of the texts of rooted (band, key, tid, root) that may have a link to another class: in their buckets there is
    one, and enough of their shingles stand in texts of other classes. At a similarity s two sets share s of either."""
    several = rooted.groupBy("band", "key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo != hi").select("band", "key")
    asked = rooted.join(several, ["band", "key"], "left_semi").select("tid", "root").distinct()
    held = cut(asked.join(sets, "tid"), "asked")
    each = held.select("tid", "root", F.explode("set").alias("s"))
    met = each.groupBy("s").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo != hi").select("s")
    found = each.select("tid", "s").join(met, "s", "left_semi").groupBy("tid").agg(F.count("*").alias("met"))
    out = held.select("tid", F.size("set").alias("n")).join(found, "tid").where(F.col("met") >= F.col("n") * similar).select("tid")
    out = cut(out, "alive")
    release(held)
    return out


def links_between_classes(members: DataFrame, once: DataFrame, sets: DataFrame, roots: DataFrame, registers: int, rows: int, similar: float) -> DataFrame:
    """The links (a, b) of texts in one bucket but different classes, each from the first bucket that the two share.
    members: band, key, tid; once: tid, sig; sets: tid, set; roots: node, root."""
    rooted = members.select("band", "key", "tid").join(roots.withColumnRenamed("node", "tid"), "tid", "left").withColumn("root", F.coalesce("root", "tid"))
    rooted = cut(rooted, "rooted")
    rooted = rooted.join(_in_other_classes(rooted, sets, similar), "tid", "left_semi")
    sizes = rooted.groupBy("band", "key", "root").agg(F.count("*").alias("c"))
    buckets = sizes.groupBy("band", "key").agg(F.count("*").alias("classes"), F.sum("c").alias("total"), F.max(F.struct("c", "root")).alias("big")).where("classes > 1")
    buckets = buckets.select("band", "key", F.col("big.root").alias("big"), F.ceil(F.col("total") / RIGHT_BLOCK).cast("int").alias("rights"), F.ceil((F.col("total") - F.col("big.c")) / LEFT_BLOCK).cast("int").alias("lefts"))
    held = rooted.join(buckets, ["band", "key"]).join(once.select("tid", "sig"), "tid").join(sets, "tid")
    deal = lambda n: F.pmod(F.xxhash64("band", "tid"), F.col(n)).cast("int")
    each = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    whole = ["band", "key", "tid", "root", "sig", "set"]
    left = held.where("root != big").select(*whole, F.lit(0).alias("side"), deal("lefts").alias("lb"), each("rights").alias("rb"))
    right = held.select(*whole, F.lit(1).alias("side"), each("lefts").alias("lb"), deal("rights").alias("rb"))
    dealt = left.unionByName(right).select("band", "key", "lb", "rb", "side", "tid", "root", "sig", "set")
    least = int(DOUBTFUL * registers)

    def compare(group: pa.Table) -> tuple[list, list]:
        side = group.column("side").to_numpy()
        cut_at = int((side == 0).sum())
        if not cut_at or cut_at == len(side):
            return [], []
        tid, root = group.column("tid").to_pylist(), group.column("root").to_pylist()
        sig = np.frombuffer(b"".join(group.column("sig").to_pylist()), np.uint8).reshape(len(side), -1)
        flat, ends = _lists(group.column("set").combine_chunks())
        flat, n, band = flat.view(np.uint64), np.diff(ends), group.column("band")[0].as_py()
        names = {r: i for i, r in enumerate(set(root))}
        kind = np.array([names[r] for r in root])
        a, b = [], []
        for i in range(cut_at):
            may = np.flatnonzero((kind[cut_at:] != kind[i]) & (np.minimum(n[cut_at:], n[i]) >= similar * np.maximum(n[cut_at:], n[i]))) + cut_at
            if not len(may):
                continue
            same = sig[may] == sig[i]
            earlier = np.zeros(len(may), bool)
            for k in range(band):
                earlier |= same[:, k * rows : (k + 1) * rows].all(axis=1)
            own = flat[ends[i] : ends[i + 1]]
            for j in may[(same.sum(axis=1) >= least) & ~earlier]:
                if jaccard(own, flat[ends[j] : ends[j + 1]]) >= similar:
                    a.append(max(tid[i], tid[j]))
                    b.append(min(tid[i], tid[j]))
        return a, b

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for groups in _groups(batches, ("band", "key", "lb", "rb")):
            found = [compare(g) for g in groups]
            yield pa.RecordBatch.from_arrays([pa.array([x for f in found for x in f[k]], pa.binary()) for k in (0, 1)], names=["a", "b"])

    keys = ["band", "key", "lb", "rb"]
    return dealt.repartition(*keys).sortWithinPartitions(*keys, "side").mapInArrow(run, "a binary, b binary")


def _groups(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...]) -> Iterator[list[pa.Table]]:
    """The groups of equal keys of sorted batches, a list of whole ones at a time."""
    kept: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        kept.append(b)
        table = pa.Table.from_batches(kept)
        columns = [table.column(k).to_numpy() for k in keys]
        starts = np.flatnonzero(np.logical_or.reduce([c[1:] != c[:-1] for c in columns])) + 1
        if len(starts):
            ends = [0, *starts.tolist()]
            yield [table.slice(i, j - i) for i, j in zip(ends, ends[1:], strict=False)]
            kept = table.slice(ends[-1]).to_batches()
    if kept:
        yield [pa.Table.from_batches(kept)]


def near_dedup(docs: DataFrame, **settings) -> DataFrame:
    """doc_id, class_id (least doc_id of the class), class_size, kept and row_key1/2 for every row of docs."""
    k1, k2 = row_key(docs)
    rows = cut(docs.select("doc_id", text_id(F.col("text")).alias("tid"), k1.alias("row_key1"), k2.alias("row_key2")).withColumn("row", F.monotonically_increasing_id()), "near-rows")
    roots = near_classes(docs, **settings).select(F.col("node").alias("tid"), "root")
    rooted = cut(rows.join(roots, "tid", "left").withColumn("root", F.coalesce("root", "tid")), "near-rooted")
    order = F.struct(F.col("doc_id").isNull().alias("absent"), "doc_id", "row")
    classes = cut(rooted.groupBy("root").agg(F.min(order).alias("lead"), F.count("*").alias("class_size")), "near-groups")
    out = rooted.join(classes, "root")
    return out.select("doc_id", F.col("lead.doc_id").alias("class_id"), "class_size", (F.col("row") == F.col("lead.row")).alias("kept"), "row_key1", "row_key2")


def keep_one_of_each(docs: DataFrame, **settings) -> DataFrame:
    """docs with one document of each class, columns as given."""
    return keep_rows(docs, near_dedup(docs, **settings))
