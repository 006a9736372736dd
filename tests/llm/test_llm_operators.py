"""The training-data operators against brute force, and on nulls, empty, long, tied and repeated rows and clashing names."""

import hashlib
import math
import random
import re
import time
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from joinpoisson.llm import exact_dedup, line_dedup, minhash_dedup, mixing, sentencepiece_codec, sharding, substring_dedup, topk_search, toxicity, url_filter
from joinpoisson.llm.components import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^ \t-\r]+")


def words(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefghij") for _ in range(5)) for _ in range(n))


def odd_rows():
    """Nulls in every column, empty and very long texts, ties, repeated rows."""
    long = words(30_000, 1)
    rows = [(1, "one two three four five six", "en", "a", 3), (2, None, None, None, None), (3, "", "en", "b", 0), (None, "no id here at all my friend", "en", "a", 1), (5, long, "en", "b", 9)]
    rows += [(6, "one  two three\tfour five six", "en", "a", 3), (7, long + " ", "de", None, 9), (7, long + " ", "de", None, 9), (8, "x", "en", "c", 1), (8, "y", "en", "c", 1), (9, " \n\n ", "en", "a", 4), (10, "Ünïcode ▁ 😀 text\x00 here ok", "fr", "a", 5)]
    return rows


def frame(spark, rows, extra=True):
    df = spark.createDataFrame(rows, DOCS)
    if extra:  # names that clash with inner ones
        df = df.select("*", *[F.lit(k).alias(n) for k, n in enumerate(("row", "size", "w", "tid", "part", "shard", "key", "times", "score", "name", "level", "__k1", "__K2", "__times", "__copies", "__again", "__lines", "N_lines", "kept_text", "row_key1", "k1", "c0", "a.b", "x`y"))])
    return df


@pytest.fixture(scope="module")
def odd(spark):
    return frame(spark, odd_rows())


@pytest.fixture(scope="module")
def none(spark):
    return frame(spark, [])


def white_free(t):
    return re.sub(r"[ \t-\r]", "", t or "")


def expected_exact(rows):
    groups = defaultdict(list)
    for i, r in enumerate(rows):
        groups[white_free(r[1])].append((-len(r[1] or ""), r[0] is None, r[0] or 0, i))
    keep = {k: min(v) for k, v in groups.items()}
    return Counter((r[0], len(groups[white_free(r[1])]), hashlib.sha256(white_free(r[1]).encode()).hexdigest()) for r in rows), {k: v[3] for k, v in keep.items()}


@pytest.mark.parametrize(("block", "bits"), [(4096, None), (4, None), (3, 2), (7, 0)])
def test_block_naming_is_free_of_collisions(spark, odd, block, bits):
    """Few hash bits make most blocks share a hash; the names must still tell them apart."""
    rows = odd_rows()
    if block < 100:
        rows = [r for r in rows if len(r[1] or "") < 1000] + [(20 + k, "abcd" * k + "x" * (k % 3), "en", "a", 1) for k in range(12)]
    got = exact_dedup.exact_dedup(frame(spark, rows), block, bits).collect()
    want, keep = expected_exact(rows)
    assert Counter((r.doc_id, r.group_size, r.text_sha256) for r in got) == want
    assert sum(r.kept for r in got) == len(keep)
    ids = {white_free(rows[i][1]): rows[i][0] for i in keep.values()}
    by_hash = {hashlib.sha256(k.encode()).hexdigest(): v for k, v in ids.items()}
    assert all(r.keep_id == by_hash[r.text_sha256] for r in got)


def test_exact_dedup_stage_keeps_columns_and_one_of_repeated_rows(spark, odd, none):
    kept = exact_dedup.keep_one_of_each(odd)
    assert kept.columns == odd.columns
    texts = [white_free(r.text) for r in kept.collect()]
    assert len(texts) == len(set(texts)) == len({white_free(r[1]) for r in odd_rows()})
    assert exact_dedup.keep_one_of_each(none).count() == 0 and exact_dedup.exact_dedup(none).count() == 0


def test_line_dedup_matches_brute_force(spark, none):
    rows = [(i, f"Head Line\nown {i}\n  head line \t\n\nfoot", "en", "a", 1) for i in range(9)] + [(9, "foot\n" * 3, "en", "a", 1), (10, None, None, None, None), (11, "", "en", "a", 0), (12, "HEAD LINE", "x", "y", 1), (12, "HEAD LINE", "x", "y", 1)]
    got = {(r.doc_id, r.n_lines, r.n_dropped, r.kept_text) for r in line_dedup.line_dedup(frame(spark, rows, extra=False)).collect()}
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").lower()
    seen = Counter(k for _, k in {(r[0], key(x)) for r in rows for x in (r[1] or "").split("\n")})
    want = set()
    for r in rows:
        lines = (r[1] or "").split("\n")
        left = [x for x in lines if not (key(x) and seen[key(x)] >= 10)]
        want.add((r[0], len(lines), len(lines) - len(left), "\n".join(left)))
    assert got == want
    assert line_dedup.line_dedup(none).count() == 0
    again = [(1, "same line", "en", "a", 1)] * 12  # one document
    assert {(r.n_dropped, r.kept_text) for r in line_dedup.line_dedup(frame(spark, again, extra=False)).collect()} == {(0, "same line")}


def test_line_dedup_of_a_text_of_many_lines(spark):
    """Time in proportion to the lines: a text of 100,000 lines, every third of them frequent, in seconds."""
    lines = [f"line {i}" for i in range(100_000)]
    docs = spark.createDataFrame([(0, "\n".join(lines))] + [(k, "\n".join(lines[::3])) for k in range(1, 10)], "doc_id long, text string")
    began = time.time()
    got = {r.doc_id: (r.n_lines, r.n_dropped, r.kept_text) for r in line_dedup.line_dedup(docs).collect()}
    assert time.time() - began < 60
    assert got[0] == (100_000, 33_334, "\n".join(x for i, x in enumerate(lines) if i % 3)) and got[1][1:] == (33_334, "")


def test_line_runs_are_read_without_an_exchange(spark):
    from joinpoisson.operators.metrics import plan_shape

    store = line_dedup.LineRuns(spark, fanout=3)
    for b in range(2):
        store.ingest(spark.range(b, 50 + b).select(F.col("id").alias("h1"), F.col("id").alias("h2")))
    first, second = store.runs()
    assert plan_shape(first.join(second, line_dedup.KEY))["Exchange"] == 0


def test_line_runs_compact_and_tell_new_keys(spark):
    store = line_dedup.LineRuns(spark, fanout=2)
    for b in range(5):
        keys = spark.createDataFrame([(k, k) for k in range(b, b + 3)], "h1 long, h2 long")
        run = store.ingest(keys)
        assert {r.h1 for r in run.where("is_new").collect()} == ({0, 1, 2} if b == 0 else {b + 2})
    assert [len(x) for x in store.levels] == [1, 0, 1]
    assert {r.h1: r.n for r in store.counts().collect()} == {0: 1, 1: 2, 2: 3, 3: 3, 4: 3, 5: 2, 6: 1}


def test_mixing_hits_targets_and_reruns_agree(spark, odd, none):
    r = random.Random(3)
    rows = [(i, words(r.randint(1, 60), i), "en", f"s{min(3, int(r.expovariate(1)))}", 1) for i in range(900)] + [(-1, None, None, None, None), (-2, "", None, "empty", 0)]
    df = frame(spark, rows)
    got = mixing.digest(df).collect()
    assert len(got) == len(rows) and all(x.taken <= 2 * x.size for x in got)
    again = mixing.digest(df.repartition(7)).collect()
    assert Counter((x.doc_id, x.taken) for x in got) == Counter((x.doc_id, x.taken) for x in again)
    sizes, taken, target = Counter(), Counter(), {}
    for x in got:
        sizes[x.source] += x.size
        taken[x.source] += x.taken
        target[x.source] = x.target
    total = sum(sizes.values())
    assert abs(sum(target.values()) - 1.5 * total) < 1e-6
    assert all(target[s] <= 2 * sizes[s] + 1e-9 and abs(taken[s] - target[s]) <= 65 for s in sizes)
    mixed = Counter(x.doc_id for x in mixing.mix(df).collect())
    for x in got:
        assert mixed[x.doc_id] * x.size == x.taken
    assert mixing.mix(odd).columns == odd.columns and len(mixing.digest(odd).collect()) == len(odd_rows())
    assert mixing.digest(none).count() == 0 and mixing.mix(none).count() == 0


def test_targets_are_the_limit_of_resharing(spark):
    sizes = {"a": 100, "b": 1000, "c": 50, "d": 400}
    got = {r.source: r.target for r in mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long")).collect()}
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(sorted(sizes))}
    want, left, open_ = dict.fromkeys(sizes, 0.0), 1.5 * sum(sizes.values()), set(sizes)
    while left > 1e-9 and open_:
        share, over = sum(weight[s] for s in open_), 0.0
        for s in list(open_):
            want[s] += left * weight[s] / share
            if want[s] >= 2 * sizes[s]:
                over += want[s] - 2 * sizes[s]
                want[s] = 2.0 * sizes[s]
        left, open_ = over, {s for s in open_ if want[s] < 2 * sizes[s]}
    assert all(abs(got[s] - want[s]) < 1e-6 for s in sizes)


def greedy(sizes, capacity):
    parts, now = 1, 0
    for s in sizes:
        if s > capacity:
            return 1 << 30
        if now + s > capacity:
            parts, now = parts + 1, 0
        now += s
    return parts


@pytest.mark.parametrize("bits", [12, 3])
def test_minimax_capacity_is_the_least(spark, odd, none, bits, monkeypatch):
    monkeypatch.setattr(sharding.EndGrid.__init__, "__defaults__", (bits,))
    r = random.Random(5)
    rows = [(i, words(r.randint(1, 40), i % 211), "en", "a", 1) for i in range(400)]
    got = sharding.minimax_shards(frame(spark, rows), 9).collect()
    assert len(got) == len(rows) and {x.shard for x in got} <= set(range(9))
    where = defaultdict(set)
    load, slots = Counter(), defaultdict(set)
    for x in got:
        where[rows[x.doc_id][1]].add(x.shard)
        load[x.shard] += x.size
        slots[x.shard].add(x.slot)
    assert all(len(s) == 1 for s in where.values())
    assert all(s == set(range(len(s))) for s in slots.values())
    groups = defaultdict(int)
    for row in rows:
        groups[hashlib.sha256(row[1].encode()).digest()] += len(row[1]) + 16
    ordered = [groups[k] for k in sorted(groups)]
    want = next(c for c in range(max(ordered), sum(ordered) + 1) if greedy(ordered, c) <= 9)
    assert {x.capacity for x in got} == {want} and max(load.values()) == want
    assert len(sharding.minimax_shards(odd).collect()) == len(odd_rows()) and sharding.minimax_shards(none).count() == 0


def test_oversized_groups_get_shards_of_their_own(spark):
    rows = [(i, "same text " * 20, "en", "a", 1) for i in range(50)] + [(100 + i, words(5, i), "en", "a", 1) for i in range(40)]
    got = sharding.minimax_shards(frame(spark, rows), 8).collect()
    big = {x.shard for x in got if x.doc_id < 100}
    assert big == {0} and len({x.shard for x in got if x.doc_id >= 100}) == 7


def test_url_rules_match_brute_force(spark):
    r = random.Random(9)
    labels = ["a", "b", "net", "org", "com", "example", "x-y", "ab"]
    rules = [(".".join(r.choice(labels) for _ in range(r.randint(1, 3))), r.choice(["/", "/a", "/a/b", "/en/"]), r.choice(["block", "allow"])) for _ in range(60)]
    urls = [f"http://{'.'.join(r.choice(labels) for _ in range(r.randint(1, 5))).upper() if i % 9 == 0 else '.'.join(r.choice(labels) for _ in range(r.randint(1, 5)))}{r.choice(['', '/', '/a', '/a/b/c', '/en/x', '?q=://z', '#f'])}" for i in range(600)]
    rows = [(i, u, "<html>") for i, u in enumerate(urls)] + [(900, None, None), (901, "no scheme", "x"), (902, "", None), (None, "http://a.net/", None), (903, "http://", None), (904, "a://b\nc/d\ne", None)]
    got = url_filter.judge(spark.createDataFrame(rows, "page_id long, url string, html string"), url_filter.rules_frame(spark, rules)).collect()
    merged = {}
    for h, p, a in rules:
        merged[h, p] = "block" if merged.get((h, p)) == "block" else a
    assert len(got) == len(rows)
    byid = {x.page_id: x for x in got}
    for i, u, _ in rows:
        m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", u or "")
        host, path = ("".join(c.lower() if c.isascii() else c for c in m[1]), m[2]) if m else ("", "")
        fits = [(len(h) + len(p), len(h), h, p, a) for (h, p), a in merged.items() if (host == h or host.endswith("." + h)) and path.startswith(p)]
        x = byid[i]
        assert (x.host, x.path) == (host, path)
        assert (x.rule, x.verdict) == ((max(fits)[2] + max(fits)[3], max(fits)[4]) if fits else (None, "allow"))
    empty = spark.createDataFrame([], "page_id long, url string")
    assert url_filter.judge(empty, url_filter.rules_frame(spark)).count() == 0


@pytest.mark.parametrize("sizes", [(1024, 8192), (7, 11)])
def test_topk_is_exact(spark, sizes):
    r = np.random.default_rng(1)
    vectors = [(int(i), [float(x) for x in v]) for i, v in enumerate(r.normal(size=(230, 8)) / 2)]
    vectors[40] = (40, vectors[20][1])
    vectors += [(300, None), (320, [1.0, None] + [0.0] * 6), (340, [float("nan")] * 8), (360, [float("inf")] * 8), (380, [0.5] * 3), (400, vectors[0][1]), (20, vectors[3][1]), (None, [0.1] * 8)]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<float>")
    got = topk_search.digest(df, k=5, query_block=sizes[0], block=sizes[1], sample=50)
    # A shorter vector counts as having zeros behind.
    ok = [(i, np.floor(np.float32(v + [0.0] * (8 - len(v))).astype(np.float64) * 64).astype(int)) for i, v in vectors if i is not None and v is not None and None not in v and np.isfinite(v).all()]
    want = Counter()
    for q, v in ok:
        if q % 20 == 0:
            best = sorted((-int(v @ u), i) for i, u in ok if i != q)[:5]
            want.update((q, k + 1, i, -s) for k, (s, i) in enumerate(best))
    assert Counter((x.query_id, x["rank"], x.vec_id, x.score) for x in got.collect()) == want
    assert topk_search.digest(df.where("false")).count() == 0


def test_topk_of_large_components_and_unequal_lengths(spark):
    r = random.Random(3)
    rows = [(i, [r.choice((1e9, -1e9, 3.0, 0.5)) for _ in range(3 - i % 2)]) for i in range(60)] + [(60, []), (61, None), (62, [float("nan")]), (63, [None, 1.0])]
    whole = {i: [math.floor(64 * x) for x in v] for i, v in rows if i <= 60}
    want = []
    for q in whole:
        if q % 20 == 0:
            scored = sorted((-sum(a * b for a, b in zip(whole[q], v, strict=False)), i) for i, v in whole.items() if i != q)[:20]
            want += [(q, k, i, max(-(1 << 63), min((1 << 63) - 1, -s))) for k, (s, i) in enumerate(scored, 1)]
    clipped = defaultdict(list)
    for q, _, i, s in want:
        clipped[q].append((s, i))
    got = topk_search.digest(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    assert sorted((x.query_id, x.rank, x.score) for x in got) == sorted((q, k, s) for q, v in clipped.items() for k, s in enumerate(sorted((s for s, _ in v), reverse=True), 1))


def test_pivots_exclude_clustered_candidates():
    r = np.random.default_rng(2)
    x = np.concatenate([np.rint(r.normal(size=(2000, 6)) + 40 * c) for c in np.eye(6)]).astype(np.int64)
    table = topk_search.PivotTable(x[::20], 8, float((x**2).sum(1).max()))
    q = x[:5]
    *_, made = topk_search.best_of_block(table, 10, np.arange(5), q, np.full(5, -(1 << 62)), np.arange(len(x)), x)
    assert made < 0.6 * 5 * len(x)


def jaccard(a, b):
    sets = []
    for t in (a, b):
        w = WORD.findall(t)
        n = min(5, len(w)) or 1
        sets.append({tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set())
    return len(sets[0] & sets[1]) / len(sets[0] | sets[1]) if sets[0] | sets[1] else 1.0


def near_rows():
    rows = []
    for i in range(40):
        base = words(120, i).split()
        for k in range(1 + i % 4):
            t = list(base)
            for j in range(k):
                t[(37 * j + 11) % len(t)] = f"new{k}{j}"
            rows.append((100 * i + k, " ".join(t), "en", "a", 1))
    return rows + odd_rows()


def test_near_classes_match_brute_force(spark):
    rows = near_rows()
    got = minhash_dedup.near_dedup(frame(spark, rows)).collect()
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if jaccard(rows[i][1] or "", rows[j][1] or "") >= 0.8:
                parent[find(i)] = find(j)
    sizes = Counter(find(i) for i in range(len(rows)))
    assert Counter((r[0], sizes[find(i)]) for i, r in enumerate(rows)) == Counter((x.doc_id, x.class_size) for x in got)
    assert sum(x.kept for x in got) == len(sizes)


def test_near_pairs_in_a_template_family(spark):
    base, rows, used = words(600, 1).split(), [], []
    r = random.Random(8)
    while len(rows) < 120:
        spots = r.sample(range(5, 590, 6), 14)
        sides = [{*spots[:2], *spots[2 + 6 * k : 8 + 6 * k]} for k in (0, 1)]
        if all(len(s & u) < 3 for s in sides for u in used):  # others are below 0.8
            used += sides
            n = len(rows)
            rows += [(n + k, " ".join(f"pair{n}spot{i}" if i in s else w for i, w in enumerate(base)), "en", "a", 1) for k, s in enumerate(sides)]
    alike = [jaccard(rows[2 * k][1], rows[2 * k + 1][1]) for k in range(60)]
    assert min(alike) >= 0.8 and max(jaccard(rows[0][1], t[1]) for t in rows[2:]) < 0.8
    got = {x.doc_id: x.class_id for x in minhash_dedup.near_dedup(frame(spark, rows)).collect()}
    assert got == {i: i - i % 2 for i in range(120)}


def test_stages_keep_rows_and_values_of_clashing_columns(spark):
    """Different texts all come back, with the values of columns that have the names that the stages use inside."""
    rows = [(i, words(30, i), "en", "a", 1) for i in range(6)]
    docs = frame(spark, rows)
    want = sorted(tuple(x) for x in docs.collect())
    assert sorted(tuple(x) for x in exact_dedup.keep_one_of_each(docs).collect()) == want
    assert sorted(tuple(x) for x in minhash_dedup.keep_one_of_each(docs).collect()) == want
    mixed = [tuple(x) for x in mixing.mix(docs).collect()]
    assert set(mixed) <= set(want) and mixed and mixing.mix(docs).columns == docs.columns
    done = line_dedup.line_dedup(docs)
    assert sorted(tuple(x)[: len(docs.columns)] for x in done.collect()) == want
    assert done.columns[len(docs.columns) :] == ["n_lines_", "n_dropped", "kept_text_"]


def test_near_dedup_stage_keeps_one_of_each(spark, odd, none):
    kept = minhash_dedup.keep_one_of_each(odd)
    assert kept.columns == odd.columns and kept.count() == minhash_dedup.near_dedup(odd).where("kept").count() == 7
    assert minhash_dedup.keep_one_of_each(none).count() == 0


def test_signatures_estimate_weighted_similarity():
    r = np.random.default_rng(4)
    a = (np.arange(1, 301, dtype=np.uint64) * np.uint64(7919), r.uniform(0.5, 3, 300))
    b = (np.arange(61, 361, dtype=np.uint64) * np.uint64(7919), r.uniform(0.5, 3, 300))
    sig = minhash_dedup.signatures([a, b], 4000)
    wa, wb = dict(zip(a[0].tolist(), a[1], strict=True)), dict(zip(b[0].tolist(), b[1], strict=True))
    keys = set(wa) | set(wb)
    want = sum(1 / sum(max(wa.get(y, 0) / wa[x], wb.get(y, 0) / wb[x]) for y in keys) for x in set(wa) & set(wb))
    assert abs((sig[0] == sig[1]).mean() - want) < 0.03


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 102), (200, 200), (102, 100)]
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == dict.fromkeys(range(41), 0) | {100: 100, 101: 100, 102: 100}


def test_passages_are_found_and_clean_texts_left_alone(spark, odd, none):
    passage = words(60, 77).split()
    fuzzy = passage[:20] + ["changed"] + passage[21:40] + passage[41:]
    rows = [(1, f"{words(80, 1)} {' '.join(passage)} {words(30, 2)}", "en", "a", 1), (2, f"{words(10, 3)} {' '.join(fuzzy)}", "en", "a", 1), (3, words(300, 4), "en", "a", 1), (4, f"{' '.join(passage[:30])} {words(90, 5)}", "en", "a", 1), (5, words(300, 4), "de", "b", 1), (6, "again " * 80, "en", "a", 1), (7, f"{words(20, 8)} {'again ' * 70}", "en", "a", 1), (8, words(200, 9), "en", "a", 1)]
    got = substring_dedup.substring_dedup(frame(spark, rows)).collect()
    pairs = {frozenset((x.doc_id, x.match_doc_id)) for x in got}
    assert pairs == {frozenset((1, 2)), frozenset((3, 5)), frozenset((6, 7))}
    x = next(x for x in got if {x.doc_id, x.match_doc_id} == {1, 2})
    span = {x.doc_id: (x.start_word, x.n_words), x.match_doc_id: (x.match_start, x.match_words)}
    assert span == {1: (80, 60), 2: (10, 59)} and x.same_words == 58
    assert {frozenset((x.doc_id, x.match_doc_id)) for x in substring_dedup.substring_dedup(odd).collect()} == {frozenset((5, 7)), frozenset((7,))}
    assert substring_dedup.substring_dedup(none).count() == 0


def test_a_passage_is_found_past_the_first_texts_with_its_seeds(spark):
    rows, wanted = [], set()
    for k in range(12):
        p = words(70, 5000 + k).split()
        z1, z2 = [f"{words(20, 6000 + 10 * k)} {' '.join(h)} {words(20, 6001 + 10 * k)}" for h in (p[:35], p[35:])]
        a, b = f"{words(30, 6002 + 10 * k)} {' '.join(p)}", f"{' '.join(p)} {words(30, 6003 + 10 * k)}"
        rows += [(4 * k + i, t, "en", "a", 1) for i, t in enumerate((z1, z2, a, b))]
        wanted.add(frozenset((4 * k + 2, 4 * k + 3)))
    got = substring_dedup.substring_dedup(frame(spark, rows)).collect()
    assert {frozenset((x.doc_id, x.match_doc_id)) for x in got} == wanted and all(x.n_words == x.same_words == 70 for x in got)


def test_a_passage_is_found_past_many_texts_with_its_seeds(spark):
    """More texts than DEEP hold parts of the passage, too short to be passages, ahead of the two that hold it."""
    rows, wanted, n = [], set(), substring_dedup.DEEP + 4
    for k, cuts in enumerate(((0, 25, 30), (0, 15, 30), (0, 20, 30))):
        p = words(75, 7000 + k).split()
        parts = [p[i : i + 45] for i in cuts]
        texts = [f"{words(20, 7100 + 1000 * k + 10 * i + j)} {' '.join(h)} {words(20, 7105 + 1000 * k + 10 * i + j)}" for i in range(n) for j, h in enumerate(parts)]
        texts += [f"{words(30, 7010 + k)} {' '.join(p)}", f"{' '.join(p)} {words(30, 7020 + k)}"]
        rows += [(1000 * k + i, t, "en", "a", 1) for i, t in enumerate(texts)]
        wanted.add(frozenset((1000 * k + len(texts) - 2, 1000 * k + len(texts) - 1)))
    got = substring_dedup.substring_dedup(frame(spark, rows)).collect()
    assert {frozenset((x.doc_id, x.match_doc_id)) for x in got} == wanted and all(x.n_words == x.same_words == 75 for x in got)


def test_pairs_of_many_texts_are_aligned_a_part_at_a_time(spark, monkeypatch):
    """More texts than DEEP share parts of a passage: the pairs left for the last round are cut into parts, with the same passages."""
    p = words(45, 8000)
    texts = [f"{words(60, 8100 + 2 * i)} {p} {words(60, 8101 + 2 * i)}" for i in range(24)]
    long = words(75, 8001).split()
    texts += [f"{words(20, 8300 + i)} {' '.join(long[:45])} {words(20, 8400 + i)}" for i in range(20)]
    texts += [f"{words(30, 8010)} {' '.join(long)}", f"{' '.join(long)} {words(30, 8020)}"]
    docs = frame(spark, [(i, t, "en", "a", 1) for i, t in enumerate(texts)])
    made, whole = [], substring_dedup.aligned
    monkeypatch.setattr(substring_dedup, "aligned", lambda pairs, *a: (made.append(pairs.count()), whole(pairs, *a))[1])
    found = []
    for room in (1 << 40, 1):
        made.clear()
        monkeypatch.setattr(substring_dedup, "PART_BYTES", room, raising=False)
        found.append((sorted(map(tuple, substring_dedup.substring_dedup(docs).collect())), made[:3], made[3:]))
    (one, first, last), (parts, again, each) = found
    assert one == parts and len(one) == 1 and first == again
    assert len(last) == 1 < len(each) and sum(each) == last[0] > max(each)


@pytest.mark.parametrize("every", [6, 7, 8, 10, 20])
def test_passages_are_found_at_each_identity(spark, every):
    rows = []
    for k in range(20):
        p = words(60, 9000 + k).split()
        q = [f"other{k}x{i}" if i % every == every - 1 and i < 59 else w for i, w in enumerate(p)]
        rows += [(2 * k, f"{words(20, 9100 + k)} {' '.join(p)}", "en", "a", 1), (2 * k + 1, f"{' '.join(q)} {words(20, 9200 + k)}", "en", "a", 1)]
    r = random.Random(every)
    for k in range(20, 40):
        p = words(60, 9000 + k).split()
        gone = set(r.sample(range(1, 59), 60 // every))
        q = [f"other{k}x{i}" if i in gone else w for i, w in enumerate(p)]
        rows += [(2 * k, f"{words(20, 9100 + k)} {' '.join(p)}", "en", "a", 1), (2 * k + 1, f"{' '.join(q)} {words(20, 9200 + k)}", "en", "a", 1)]
    got = substring_dedup.substring_dedup(frame(spark, rows)).collect()
    assert {frozenset((x.doc_id, x.match_doc_id)) for x in got} == {frozenset((2 * k, 2 * k + 1)) for k in range(40)}


def test_each_place_of_a_passage_has_a_span(spark):
    p, q = words(60, 31), words(55, 32)
    rows = [(1, f"{p} {words(40, 33)}", "en", "a", 1), (2, f"{words(10, 34)} {p} {words(20, 35)} {p} {words(5, 36)} {p}", "en", "a", 1), (3, f"{q} {words(7, 37)} {q} {q}", "en", "a", 1), (4, words(150, 38), "en", "a", 1)]
    got = substring_dedup.substring_dedup(frame(spark, rows)).collect()
    spans = {(x.doc_id, x.start_word, x.n_words, x.match_doc_id, x.match_start) for x in got}
    assert {(2, 10, 60, 1, 0), (2, 90, 60, 1, 0), (2, 155, 60, 1, 0), (3, 62, 55, 3, 0), (3, 117, 55, 3, 0)} <= spans
    assert all(x.match_start + x.match_words <= x.start_word for x in got if x.doc_id == x.match_doc_id)


def test_pairs_of_a_head_are_looked_at_together():
    """The common runs of all texts of a head at once: the same passages as pair by pair, repeated words and equal ids included."""
    rng = np.random.default_rng(5)
    heads = [rng.integers(-200, 200, n).astype(np.int16) for n in (300, 2, 120)]
    heads[2][40:52] = 7
    pairs = []
    for h, b in enumerate(heads):
        for k in range(12):
            a = rng.integers(-200, 200, int(rng.integers(0, 200))).astype(np.int16)
            if k % 3:
                a = np.concatenate([a, b[k : k + 80], np.full(k % 2 * 9, 7, np.int16), a])
            pairs.append((k if k != h else 100 + h, 100 + h, b if k == h else a, b))
    ends = lambda c: np.cumsum([0, *[len(p[c]) for p in pairs]])
    (a, ae), (r, re_) = ((np.concatenate([p[c] for p in pairs]), ends(c)) for c in (2, 3))
    ids, rids = (np.array([p[c] for p in pairs]) for c in (0, 1))
    wide = lambda w: w.astype(np.int64)
    least = substring_dedup._least(50, 0.8, 4)
    met = dict(substring_dedup._met(a, ae, ids, rids, r, re_, least, 4))
    found = 0
    for i, (x, y, u, v) in enumerate(pairs):
        want = substring_dedup.passages_of(wide(u), wide(v), 50, 0.8, own=x == y)
        got = substring_dedup.passages_of(wide(u), wide(v), 50, 0.8, own=x == y, hits=met[i]) if i in met else []
        assert got == want
        found += len(got)
    assert found > 8 and any(h is None for h in met.values()) and any(h is not None for h in met.values())


def test_chains_match_quadratic_chaining():
    r = np.random.default_rng(6)
    for _ in range(30):
        n = int(r.integers(2, 40))
        x, y = np.sort(r.integers(0, 120, n)), r.integers(0, 120, n)
        best = np.zeros(n)
        for i in range(n):
            best[i] = substring_dedup.SEED + max([0.0] + [best[j] - 0.1 * (x[i] - x[j] + y[i] - y[j]) for j in range(i) if x[j] < x[i] and y[j] < y[i]])
        got = substring_dedup.chains(x, y, max_gap=10_000)
        assert sorted(k for c in got for k in c) == list(range(n))
        if not ((np.diff(x) > 0).all() and (np.diff(y) > 0).all()):
            c = got[0]
            score = sum(substring_dedup.SEED for _ in c) - sum(0.1 * (x[b] - x[a] + y[b] - y[a]) for a, b in zip(c, c[1:], strict=False))
            assert abs(score - best.max()) < 1e-9


def test_codec_equals_the_library_and_round_trips(spark, odd, none, small):
    import sentencepiece

    path = sentencepiece_codec.vocabulary_path()
    library, codec = sentencepiece.SentencePieceProcessor(model_file=path), sentencepiece_codec.StreamingCodec(path)
    r = random.Random(1)
    texts = ["".join(r.choice("  aabeinorst.,\n\t-0ßé😀は漢") for _ in range(r.choice((1, 3, 9, 70)))) for _ in range(1500)]
    texts += [" " * n + t for n in range(40) for t in ("", "a", "a b")] + ["a" * 3000, "abc" * 900, "=" * 700 + "x", "ab\x00c", "<s>", "e\u0301"]
    for t in texts:
        assert codec.encode(t) == library.encode(t) and codec.decode(codec.encode(t)) == t
    got = sentencepiece_codec.encode_documents(odd).collect()
    want = Counter((d, tuple(library.encode(t)) if t else ()) for d, t, *_ in odd_rows())
    assert Counter((x.doc_id, tuple(x.ids)) for x in got) == want
    assert all(x.n_tokens == len(x.ids) and x.round_trip == (x.doc_id != 10) for x in got)
    texts_back = {x.doc_id: x.text for x in sentencepiece_codec.decode_documents(sentencepiece_codec.encode_documents(odd)).collect()}
    assert texts_back[1] == "one two three four five six" and texts_back[2] == ""
    assert sentencepiece_codec.encode_documents(none).count() == 0


def test_stream_commits_within_a_bounded_window(spark, small):
    """What is not committed yet is never longer than a few of the longest pieces, in a text without spaces and in ordinary ones."""
    codec = sentencepiece_codec.StreamingCodec(sentencepiece_codec.vocabulary_path())
    for text in ("abracadabra" * 400, "xyz" * 2000):
        runs = list(codec._commits(text))
        assert len(runs) > len(text) // (8 * codec.longest) and max(len(codec.decode(r)) + 1 for r in runs) <= 6 * codec.longest
        assert [i for r in runs for i in r] == [i for r in codec._commits(text) for i in r]
        assert "".join(codec.shown[i] for r in runs for i in r) == text
    ordinary = [r.text for r in spark.read.parquet(f"{small}/documents.parquet").select("text").collect() if r.text]
    for text in ordinary:
        runs = list(codec.stream(text))
        assert max(len(r) for r in runs) <= max(len(w) for w in text.split(" ")) + 1
        assert [i for r in runs for i in r] == codec.encode(text)


def test_disguised_words_are_restored():
    grams = Counter()
    for w in ["idiot", "moron", "hello", "world", "stupid", "the", "letter", "good", "scum"] * 5:
        p = "^^" + w + "$"
        grams.update(p[i : i + 3] for i in range(len(p) - 2))
    restorer = toxicity.Restorer(toxicity.character_model(grams))
    for shown, want in (("1d10t", "idiot"), ("m0r0n!", "moron"), ("stuuupid", "stupid"), ("i d i o t now", "idiot"), ("$cum", "scum"), ("hello", "hello"), ("good", "good"), ("2024", "2024")):
        assert want in restorer.tokens(shown)


def test_heavy_disguise_and_spaced_words_are_restored():
    grams = Counter()
    for w in "you are a stupid fool and an idiot the asshole is worthless what a good letter hello world ass".split() * 5:
        p = "^^" + w + "$"
        grams.update(p[i : i + 3] for i in range(len(p) - 2))
    restorer = toxicity.Restorer(toxicity.character_model(grams))
    cases = [("@$$", "ass"), ("1d!07", "idiot"), ("455h0l3", "asshole"), ("w0r7h13$$", "worthless"), ("you are a s t u p i d fool", "stupid"), ("a $.7.u.p.1.d fool", "stupid")]
    cases += [("s t u p i d i d i o t", "stupid"), ("s t u p i d i d i o t", "idiot"), ("an a s s", "ass"), ("y o u a r e a s t u p i d i d i o t a n d a w o r t h l e s s f o o l a n d a n a s s h o l e", "worthless"), ("stu" + "u" * 60 + "pid", "stupid")]
    for shown, want in cases:
        assert want in restorer.tokens(shown), (shown, restorer.tokens(shown))


def test_decode_is_the_least_of_all_paths():
    grams = Counter("".join(p) for p in zip("^^idiot$", "^idiot$", "idiot$", strict=False))
    model = toxicity.character_model(grams)
    for token in ("1d10t", "iii0t", "a|b4"):
        paths = [("", 0.0)]
        for choices in toxicity.lattice(token):
            paths = [(t + x, c + e) for t, c in paths for x, e in choices]

        def cost(t, c):
            p = "^^" + t + "$"
            return c + sum(model.cost(p[i : i + 2], p[i + 2]) for i in range(len(p) - 2))

        best = min(cost(t, c) for t, c in paths)
        chosen = toxicity.decode(token, model)
        assert abs(min(cost(t, c) for t, c in paths if t == chosen) - best) < 1e-9


def test_toxicity_on_held_out_labels(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = toxicity.digest(docs, labels).join(labels, "doc_id").where("held_out").groupBy("toxic", "predicted").count().collect()
    n = {(r.toxic, r.predicted): r["count"] for r in got}
    assert n[1, 1] / (n[1, 1] + n.get((1, 0), 0)) > 0.9 and n.get((0, 1), 0) / (n[0, 0] + n.get((0, 1), 0)) < 0.01


def test_character_model_keeps_all_trigrams(spark):
    signs = [chr(0x4E00 + i) for i in range(3000)]
    r = random.Random(3)
    rows = [(k, " ".join("".join(r.choices(signs, k=6)) for _ in range(200)), "zh", "a", 1) for k in range(60)]
    wanted = {p[i : i + 3] for x in rows for w in x[1].split() for p in [f"^^{w}$"] for i in range(len(p) - 2)}
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert len(wanted) > 60_000 and set(toxicity.train(frame(spark, rows), labels).chars.three) == wanted


def test_toxicity_cases(spark, odd, none):
    labels = spark.createDataFrame([(1, 1, 1), (1, 1, 0), (3, 0, None), (None, 1, 1), (999, 1, 0), (8, 1, 0)], "doc_id long, quality int, toxic int")
    got = toxicity.digest(odd, labels).collect()
    assert len(got) == len(odd_rows()) and all(0 <= x.score <= 1 for x in got)
    no = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert all(x.predicted == 0 for x in toxicity.digest(odd, no).collect())
    assert toxicity.drop_toxic(odd, no).columns == odd.columns and toxicity.digest(none, labels).count() == 0
