"""The corpus operators against brute force, round trips and defined cases."""

import hashlib
import math
import os
import random
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from approxmatch.llm import byte_bpe, line_dedup, media_gif, mixing, near_dup, pii, quality, suffix_tree_lm, toxicity, url_filter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, gone string, row long"


def texts():
    rnd = random.Random(5)
    vocabulary = ["the", "of", "Gear", "plate", "é", "日本", "ring", "bolt", "old", "new", "cold", "rod"]
    line = lambda n: " ".join(rnd.choices(vocabulary, k=n))
    base = "\n".join(line(12) for _ in range(6))
    passage = "a passage that many documents share\nand its second line stands below it"
    out = [None, "", "   \n\t ", "one", "one two", "ONE two", "a b c d e", "x " * 3000, base, base, base.replace("bolt", "nut", 1), base.upper()]
    out += [line(30) + "\n" + passage + "\n" + line(20) for _ in range(4)]
    out += ["mail me: joe.Doe+x@mail.example.org or +1 (555) 123-4567, ip 10.0.0.1 and 999.1.1.1\ncard 4111 1111 1111 1111", "no\nno\nno\nno", "w " * 20 + "\n" + "w " * 20]
    out += [line(rnd.randrange(5, 60)) for _ in range(20)]
    return out


@pytest.fixture(scope="module")
def rows():
    out = [(i, t, ["en", "de", None][i % 3], ["b", "a", None, "c"][i % 4], len(t or ""), "x", 1) for i, t in enumerate(texts())]
    return [*out, out[8], (None, "no id here at all today", "en", "a", 5, "y", 2)]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, i % 2, int(i % 5 == 0)) for i in range(30)] + [(None, 1, 1), (3, None, None), (9999, 1, 0)], "doc_id long, quality int, toxic int")


# ---- media ------------------------------------------------------------------------------------------------------


def test_gif_round_trip():
    rnd = random.Random(1)
    for n in [*range(0, 130, 13), 4095, 70_000, 200_000]:
        for data in (os.urandom(n), bytes(rnd.choices(b"ab", k=n)), b"\0" * n):
            payload = media_gif.padded(data)
            assert len(payload) % 64 == 0 and payload[:n] == data
            assert b"".join(f.samples for f in media_gif.decode(media_gif.encode(payload)).frames) == payload


def test_gif_rules():
    """Disposal 2 clears, 3 restores, transparent samples leave the canvas, interlaced rows come in four passes."""
    palette = bytes(range(12))
    stream = lambda s: media_gif._sub_blocks(media_gif.lzw_encode(bytes(s), 2))

    def frame(samples, disposal, clear=None, flags=0, w=2, h=2):
        return b"\x21\xf9\x04" + bytes([disposal << 2 | (clear is not None), 7, 0, clear or 0]) + b"\0" + b"\x2c" + bytes([0, 0, 0, 0, w, 0, h, 0, flags, 2]) + stream(samples)

    head = b"GIF89a" + bytes([2, 0, 2, 0, 0x81, 0, 0]) + palette
    image = media_gif.decode(head + frame([1, 1, 1, 1], 1) + frame([2, 0, 0, 2], 3, clear=0) + frame([3, 3, 3, 3], 2) + frame([0, 1, 1, 1], 1, clear=0) + b"\x3b")
    frames = [c.copy() for _, c in media_gif.composite(image)]
    red = lambda c: [[int(p[0]) if p[3] else None for p in line] for line in c]
    assert red(frames[0]) == [[3, 3], [3, 3]]
    assert red(frames[1]) == [[6, 3], [3, 6]]
    assert red(frames[2]) == [[9, 9], [9, 9]]
    assert red(frames[3]) == [[None, 3], [3, 3]]
    tall = b"GIF89a" + bytes([1, 0, 5, 0, 0x81, 0, 0]) + palette
    image = media_gif.decode(tall + frame([0, 1, 2, 3, 0], 1, flags=0x40, w=1, h=5) + b"\x3b")
    assert image.frames[0].samples == bytes([0, 3, 2, 0, 1])
    whole = head + frame([1, 1, 1, 1], 1) + b"\x3b"
    code_size = whole.index(b"\x2c") + 10
    for broken in (b"", b"GIF89a" + bytes(7), *(whole[:n] for n in range(len(whole))), whole[: code_size] + b"\x0c" + whole[code_size + 1 :]):
        with pytest.raises(ValueError):
            media_gif.decode(broken)


def test_gif_query(spark, docs, rows, empty):
    got = {r.doc_id: r for r in media_gif.text_media(docs).collect()}
    for i, t, *_ in rows:
        raw = (t or "").encode()
        assert got[i].n_bytes == len(raw) and got[i].payload_bytes == max(64, -(-len(raw) // 64) * 64)
        assert got[i].payload_sha256 == hashlib.sha256(media_gif.padded(raw)).hexdigest()
    assert got[8].media_sha256 == got[9].media_sha256 and got[8].feature == got[9].feature
    assert media_gif.text_media(empty).count() == 0
    frames = media_gif.media_frames(media_gif.store_texts(docs)).collect()
    assert all(sum(f.histogram) % 64 == 0 and f.error is None for f in frames) and len(frames) >= len(rows)
    for r in got.values():
        own = [(f.start_cs, f.delay_cs, f.histogram) for f in sorted((f for f in frames if f.doc_id == r.doc_id), key=lambda f: f.frame)]
        stored = [(f.start_cs, f.delay_cs, f.histogram) for f in r.frames]
        assert stored == own[: len(stored)] and r.feature.endswith("/".join(",".join(str(sum(f[2][c * 8 + k] for f in stored)) for k in range(8)) for c in range(3)))


def test_broken_media_are_rows(spark):
    whole = media_gif.encode(media_gif.padded(b"abc"))
    d = spark.createDataFrame([(1, whole), (2, whole[:40]), (3, None), (4, b"")], "doc_id long, media binary")
    got = {r.doc_id: (r.frame, r.error) for r in media_gif.media_frames(d).collect()}
    assert got[1] == (0, None) and got[2][0] is None and got[2][1] and got[4][1] and 3 not in got


# ---- mixing --------------------------------------------------------------------------------------------------------


def water(sizes, weights, most=3):
    """Targets by filling one source after another."""
    target, free, left = {}, set(sizes), float(sum(sizes.values()))
    while free:
        total = sum(weights[s] for s in free)
        full = {s for s in free if weights[s] * left / total > most * sizes[s] + 1e-9}
        if not full:
            return target | {s: weights[s] * left / total for s in free}
        for s in full:
            target[s] = float(most * sizes[s])
            left -= target[s]
        free -= full
    return target


def test_mixing(docs, rows, empty):
    got = mixing.mix(docs).collect()
    assert len(got) == len(rows)
    size = lambda t: len(WORD.findall(t or ""))
    sizes = Counter()
    for _, t, _, s, *_ in rows:
        sizes[s] += size(t)
    order = sorted((s for s in sizes if s is not None)) + [None]
    want = water(dict(sizes), {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)})
    taken = Counter()
    for r in got:
        assert r.target == pytest.approx(want[r.source]) and r.source_size == sizes[r.source]
        assert r.taken == r.copies * r.size <= 3 * r.size and len(r.shards) == r.copies
        taken[r.source] += r.taken
    for s in sizes:  # whole documents only: what isn't taken once more doesn't fit any more
        room = want[s] - taken[s]
        own = [r for r in got if r.source == s and r.size]
        assert room > -1 and all(r.size > room + 0.4 for r in own if r.copies == min(x.copies for x in own) and max(x.copies for x in own) < 3)
    assert sorted(map(str, mixing.mix(docs.repartition(7)).collect())) == sorted(map(str, got))
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns and mixed.count() == sum(r.copies for r in got)
    assert mixing.mix(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0


def test_a_long_document_leaves_no_room_that_others_fill(spark):
    """Sources of many blocks with one very long document: in the end no document that is left fits."""
    rnd = random.Random(9)
    rows = []
    for k in range(6):
        sizes = [rnd.randrange(1, 40) for _ in range(600)] + [9000]
        rows += [(k * 10_000 + i, "w " * n, f"s{k}") for i, n in enumerate(sizes)]
    rows += [(90_000 + i, "w " * 60, "t") for i in range(3000)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert len(got) == len(rows)
    for s in {r.source for r in got}:
        own = [r for r in got if r.source == s]
        room = own[0].target - sum(r.taken for r in own)
        passes = min(r.copies for r in own)
        assert room > -1 and all(r.copies - passes in (0, 1) and len(r.shards) == r.copies for r in own)
        assert own[0].target == 3 * own[0].source_size or all(r.size > room + 0.4 for r in own if r.copies == passes)


def test_tree_keeps_quotas(spark):
    units = spark.range(1000).select(F.when(F.col("id") % 3 == 0, None).otherwise(F.concat(F.lit("s"), (F.col("id") % 3).cast("string"))).alias("source"), F.lit(0).alias("block"), F.lit(0).alias("pass"), F.floor(F.col("id") / 3).cast("int").alias("unit"))
    quotas = mixing.shard_quotas(units, 3).collect()
    assert Counter({s: sum(q.quota for q in quotas if q.source == s) for s in (None, "s1", "s2")}) == Counter({None: 334, "s1": 333, "s2": 333})
    assert {sum(q.quota for q in quotas if q.shard == k) for k in range(8)} <= {124, 125, 126}
    assigned = mixing.shard_units(units, 3).groupBy("shard").count().collect()
    assert sum(r["count"] for r in assigned) == 1000 and all(r.shard is not None for r in assigned)


# ---- near duplicates ------------------------------------------------------------------------------------------------


def shingles(t):
    w = WORD.findall((t or "").translate(LOW))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def brute_components(pairs):
    sets = {i: shingles(t) for i, t in pairs}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}, sets


def test_near_duplicates(docs, rows, empty):
    want, sets = brute_components({(i, t) for i, t, *_ in rows if i is not None})
    for r in near_dup.near_duplicates(docs).collect():
        if r.doc_id is None:
            assert r.kept and r.component_id is None
            continue
        assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), want[r.doc_id], want[r.doc_id] == r.doc_id)
    kept = near_dup.deduplicated(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i in want if want[i] == i} | {None}
    odd = near_dup.deduplicated(docs.withColumn("__gone", F.lit(1)).withColumn("own", F.lit(2)).withColumn("gone", F.lit(3)))
    assert odd.columns == [*docs.columns, "__gone", "own"] and odd.count() == kept.count()
    assert sorted(near_dup.near_duplicates(docs, least_agreement=0).collect(), key=str) == sorted(near_dup.near_duplicates(docs).collect(), key=str)
    assert near_dup.near_duplicates(empty).count() == 0


def test_a_group_around_a_centre(spark):
    """Copies at many distances from one text: links go through the middle, and strays must not be lost or made."""
    rnd = random.Random(3)
    base = [f"w{k}" for k in range(120)]
    texts = []
    for i in range(150):
        w = base.copy()
        for k in rnd.sample(range(120), rnd.choice([0, 1, 2, 3, 4, 5, 7, 9, 12])):
            w[k] = f"z{i}_{k}"
        texts.append((i + 10, " ".join(w)))
    want, _ = brute_components(texts)
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    assert got == want


def test_several_texts_of_one_document(spark):
    """Each row of a repeated doc_id has its own set; links through any of them count."""
    rnd = random.Random(6)
    base = [[f"w{b}_{k}" for k in range(60)] for b in range(3)]
    rows = []
    for i in range(90):
        w = base[i % 3].copy()
        for k in rnd.sample(range(60), rnd.choice([0, 1, 2, 3, 5])):
            w[k] = f"z{i}_{k}"
        rows.append((rnd.randrange(70), " ".join(w)))
    sets, parent = [(i, shingles(t)) for i, t in rows], {i: i for i, _ in rows}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, (i, x) in enumerate(sets):
        for j, y in sets[:a]:
            if 100 * len(x & y) >= 75 * len(x | y):
                parent[max(root(i), root(j))] = min(root(i), root(j))
    got = {r.doc_id: r.component_id for r in near_dup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: root(i) for i, _ in rows}


def test_sketch_fills_and_estimates():
    rnd = np.random.default_rng(1)
    for n in (1, 3, 50, 2000):
        h = np.unique(rnd.integers(0, 2**63, n).astype(np.uint64))
        with np.errstate(over="ignore"):
            s = near_dup.sketches(np.concatenate([h, h[: max(1, n // 2)]]), np.concatenate([np.zeros(len(h), int), np.ones(max(1, n // 2), int)]), 2)
        assert (s != near_dup._EMPTY).all()
        j = max(1, n // 2) / n
        assert abs((s[0] == s[1]).mean() - j) < 5 * math.sqrt(j * (1 - j) / 128) + 1e-9


def test_repeated_ids_link_their_texts(spark):
    d = spark.createDataFrame([(1, "a b c d e f"), (2, "a b c d e f"), (2, "q r s t u v"), (3, "q r s t u v")], "doc_id long, text string")
    assert {(r.doc_id, r.component_id) for r in near_dup.near_duplicates(d).collect()} == {(1, 1), (2, 1), (3, 1)}


# ---- quality -----------------------------------------------------------------------------------------------------------


def test_quality_features(docs, rows, labels, empty):
    got = {r.doc_id: r for r in quality.judge(docs, labels).collect()}
    for i, t, *_ in rows:
        w = WORD.findall(t or "")
        windows = Counter(tuple(w[k : k + 8]) for k in range(len(w) - 7))
        hit = [False] * len(w)
        for k in range(len(w) - 7):
            if windows[tuple(w[k : k + 8])] > 1:
                hit[k : k + 8] = [True] * 8
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), sum(hit))
        assert r.base_failed == (len(w) < 20 or 100 * sum(hit) > 30 * len(w)) and not (r.base_failed and r.kept)
    assert quality.judge(empty, labels).count() == 0


def test_exact_bounds_and_certified_cutoffs(spark):
    df = spark.createDataFrame([(0, 100), (3, 100), (40, 1000)], "k long, n long")
    for r in df.select("k", "n", quality.binomial_at_most(F.col("k"), F.col("n"), 0.03).alias("p")).collect():
        want = sum(math.comb(r.n, i) * 0.03**i * 0.97 ** (r.n - i) for i in range(r.k + 1))
        assert r.p == pytest.approx(want, rel=1e-9)
    # 4,000 good documents without symbols, 300 bad ones full of them
    f = spark.range(4300).select(F.col("id").alias("doc_id"), F.lit("en").alias("stratum"), F.lit(100).cast("long").alias("n_words"), F.lit(500).cast("long").alias("word_chars"), F.when(F.col("id") < 4000, 0).otherwise(100).cast("long").alias("n_symbols"), F.lit(0).cast("long").alias("n_dup_lines"), F.lit(0).cast("long").alias("n_repeat_words"), F.lit(5).cast("long").alias("n_lines"), F.lit(False).alias("base_failed"))
    marks = spark.range(4300).select(F.col("id").alias("doc_id"), (F.col("id") < 4000).cast("int").alias("quality"))
    used = quality.cutoffs(f, marks).collect()
    assert [(r.rule, r.good_rejected, r.bad_rejected) for r in used] == [("symbols", 0, 300)] and used[0].p_value <= 0.1
    few = quality.cutoffs(f.where("doc_id % 50 = 0"), marks).collect()
    assert few == []  # too few labels certify nothing


# ---- language model --------------------------------------------------------------------------------------------------------


def test_suffix_tree(docs, rows, empty):
    import zlib

    crc = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 7 == 2
    tokens = [(i, WORD.findall((t or "").translate(LOW)) + [None]) for i, t, *_ in rows]
    c = Counter(x for i, w in tokens if not crc(i) for x in w)
    n, v = sum(c.values()), len(c)
    got = sorted((r.doc_id or -1, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in suffix_tree_lm.scores(docs).collect())
    want = sorted((i or -1, crc(i), len(w), sum(c[x] > 0 for x in w), n, round(sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w), 6)) for i, w in tokens)
    assert got == want
    assert suffix_tree_lm.scores(empty).count() == 0


def brute_tree_scores(texts, train, least, divergence, depth=suffix_tree_lm.DEPTH, shallow=suffix_tree_lm.SHALLOW):
    """Score of each text, and the retained contexts, from dictionaries of every context of the training texts."""
    stream = [b" ".join(re.split(rb"[\x20\x09-\x0D]+", t.translate(LOW).encode().strip(b" \t\n\v\f\r"))).replace(b"\0", b"\xff") + b"\0" for t in texts]
    seen = [{} for _ in range(depth + 1)]
    for s, use in zip(stream, train, strict=True):
        padded = bytes(depth) + s
        for i in range(depth, len(padded)) if use else []:
            for d in range(depth + 1):
                seen[d].setdefault(padded[i - d : i], Counter())[padded[i]] += 1
    kept = [{c for c, n in level.items() if n.total() >= least} for level in seen]
    for d in range(shallow + 1, depth + 1):
        def gain(c, d=d):
            n, up = seen[d][c], seen[d - 1][c[1:]]
            return sum(k * math.log(k / n.total() / (up[x] / up.total())) for x, k in n.items()) - divergence * len(n)

        kept[d] = {c for c in kept[d] if gain(c) >= 0}
    for d in range(depth, shallow + 1, -1):
        kept[d - 1] |= {c[1:] for c in kept[d]}

    def probability(c, x):
        while c not in kept[len(c)] and c:
            c = c[1:]
        if c not in kept[len(c)]:
            return 1 / 256
        n = seen[len(c)][c]
        q = probability(c[1:], x) if c else 1 / 256
        return (n[x] + len(n) * q) / (n.total() + len(n))

    out = []
    for s in stream:
        padded = bytes(depth) + s
        out.append(sum(math.log10(probability(padded[i - depth : i], padded[i])) for i in range(depth, len(padded))))
    return out, {c: seen[len(c)][c] for level in kept[shallow + 1 :] for c in level}


def test_tree_equals_brute_force(spark, rows):
    """Scores and retained contexts, however the texts and the tree are spread; NUL is no end; repeated rows."""
    import zlib

    data = [(i, t) for i, t, *_ in rows if t is not None] + [(500, "a nul \0 b"), (501, "\0"), (502, "\0\0 the")] * 2
    data += [(600 + k, f"the gear of the ring number {k % 7} " * 4) for k in range(40)]
    train = [zlib.crc32(("" if i is None else str(i)).encode()) % 7 != 2 for i, _ in data]
    d = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    for least, divergence, options in ((4, 2.0, {}), (2, 0.5, {"parts": 5, "salted": 2, "chunk": 3000})):
        want, kept = brute_tree_scores([t for _, t in data], train, least, divergence)
        got = suffix_tree_lm.scores(d, least, divergence, **options).collect()
        assert len(got) == len(data) and not all(train)
        key = lambda x: (x[0] if x[0] is not None else -1, x[1])
        for (i, x), (j, y) in zip(sorted(((i, w) for (i, _), w in zip(data, want, strict=True)), key=key), sorted(((r.doc_id, r.score) for r in got), key=key), strict=True):
            assert i == j and y == pytest.approx(x, rel=1e-6, abs=1e-4)
        found = {bytes(r.context): (r.n, r.kinds) for r in suffix_tree_lm.states(d, least, divergence, **options).collect()}
        assert found == {c: (n.total(), len(n)) for c, n in kept.items()} and any(len(c) == suffix_tree_lm.DEPTH for c in found)


def test_tree_is_a_distribution():
    """Next-byte probabilities add up to one in every state, and streams stand for tokens."""
    data = b"the gear of the ring\n the  old ring" * 20
    at = np.array([0, 300, 300, len(data)])
    full = suffix_tree_lm.DEPTH
    codes, rows = suffix_tree_lm.windows(*suffix_tree_lm.byte_streams(np.frombuffer(data, np.uint8), at))
    for k in range(3):
        part = data[at[k] : at[k + 1]]
        assert (codes[rows == k] & np.uint64(255)).astype(np.uint8).tobytes() == b" ".join(part.split()) + b"\0"
    keys, counts = np.unique(codes, return_counts=True)
    tree, _ = suffix_tree_lm.grow(keys, counts, full, range(full + 1))
    assert len(tree.levels[full].contexts)
    for d in (0, 1, 3, full):
        for c in map(int, tree.levels[d].contexts[:3]):
            p = tree.score(np.array([c << 8 * (full - d + 1) | s for s in range(256)], np.uint64), full)
            assert (10**p).sum() == pytest.approx(1.0, abs=1e-9)
    raw = np.sort(np.random.default_rng(1).integers(0, 2**56, 1000).astype(np.uint64))
    assert (suffix_tree_lm.unpacked(suffix_tree_lm.packed(raw)) == raw).all() and len(suffix_tree_lm.unpacked(b"")) == 0


def test_chunk_memory_is_bounded():
    """What a scan of a chunk holds doesn't grow with its bytes; several batches, either side alone."""
    import tracemalloc

    import pyarrow as pa

    rnd = random.Random(3)
    some = [" ".join(rnd.choices(["the", "of", "Gear", "plate", "é"], k=300)) for _ in range(40)]
    some_held = [rnd.random() < 0.3 for _ in some]
    half = pa.table({"text": some, "held": some_held})
    for table in (pa.concat_tables([half, half]), half.filter(pa.array(some_held)), half.slice(0, 0)):
        got = suffix_tree_lm.chunk_windows(table)
        want = Counter()
        for t, held in zip(table["text"].to_pylist(), table["held"].to_pylist(), strict=True):
            padded = bytes(suffix_tree_lm.DEPTH) + t.translate(LOW).encode() + b"\0"
            for i in range(suffix_tree_lm.DEPTH, len(padded)):
                code = int.from_bytes(padded[i - suffix_tree_lm.DEPTH : i][::-1] + padded[i : i + 1], "big")
                want[code] += not held
        assert list(zip(*(x.tolist() for x in got), strict=True)) == sorted(want.items())
    large = pa.table({"text": some * 150, "held": some_held * 150})
    assert large["text"].nbytes > 6_000_000
    tracemalloc.start()
    try:
        suffix_tree_lm.chunk_windows(large)
        held = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert held < 55_000_000


# ---- BPE -----------------------------------------------------------------------------------------------------------------------


def test_bpe_equals_the_library(docs, rows, empty):
    import tiktoken

    path, pattern = byte_bpe.public_vocabulary()
    v = byte_bpe.load(path, pattern)
    library = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=v.ranks, special_tokens={})
    hard = ["a" * 3000, "ab" * 200, " \n\n  x", "don't 12345!!!###", "日本語" * 60, "\x85\xa0ﬁ²½", "<|endoftext|>", "\U0001f600" * 50]
    e = byte_bpe.Encoder(v)
    for t in hard:
        assert np.frombuffer(e.encode([t])[0], "<u4").tolist() == library.encode_ordinary(t)
    for piece in (b"abracadabra" * 9, "überfluß".encode(), bytes(range(200, 256))):
        assert byte_bpe.encode_piece(piece, v) == library._encode_single_piece(piece)
        if piece not in v.ranks:
            assert byte_bpe.encode_pieces([piece], v) == [byte_bpe.encode_piece(piece, v)]
    got = {r.doc_id: r for r in byte_bpe.digests(docs, path, pattern).collect()}
    for i, t, *_ in rows:
        ids = np.array(library.encode_ordinary(t or ""), "<u4").tobytes()
        assert (got[i].n_tokens, got[i].ids_sha256, got[i].decoded_sha256) == (len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest())
    back = byte_bpe.decoded(byte_bpe.encoded(docs, path, pattern), path, pattern).collect()
    assert {r.doc_id: r.text for r in back} == {i: t or "" for i, t, *_ in rows}
    assert byte_bpe.digests(empty, path, pattern).count() == 0


def test_bpe_memory_is_bounded():
    """Neither the strings of a text's pieces nor remembered ones grow with the text; long pieces aren't remembered."""
    import tracemalloc

    v = byte_bpe.Vocabulary({bytes([i]): i for i in range(256)} | {b"ab": 256}, r" ?[a-z]+")
    e = byte_bpe.Encoder(v)
    text = " ab c" * 800_000 + " " + "z" * 300
    tracemalloc.start()
    try:
        ids = e.encode([text])[0]
        held = tracemalloc.get_traced_memory()[1]
        tracemalloc.reset_peak()
        same = e.decode(ids).decode() == text
        back = tracemalloc.get_traced_memory()[1] - tracemalloc.get_traced_memory()[0]
    finally:
        tracemalloc.stop()
    assert same and len(ids) == 4 * (4 * 800_000 + 301)
    assert held < 60_000_000 and back < 40_000_000
    assert set(e.known) == {" ab", " c"}


def test_bpe_remembers_pieces_in_use(monkeypatch):
    """Forgetting changes no ids, and a piece that every chunk has is not encoded again."""
    monkeypatch.setattr(byte_bpe, "REMEMBERED", 8)
    v = byte_bpe.Vocabulary({bytes([i]): i for i in range(256)} | {b"ab": 256}, r" ?[a-z]+")
    e, asked = byte_bpe.Encoder(v), Counter()
    plain = byte_bpe.encode_pieces
    monkeypatch.setattr(byte_bpe, "encode_pieces", lambda pieces, v: asked.update(pieces) or plain(pieces, v))
    for i in range(20):
        text = "abab " + " ".join(chr(97 + (i + k) % 26) * 3 for k in range(6))
        assert e.decode(e.encode([text])[0]) == text.encode()
        assert len(e.known) + len(e.older) <= 8 + 2 * 7
    assert asked[b"abab"] == 1


def test_a_piece_of_more_than_16_mib():
    """Only the last two bytes merge, at a position above 2 ** 24."""
    v = byte_bpe.Vocabulary({bytes([i]): i for i in range(256)} | {b"bc": 256}, r"[a-z]+")
    n = (1 << 24) + 10
    got = byte_bpe.encode_piece(b"a" * n + b"bc", v)
    assert len(got) == n + 1 and got[-1] == 256 and set(got[:-1]) == {97}


# ---- lines ------------------------------------------------------------------------------------------------------------------------


def brute_lines(rows, least=5):
    order = sorted({(i if i is not None else -1, t) for i, t, *_ in rows if t is not None}, key=lambda x: x[0])
    seqs = {(i, t): [(p, x, len(WORD.findall(x))) for p, x in enumerate(t.split("\n")) if WORD.search(x)] for i, t in order}
    first, gone = {}, {k: set() for k in order}
    for k in order:
        for a in range(len(seqs[k])):
            for n in range(1, least + 1):
                if a + n <= len(seqs[k]):
                    first.setdefault(tuple(x for _, x, _ in seqs[k][a : a + n]), (k, a))
    for k in order:
        for a in range(len(seqs[k])):
            for n in range(1, least + 1):
                part = seqs[k][a : a + n]
                if len(part) == n and sum(w for *_, w in part) >= least and first[tuple(x for _, x, _ in part)] != (k, a):
                    gone[k] |= {p for p, _, _ in part}
    return {(i, t): "\n".join(x for p, x in enumerate(t.split("\n")) if p not in gone[i, t]) for i, t in order}


def test_line_dedup(docs, rows, empty):
    want = brute_lines(rows)
    out = line_dedup.deduplicated(docs)
    assert out.columns == docs.columns and out.count() == len(rows)
    got = {(-1 if r.doc_id is None else r.doc_id, r.n_chars): r.text for r in out.collect()}
    for (i, _), text in want.items():
        assert got[i, len(text)] == text
    assert next(r for r in out.collect() if r.doc_id == 0).text is None
    assert line_dedup.deduplicated(empty).count() == 0


def brute_runs(rows):
    """Of every position the longest run that stands twice; not those inside a longer one. And the lines with a word."""
    seqs = {i: [(p, x) for p, x in enumerate(t.split("\n")) if WORD.search(x)] for i, t in sorted(set(rows))}

    def same(a, i, b, j):
        n = 0
        while i + n < len(a) and j + n < len(b) and a[i + n][1] == b[j + n][1]:
            n += 1
        return n

    out = set()
    for d, a in seqs.items():
        longest = [max((same(a, i, b, j) for e, b in seqs.items() for j in range(len(b)) if (e, j) != (d, i)), default=0) for i in range(len(a))]
        out |= {(d, a[i][0], k) for i, k in enumerate(longest) if k and not (i and longest[i - 1] > k)}
    return out, seqs


def test_maximal_runs_equal_brute_force(spark):
    rnd = random.Random(8)
    pool = [f"line {c} of words" for c in "abcdefgh"]
    rows = []
    for i in range(25):
        body = [rnd.choice([*pool, "", f"own line {i}"]) for _ in range(rnd.randrange(1, 9))]
        if i % 4 == 0:
            body += [f"long {k}" for k in range(rnd.randrange(3, 23))]
        rows.append((i, "\n".join(body)))
    rows.append((90, "same\n" * 20))
    want, seqs = brute_runs(rows)
    d = spark.createDataFrame([*rows, rows[3], (95, None)], "doc_id long, text string").repartition(3)
    got = line_dedup.maximal_runs(d).collect()
    assert {(r.doc_id, r.line, r.lines) for r in got} == want and len(got) == len(want) and max(r.lines for r in got) > 9
    for r in got:
        part = lambda i, p, n=r.lines: [x for q, x in seqs[i] if q >= p][:n]
        assert (r.doc_id, r.line) != (r.other_doc, r.other_line) and part(r.doc_id, r.line) == part(r.other_doc, r.other_line)
    assert line_dedup.maximal_runs(d.limit(0)).count() == 0


def test_places_split_a_line_with_many_continuations(spark):
    """Places by three steps equal one sort."""
    rnd = random.Random(4)
    kinds = {(rnd.randrange(2), 0, rnd.choice([None, rnd.randrange(-(2**63), 2**63), 5 << 56]), rnd.choice([None, rnd.randrange(1 << 20)])): rnd.randrange(1, 9) for _ in range(500)}
    got = line_dedup._places(spark.createDataFrame([(*k, n) for k, n in kinds.items()], "h long, name long, nh long, nn long, n long")).collect()
    order = lambda k: (k[0], k[2] is not None, k[2] or 0, k[3] is not None, k[3] or 0)
    up, want = Counter(), {}
    for k in sorted(kinds, key=order):
        want[k] = up[k[0]]
        up[k[0]] += kinds[k]
    assert {(r.h, r.name, r.nh, r.nn): r.up for r in got} == want


# ---- toxicity ------------------------------------------------------------------------------------------------------------------------


def test_toxicity(spark, docs, labels, empty):
    rnd = random.Random(2)
    rows, marks = [], []
    for i in range(600):
        bad = i % 6 == 0
        w = [f"w{rnd.randrange(200)}" for _ in range(40)]
        if bad:
            w[rnd.randrange(40)] = rnd.choice(["vilea", "vileb", "nastyx"])
        rows.append((i, " ".join(w)))
        marks.append((i, int(rnd.random() < 0.9), int(bad)))
    d = spark.createDataFrame(rows, "doc_id long, text string")
    chain = toxicity.train(d, spark.createDataFrame(marks[:400], "doc_id long, quality int, toxic int"))
    got = {r.doc_id: r.rejected for r in toxicity.scored(d, chain).collect()}
    held = range(400, 600)
    assert sum(got[i] for i in held if i % 6 == 0) >= 0.95 * sum(i % 6 == 0 for i in held)
    assert not any(got[i] for i in held if i % 6)
    assert {r.doc_id for r in toxicity.filtered(d, chain).collect()} == {i for i in got if not got[i]}
    assert chain.models[1].before.shape == (1,)
    again = toxicity.train(d.repartition(5), spark.createDataFrame(marks[:400], "doc_id long, quality int, toxic int"))
    assert np.allclose(again.models[1].weights, chain.models[1].weights)
    none = toxicity.train(docs, labels.limit(0))
    assert not any(r.rejected for r in toxicity.scored(docs, none).collect())
    assert toxicity.filtered(docs, none).columns == docs.columns
    assert toxicity.scored(empty, chain).count() == 0
    toxicity.train(docs, labels)


def brute_features(t):
    """Hashed words and word beginnings of a text, word by word."""
    out = set()
    for w in re.findall(rb"[0-9a-z\x80-\xff]+", (t or "").translate(LOW).encode()):
        with np.errstate(over="ignore"):
            one = lambda x: np.uint64(near_dup.span_hashes(np.frombuffer(x, np.uint8), np.array([0]), np.array([len(x)]))[0])
            out |= {int(one(w) >> np.uint64(44)), int(near_dup.mix(np.array([one(w[:6]) ^ toxicity._SEED]))[0] >> np.uint64(44))}
    return out


def test_chain_equals_brute_force(spark, docs, rows, empty):
    """Features, their choice, the folds, the chain of odds and the threshold against plain loops."""
    rnd = random.Random(12)
    texts = [" ".join([f"w{rnd.randrange(30)}" for _ in range(12)] + (["vile é"] if i % 5 == 0 and rnd.random() < 0.8 else []) + (["poor"] if i % 3 == 0 else [])) for i in range(150)]
    marks = [(i, int(i % 3 > 0), int(i % 5 == 0)) for i in range(150)]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    chain = toxicity.train(d, spark.createDataFrame(marks, "doc_id long, quality int, toxic int"))
    sets = [brute_features(t) for t in texts]
    y = {"low_quality": [float(q == 0) for _, q, _ in marks], "toxic": [float(x == 1) for *_, x in marks]}
    present, best = Counter(f for s in sets for f in s), {}
    for f, k in present.items():
        for v in y.values():
            p, a = sum(v) / 150, sum(v[i] for i in range(150) if f in sets[i])
            g = (a * math.log(a / (k * p)) if a else 0) + ((k - a) * math.log((k - a) / (k * (1 - p))) if k > a else 0)
            best[f] = max(best.get(f, 0), round(g, 9))
    chosen = sorted((f for f, k in present.items() if k >= toxicity.MIN_DOCS and best[f] > 3), key=lambda f: (-best[f], f))
    assert [int(f) for f in np.argsort(np.where(chain.places < 0, 1 << 30, chain.places))[: len(chosen)]] == chosen and (chain.places >= 0).sum() == len(chosen)
    # out-of-fold odds of the first category are the second's feature: fit again by loops over documents
    fold = (near_dup.mix(np.arange(150).astype(np.uint64)) % np.uint64(toxicity.FOLDS)).astype(int)
    at = {f: k for k, f in enumerate(chosen)}

    def model(inside, target, earlier):
        cols = [at[f] for n, i in enumerate(inside) for f in sets[i] if f in at]
        rws = [n for n, i in enumerate(inside) for f in sets[i] if f in at]
        return toxicity.fit(np.array(cols), np.array(rws), len(chosen), np.array([earlier[i] for i in inside]).reshape(len(inside), -1), np.array([target[i] for i in inside]), np.ones(len(inside)))

    def odds(m, i, before):
        return m.bias + sum(m.weights[at[f]] for f in sets[i] if f in at) + sum(a * b for a, b in zip(before, m.before, strict=True))

    none = [()] * 150
    held = [odds(model([j for j in range(150) if fold[j] != fold[i]], y["low_quality"], none), i, ()) for i in [int(np.flatnonzero(fold == k)[0]) for k in range(toxicity.FOLDS)]]
    parts = [model([j for j in range(150) if fold[j] != k], y["low_quality"], none) for k in range(toxicity.FOLDS)]
    earlier = [(odds(parts[fold[i]], i, ()),) for i in range(150)]
    assert held == pytest.approx([earlier[int(np.flatnonzero(fold == k)[0])][0] for k in range(toxicity.FOLDS)])
    first, second = model(range(150), y["low_quality"], none), model(range(150), y["toxic"], earlier)
    got = {r.doc_id: r for r in toxicity.scored(d, chain).collect()}
    sigmoid = lambda x: 1 / (1 + math.exp(-x))
    for i in range(150):
        o = odds(first, i, ())
        assert got[i].p_low_quality == pytest.approx(sigmoid(o), abs=1e-6) and got[i].p_toxic == pytest.approx(sigmoid(odds(second, i, (o,))), abs=1e-6)
        assert got[i].rejected == (got[i].p_toxic >= chain.threshold)


def test_fit_reaches_the_optimum():
    """The loss is within a thousandth of what Newton steps on the dense problem reach."""
    rnd = np.random.default_rng(3)
    x = (rnd.random((300, 8)) < 0.3).astype(float)
    y = (rnd.random(300) < 1 / (1 + np.exp(1 - x @ np.arange(-3, 5)))).astype(float)
    m = toxicity.fit(*np.nonzero(x)[::-1], 8, np.zeros((300, 0)), y, np.ones(300))
    ridge, dense, w = toxicity.RIDGE * 10 / 300, np.hstack([x, np.ones((300, 1))]), np.zeros(9)
    scale = np.append(np.full(8, ridge), 0)
    loss = lambda v: float(np.mean(np.logaddexp(0, dense @ v) - y * (dense @ v)) + (scale * v * v).sum() / 2)
    for _ in range(50):
        p = 1 / (1 + np.exp(-dense @ w))
        w -= np.linalg.solve((dense * (p * (1 - p))[:, None]).T @ dense / 300 + np.diag(scale), dense.T @ (p - y) / 300 + scale * w)
    assert loss(w) <= loss(np.append(m.weights, m.bias)) <= loss(w) * 1.001


def test_threshold_of_a_precision_or_the_best():
    p, y = np.array([0.9, 0.8, 0.61, 0.55]), np.array([1.0, 1.0, 0.0, 1.0])
    assert toxicity.best_threshold(p, y, np.ones(4)) == pytest.approx(0.62)
    assert toxicity.best_threshold(p, np.array([0.0, 1.0, 1.0, 0.0]), np.ones(4)) == pytest.approx(0.56)  # 2 of 3 is the best
    assert toxicity.best_threshold(p * 0.1, y, np.ones(4)) == 2.0


def test_toxicity_defined_cases(spark, docs, rows, labels, empty):
    """Null and empty texts, ties, repeated rows and labels, clashing columns, empty tables."""
    odd = [(1, None, 1, 2), (2, "", 3, 4), (3, "vile words", 5, 6), (3, "vile words", 5, 6), (4, "good words", 7, 8), (None, "vile words", 1, 1)]
    d = spark.createDataFrame(odd, "doc_id long, text string, quality int, p_toxic int")
    marks = spark.createDataFrame([(i, 1, i % 2) for i in range(1, 5)] * 3 + [(None, 1, 1)], "doc_id long, quality int, toxic int")
    chain = toxicity.train(d, marks)
    got = toxicity.scored(d, chain).collect()
    assert len(got) == 6 and len({r.p_toxic for r in got if r.doc_id in (3, None)}) == 1 and len({r.p_toxic for r in got if r.doc_id in (1, 2)}) == 1
    assert toxicity.filtered(d, chain).columns == d.columns
    assert toxicity.scored(empty, toxicity.train(empty, labels)).count() == 0 and toxicity.filtered(empty, chain).count() == 0
    assert not any(r.rejected for r in toxicity.scored(d, toxicity.train(d, marks.where("toxic = 0"))).collect())


# ---- personal data ----------------------------------------------------------------------------------------------------------------------


def test_base_spans_equal_the_patterns(docs, rows, empty):
    kinds = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([\x20-]?[0-9])+", r"\+[0-9][\x20().0-9-]+[0-9]"]
    rnd = random.Random(4)
    samples = [t or "" for _, t, *_ in rows] + ["".join(rnd.choices("a1.@+- (é4", k=60)) for _ in range(3000)]
    samples += ["@" * 50, "a" * 5000 + "@", "1" * 5000, "1." * 3000, "+1" + "(" * 5000]
    for t in samples:
        raw, want = t.encode(), []
        for k, p in enumerate(kinds):
            for m in re.compile(p.encode()).finditer(raw) if len(t) < 1000 else []:
                digits = re.sub(rb"[^0-9]", b"", m[0])
                if k == 1 and any(int(x) > 255 for x in m[0].split(b".")) or k == 2 and not (16 <= len(digits) <= 19 and pii.luhn(digits)) or k == 3 and not 8 <= len(digits) <= 15:
                    continue
                want.append((k, *m.span()))
        got = pii.base_spans(raw)
        assert got == want or len(t) >= 1000
    r = next(r for r in pii.digests(docs).collect() if r.n_email)
    assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == (1, 1, 1, 1)
    assert pii.digests(empty).count() == 0


def test_terms_that_disclose(spark):
    rows = [(i, f"filler{i} words about nothing here\nproject bluebird contact ann@corp.example please reply{i}") for i in range(8)]
    rows += [(100 + i, f"filler{i} please note that nothing else matters here {i}") for i in range(60)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.digests(d).collect()}
    text = rows[0][1]
    a = text.index("bluebird")
    assert f"term:{a}:{a + 8}" in got[0].spans and "email:" in got[0].spans
    b = text.index("please")
    assert f"term:{b}:{b + 6}" not in got[0].spans and got[100].n_term == 0
    clean = {r.doc_id: r.text for r in pii.sanitised(d).collect()}
    assert "bluebird" not in clean[0] and "[email]" in clean[0] and clean[100] == rows[8][1]


def test_copies_of_a_text_leave_the_disclosure_of_its_terms(spark):
    """A term that never stands without its entity discloses it, however often one of its texts is copied."""
    rows = [(i, f"filler{i}\nproject bluebird contact ann@corp.example now{i}") for i in range(4)]
    rows += [(100 + i, f"other{i} words about nothing") for i in range(60)]
    rows += [(1000 + i, rows[0][1]) for i in range(300)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.spans for r in pii.digests(d).collect()}
    a = rows[0][1].index("bluebird")
    assert all(f"term:{a}:{a + 8}" in got[i] for i in (0, 1, 2, 3, 1000, 1299))


def test_terms_disclose_over_whole_texts(spark):
    """A name two lines above an e-mail counts, and is marked in every text, with or without the e-mail."""
    rows = [(i, f"née bluebird opens{i}\n" + f"filler{i} " * 20 + f"\n\nwrite to ann@corp.example or bluebird{i}@other.example\nbluebird") for i in range(8)]
    rows += [(100 + i, f"other{i} words about nothing" + (" bluebird" if i == 7 else "")) for i in range(200)]
    d = spark.createDataFrame(rows, "doc_id long, text string")
    for most in (pii.MOST_TERMS, 0):
        got = {r.doc_id: r for r in pii.digests(d, most_terms=most).collect()}
        for i, t in rows:
            want = [f"term:{m.start()}:{m.end()}" for m in re.finditer(r"\bbluebird\b", t)]
            assert [x for x in got[i].spans.split(",") if x in want] == want
        assert got[107].n_term == 1 and got[106].n_term == 0
    clean = {r.doc_id: r.text for r in pii.sanitised(d).collect()}
    assert "bluebird" not in clean[0] + clean[107] and clean[106] == dict(rows)[106]


def brute_terms(texts, disclose, error):
    """Disclosing terms with their largest share, from every pair of a term and an entity of every level."""
    different = sorted(set(texts))
    holds, stands = {}, {}
    for i, t in enumerate(different):
        raw = t.encode()
        spans = pii.base_spans(raw)
        for k, a, b in spans:
            for e in (pii.entity(k, raw[a:b]), pii.group(k, raw[a:b]), k, "any"):
                holds.setdefault(e, set()).add(i)
        for m in re.finditer(rb"[0-9A-Za-z\x80-\xff]+", raw):
            if len(m[0].decode()) >= pii.MIN_TERM and not any(a < m.end() and m.start() < b for _, a, b in spans):
                stands.setdefault(m[0].decode().translate(LOW), set()).add(i)
    for k in (*range(4), "any"):
        holds.setdefault(k, set())
    n, bound, out = len(different), math.log(max(len(holds) * len(stands), 1) / error), {}
    for e, own in holds.items():
        for t, at in stands.items():
            p, q = len(own) / n, len(at & own) / len(at)
            if own and p < 1 and q > p:
                chance = len(at) * (q * math.log(q / p) + ((1 - q) * math.log((1 - q) / (1 - p)) if q < 1 else 0))
                share = 1 + math.log(q) / -math.log(p)
                if chance >= bound and share >= disclose:
                    out[t] = max(out.get(t, 0), share)
    return out


def test_disclosing_terms_equal_brute_force(spark):
    """Random corpora with terms tied to a value, a domain, a kind and to any personal data, more or less closely."""
    for seed in range(3):
        rnd = random.Random(seed)
        texts = []
        for i in range(400):
            w = [f"word{rnd.randrange(300)}" for _ in range(rnd.randrange(3, 25))] + ["née"] * rnd.randrange(2)
            if i % 9 == 0:
                w += [f"u{i}@{rnd.choice(['a', 'b'])}.example.com"] + ["secretly"] * (rnd.random() < 0.9)
                w += ["alpha"] if w[-2].endswith("@a.example.com") or w[-1].endswith("@a.example.com") else []
            if i % 13 == 0:
                w += [f"10.1.{i % 7}.{i % 200}", "Address", "secretly"] if rnd.random() < 0.8 else ["10.1.0.1"]
            if i % 40 == 1:
                w += ["+1 (555) 123-4567", "Phone"]
            rnd.shuffle(w)
            texts.append(" ".join(w))
        texts += texts[:60]
        d = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
        for disclose, error in ((0.8, 0.05), (0.5, 0.5)):
            want = brute_terms(texts, disclose, error)
            assert want
            got = pii.disclosing(pii.found(d), d, disclose, error)
            assert sorted(r.share for r in got.collect()) == pytest.approx(sorted(want.values()))
            low = {r.doc_id: r for r in pii.digests(d, disclose=disclose, error=error).collect()}
            for i, t in enumerate(texts):
                marked = {t[int(a) : int(b)].translate(LOW) for k, a, b in (x.split(":") for x in low[i].spans.split(",") if x) if k == "term"}
                outside = t
                for r in pii.base_spans(t.encode())[::-1]:
                    outside = outside.replace(t.encode()[r[1] : r[2]].decode(), " ")
                assert marked == want.keys() & set(re.findall(r"[0-9A-Za-zé]+", outside.translate(LOW)))


def test_sanitising_removes_or_generalises(spark):
    """A term that never stands without a kind goes; one that sometimes does keeps its shape."""
    rows = [(i, f"common{i} Ref7x sometimes +1 (555) 123-{4000 + i}") for i in range(40)]
    rows += [(100 + i, f"common{i} words of no note{i}") for i in range(400)] + [(900 + i, f"sometimes other words {i}") for i in range(12)]
    clean = {r.doc_id: r.text for r in pii.sanitised(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert clean[3] == "common3  [x] [phone]"
    assert clean[105] == "common5 words of no note5" and clean[901].startswith("[x] other words")


# ---- urls -----------------------------------------------------------------------------------------------------------------------------------


def test_url_rules(spark):
    urls = [None, "", "nothing", "http://", "http://EXAMPLE.com/en/x?q=/en/", "https://www.example.com/en/a", "https://a.b.example.com/en/", "http://example.com", "http://notexample.com/en/", "ftp://x.net/es/", "http://net/fr/", "http://x.net/de/", "http://com/", "a://b://c.com/", "http://x.com#/en/", "http://example.com/en"]
    urls += ["http://x\x01com/en", "http://example\x01com/en/", "http://example.com\x02/en/"]
    pages = spark.createDataFrame(list(enumerate(urls * 2)), "page_id long, url string").repartition(3)

    def brute(u):
        rest = u.split("://", 1)[1] if u and "://" in u else ""
        host = re.split(r"[/?#]", rest)[0].translate(LOW)
        path = re.split(r"[?#]", rest[len(host) :])[0]
        fits = [(h.count("."), len(p), h + p, v) for v, h, p in url_filter.RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
        return (host, path, max(fits)[2], max(fits)[3]) if fits else (host, path, None, "allow")

    small = {r.page_id: tuple(r)[1:] for r in url_filter.judge(pages, url_filter.RULES).collect()}
    assert small == {i: brute(u) for i, u in enumerate(urls * 2)}
    rules = spark.createDataFrame(url_filter.RULES, "verdict string, host string, path string")
    assert {r.page_id: tuple(r)[1:] for r in url_filter.judge_large(pages, rules).collect()} == small
    assert url_filter.judge(pages.limit(0), url_filter.RULES).count() == 0
    clash = pages.select("page_id", "url", *(F.lit("/").alias(c) for c in ("host", "path", "key", "rule", "verdict")))
    assert {r.page_id: tuple(r)[1:] for r in url_filter.judge(clash, url_filter.RULES).collect()} == small
    own = [("block", "\u00c9a.com", "/"), ("allow", "x.\u00c9A.com", "/a")]
    odd = spark.createDataFrame([(1, "http://X.\u00c9a.Com/a"), (2, "http://\u00e9a.com/"), (None, "http://b.\u00c9A.com/")], "page_id long, url string")
    want = {1: ("x.\u00c9a.com/a", "allow"), 2: (None, "allow"), None: ("\u00c9a.com/", "block")}
    for got in (url_filter.judge(odd, own), url_filter.judge_large(odd, spark.createDataFrame(own, "verdict string, host string, path string"))):
        assert {r.page_id: (r.rule, r.verdict) for r in got.collect()} == want
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 3)  # one sweep over many batches
    try:
        assert {r.page_id: tuple(r)[1:] for r in url_filter.judge(pages, url_filter.RULES).collect()} == small
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_sweep_with_many_nested_rules():
    rnd = random.Random(9)
    names = ["a", "b", "a-b", "c"]
    rules = {(rnd.choice(["allow", "block"]), ".".join(rnd.choices(names, k=rnd.randrange(1, 4))), rnd.choice(["/", "/x/", "/x/y"])) for _ in range(60)}
    table = url_filter.ordered_rules(rules)
    urls = sorted(((".".join(rnd.choices(names, k=rnd.randrange(1, 5))), rnd.choice(["/", "/x/", "/x/yz", ""])) for _ in range(500)), key=lambda u: url_filter.key_of(u[0]).encode())
    got = list(url_filter.sweep([(url_filter.key_of(h), p) for h, p in urls], table))
    for (host, path), winner in zip(urls, got, strict=True):
        fits = [(h.count("."), len(p), v == "block") for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
        assert (winner is None) == (not fits)
        if fits:
            assert winner[1] == ("block" if max(fits)[2] else "allow")


# ---- pipeline ---------------------------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names, before = docs.columns, docs
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        after = stage(spark, before, sf).cache()
        if k < 4:
            assert after.columns == names, name
        if name == "near_dedup":
            want, _ = brute_components({(r.doc_id, r.text) for r in before.collect()})
            assert {r.doc_id for r in after.collect()} == {i for i in want if want[i] == i}
        if name == "line_dedup":
            want = brute_lines([(r.doc_id, r.text) for r in before.collect()])
            had = {r.doc_id for r in before.collect() if WORD.search(r.text or "")}
            assert {r.doc_id: r.text for r in after.collect()} == {i: t for (i, _), t in want.items() if i not in had or WORD.search(t)}
        before = after
    assert before.count() > 0 and before.columns == ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]


def test_pipeline_on_odd_documents(spark, rows, tmp_path):
    """Null, empty and repeated rows, ties, a null doc_id and clashing columns go through; empty tables give nothing."""
    import corpus_pipeline

    d = spark.createDataFrame([*rows, (700, "", "en", "a", 0, "x", 1), (700, "", "en", "a", 0, "x", 1)], SCHEMA)
    d.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, i % 2, 0) for i in range(30)] + [(None, 1, 1)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    again = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert out and sorted(map(str, out)) == sorted(map(str, again))
    wordless = {i for i, t, *_ in rows if not WORD.search(t or "")} | {700}
    assert not wordless & {r.doc_id for r in out} and all(r.n_tokens > 0 for r in out)
    exact = [i for i, t, *_ in rows if t == rows[8][1]]
    assert len({r.doc_id for r in out} & set(exact)) <= 1
    for name in ("documents", "labels"):
        spark.read.parquet(f"{tmp_path}/{name}.parquet").limit(0).write.parquet(f"{tmp_path}/empty/{name}.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/empty").count() == 0


def test_clashing_columns(spark, docs, rows, labels):
    """Columns named like an operator's own don't matter."""
    odd = docs
    for c in ("features", "rejected", "p_toxic", "text_id", "terms", "entities", "kinds", "ids", "media", "frames", "chunk", "held", "own", "size", "block", "d", "t", "i", "h", "node", "stratum", "n_words"):
        odd = odd.withColumn(c, F.lit("odd"))
    plain = lambda df: sorted(map(str, df.collect()))
    path, pattern = byte_bpe.public_vocabulary()
    chain = toxicity.train(docs, labels)
    for f in (
        media_gif.text_media, mixing.mix, lambda x: byte_bpe.digests(x, path, pattern), lambda x: toxicity.scored(x, chain), pii.digests,
        lambda x: quality.judge(x, labels), suffix_tree_lm.scores, near_dup.near_duplicates,
    ):
        assert plain(f(odd)) == plain(f(docs))
    for f in (line_dedup.deduplicated, near_dup.deduplicated, mixing.mixed_documents, lambda x: toxicity.filtered(x, chain)):
        got = f(odd)
        assert got.columns == odd.columns and plain(got.select(docs.columns)) == plain(f(docs))


def test_mix_comes_shard_by_shard(spark):
    """Shards follow the units, each document's copies are those that the shards draw, and texts tell twins apart."""
    rows = [(i, f"{'w ' * (1 + i % 9)}{i}", "ab"[i % 2]) for i in range(9000)] + [(5, f"twin {k} of five", "a") for k in range(4)]
    d = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    got = mixing.mix(d).collect()
    shards = Counter(s for r in got for s in r.shards)
    assert len(shards) >= 2 and set(shards) == set(range(len(shards))) and all(r.taken == r.size * len(r.position_keys) for r in got)
    first = mixing.mixed_documents(d, with_shards=True)
    assert Counter(r.shard for r in first.select("shard").collect()) == shards
    for part in first.rdd.map(lambda r: (r.shard, r.position_key)).glom().collect():
        assert part == sorted(part)
    again = mixing.mixed_documents(d.repartition(3), with_shards=True)
    assert sorted(map(str, first.collect())) == sorted(map(str, again.collect()))


def test_quality_sql_with_certified_cutoffs(spark, tmp_path):
    """On documents with enough labels cutoffs are certified, and the SQL finds the same rows."""
    import duckdb

    from approxmatch.llm import quality_sql

    rnd = random.Random(3)
    rows = []
    for i in range(6000):
        bad = i % 10 == 0
        w = [f"word{rnd.randrange(500)}" + ("#$%" * 2 if bad and rnd.random() < 0.7 else "") for _ in range(30)]
        rows.append((i, " ".join(w), "en" if i % 3 else None))
    d = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    marks = spark.createDataFrame([(i, int(i % 10 > 0)) for i in range(0, 6000)], "doc_id long, quality int")
    d.coalesce(1).write.parquet(f"{tmp_path}/documents")
    marks.coalesce(1).write.parquet(f"{tmp_path}/labels")
    con = duckdb.connect()
    for name in ("documents", "labels"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{tmp_path}/{name}/*.parquet')")
    result = con.execute(quality_sql.sql())
    names = [c[0] for c in result.description]
    want = sorted(tuple(dict(zip(names, r, strict=True))[c] for c in ("doc_id", "base_failed", "kept", "rejected_by")) for r in result.fetchall())
    got = sorted((r.doc_id, r.base_failed, r.kept, ",".join(r.rejected_by)) for r in quality.judge(d, marks).collect())
    assert got == want and sum("symbols" in x[3] for x in got) > 300
