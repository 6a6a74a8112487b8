import hashlib
import random
from collections import Counter

import numpy as np
import xxhash
from pyspark.sql import functions as F

from graphkw.llm import line_dedup
from graphkw.llm.base import Stage, by_bytes
from graphkw.llm.components import components
from graphkw.llm.decontaminate import TestSet, drop_contaminated, find_contamination, load_tests, locate_matches, words_of
from graphkw.llm.line_dedup import dedup_lines, hashed_lines
from graphkw.llm.minhash import drop_near_duplicates, linked, near_duplicates
from graphkw.llm.sketches import WordHashes, fast_sketch, shingle_set
from graphkw.llm.suffix_dedup import contexts, cover, remove_repeats, repeated_windows, sort_suffixes
from tests.llm.conftest import ODD


def test_components(spark):
    draw = random.Random(4)
    edges = [(draw.randrange(60), draw.randrange(60)) for _ in range(45)] + [(100, k) for k in range(101, 160)]
    root = {}

    def top(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        x, y = top(a), top(b)
        root[max(x, y)] = min(x, y)
    got = {r.node: r.root for r in components(spark.createDataFrame(edges, "x long, y long"), "t").collect()}
    assert got == {v: top(v) for v in list(root) if top(v) != v}
    assert components(spark.createDataFrame([], "x long, y long"), "t").count() == 0


def test_sketch_fills_and_estimates():
    draw = np.random.default_rng(0)
    for n in (1, 2, 5, 60, 500):
        s = draw.integers(0, 2**63, n).astype(np.uint64)
        assert (fast_sketch(s, 64) != np.uint64(2**64 - 1)).all()
    a = draw.integers(0, 2**63, 1000).astype(np.uint64)
    b = np.concatenate([a[:800], draw.integers(0, 2**63, 200).astype(np.uint64)])
    same = np.mean([(fast_sketch(a ^ np.uint64(k), 128) == fast_sketch(b ^ np.uint64(k), 128)).mean() for k in range(20)])
    assert abs(same - 800 / 1200) < 0.04


def _components(sets, ids, num, den):
    root = dict.fromkeys(range(len(ids)), None)
    for i in root:
        root[i] = i

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(ids)):
        for j in range(i):
            c = len(sets[i] & sets[j])
            if sets[i] and sets[j] and den * c >= num * (len(sets[i]) + len(sets[j]) - c):
                root[top(i)] = top(j)
    groups = {}
    for i in range(len(ids)):
        groups.setdefault(top(i), []).append(ids[i])
    return {ids[i]: min(groups[top(i)]) for i in range(len(ids))}


def _copies(seed, bases=8, each=25):
    draw, out = random.Random(seed), []
    for _ in range(bases):
        base = [f"w{draw.randrange(3000)}" for _ in range(draw.randint(3, 150))]
        for _ in range(each):
            words = list(base)
            for _ in range(draw.choice([0, 0, 1, 2, 5, 12])):
                words[draw.randrange(len(words))] = f"x{draw.randrange(9999)}"
            out.append(" ".join(words))
    draw.shuffle(out)
    return list(enumerate(out))


def test_near_duplicates_against_brute_force(docs):
    rows = _copies(1) + [(1000, ""), (1001, None), (1002, "one two"), (1003, "One TWO"), (1004, "one")]
    hashes = WordHashes()
    sets = [set(shingle_set(t, 3, hashes).tolist()) for _, t in rows]
    want = _components(sets, [i for i, _ in rows], 85, 100)
    for block in (512, 7):
        got = {r.doc_id: (r.component_id, r.n_shingles) for r in near_duplicates(docs(rows), 3, 85, 100, block=block).collect()}
        assert got == {i: (want[i], len(s)) for (i, _), s in zip(rows, sets, strict=True)}


def test_drop_near_duplicates_keeps_one_of_each(docs):
    rows = _copies(2, 4, 10)
    kept = drop_near_duplicates(docs(rows + ODD))
    assert kept.columns == docs([]).columns
    ids = [r.doc_id for r in kept.collect()]
    hashes = WordHashes()
    want = _components([set(shingle_set(t, 5, hashes).tolist()) for _, t in rows], [i for i, _ in rows], 80, 100)
    assert {i for i in ids if i is not None and i < 40 and i > 6} == {i for i in want if want[i] == i and i > 6}
    assert drop_near_duplicates(docs([])).count() == 0


def test_linked_two_blocks_only_crosses():
    a = np.arange(50, dtype=np.uint64)
    sets = [a, a.copy(), a.copy()]
    assert len(linked(sets, np.array([True, True, True]), 85, 100)) == 2
    assert sorted(linked(sets, np.array([True, False, False]), 85, 100)) == [(0, 1), (0, 2)]
    assert linked(sets, np.array([True, True, True]), 85, 100, columns=7) == linked(sets, np.array([True, True, True]), 85, 100)


def _hits(text, items, window=10):
    words = words_of(text)
    hit, found, far = set(), set(), 0
    for name, t in items:
        w = words_of(t)
        n = min(window, len(w))
        for q in range(len(w) - n + 1 if w else 0):
            for p in range(len(words) - n + 1):
                if words[p : p + n] == w[q : q + n]:
                    hit |= set(range(p, p + n))
                    found.add(str(name))
                    k = n
                    while p + k < len(words) and q + k < len(w) and words[p + k] == w[q + k]:
                        k += 1
                    far = max(far, k)
    ids = ",".join(sorted(found))
    return len(words), len(hit), len(found), hashlib.sha256(ids.encode()).hexdigest(), bool(hit), far


def test_contamination_against_brute_force(spark, docs):
    draw = random.Random(6)
    vocabulary = [f"t{k}" for k in range(12)]
    items = [(k, " ".join(draw.choice(vocabulary) for _ in range(n))) for k, n in enumerate([3, 9, 10, 11, 25, 60, 1, 2])] + [(90, None), (91, "..."), (92, "T1-t2 t3")]
    rows = []
    for i in range(120):
        words = [draw.choice(vocabulary) for _ in range(draw.randint(0, 60))]
        if i % 3 == 0:
            w = draw.choice(items[:6])[1].split()
            a = draw.randrange(len(w))
            words[10:10] = w[a : a + draw.randint(5, 30)]
        rows.append((i, " ".join(words)))
    rows += [(500, None), (501, ""), (502, "t1, T2! t3")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    test = load_tests(bench)
    for shard in (1 << 22, 300):
        got = {r[0]: tuple(r[1:]) for r in find_contamination(docs(rows), test, shard).collect()}
        assert got == {i: _hits(t, items) for i, t in rows}
    clean = {i for i, t in rows if not _hits(t, items)[4]}
    assert {r.doc_id for r in drop_contaminated(docs(rows), test).collect()} == clean
    places = locate_matches(docs(rows), test).collect()
    text = dict(rows)
    assert places and all(len(words_of(text[r.doc_id])) >= r.doc_word + r.n_match for r in places)
    assert find_contamination(docs(ODD), load_tests(bench.limit(0))).filter("contaminated").count() == 0
    assert TestSet([], 10).names == []


def test_difference_cover():
    for m in (2, 4, 8):
        inside, steps = cover(m)
        v = m * m
        assert all(inside[(i + steps[i, j]) % v] and inside[(j + steps[i, j]) % v] and steps[i, j] < v for i in range(v) for j in range(v))


def test_suffix_order_and_repeats():
    draw = np.random.default_rng(3)
    for kind in range(3):
        data = draw.integers(97, 99 if kind else 120, 3000).astype(np.uint8)
        if kind == 2:
            data = np.tile(data[:137], 22)[:3000]
        starts = np.sort(draw.choice(2500, 400, replace=False))
        bucket = draw.integers(0, 3, 400)
        order, _ = sort_suffixes(data, starts, bucket, 400)
        raw = data.tobytes()
        keys = [(int(bucket[k]), raw[starts[k] : starts[k] + 400]) for k in order]
        assert keys == sorted(keys)
        count = Counter((int(b), raw[s : s + 100]) for s, b in zip(starts, bucket, strict=True))
        assert repeated_windows(data, starts, bucket, 100).tolist() == [count[int(b), raw[s : s + 100]] > 1 for s, b in zip(starts, bucket, strict=True)]


def _strip(rows, length):
    texts = [(t or "").encode() for _, t in rows]
    count = Counter(b[i : i + length] for b in texts for i in range(len(b) - length + 1))
    out = []
    for (doc, _), b in zip(rows, texts, strict=True):
        gone = [False] * len(b)
        for i in range(len(b) - length + 1):
            if count[b[i : i + length]] > 1:
                gone[i : i + length] = [True] * length
        left = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        out.append((doc, len(b), sum(gone), sum(g and not (i and gone[i - 1]) for i, g in enumerate(gone)), hashlib.sha256(left).hexdigest()))
    return sorted(out, key=str)


def test_contexts_of_bytes_beyond_ascii():
    assert list(by_bytes(["éé", "éé".encode(), b"abcd", None, "x"], 8)) == [(0, 2), (2, 5)]
    raw = ("é日本ß" * 60).encode()
    text, _, _, _, lo, hi = contexts([b"short", raw], 400, 256)
    assert set(text) == {1} and sorted(x for a, b in zip(lo, hi, strict=True) for x in range(a, b + 1)) == list(range(len(raw) - 399))


def test_remove_repeats_against_brute_force(docs):
    draw = random.Random(8)
    pool = ["".join(draw.choice("abcd é") for _ in range(draw.randint(20, 90))) for _ in range(6)]
    rows = []
    for i in range(60):
        parts = [draw.choice(pool) if draw.random() < 0.5 else "".join(draw.choice("xyz ") for _ in range(30)) for _ in range(draw.randint(0, 8))]
        rows.append((i, "".join(parts)))
    rows += [(70, None), (71, ""), (72, "ab" * 200), (73, "q" * 41), (5, rows[5][1]), (None, rows[6][1])]
    for gram, limit in ((26, 20_000), (26, 2)):
        from graphkw.llm import suffix_dedup

        kept, suffix_dedup.repeated_runs.__defaults__ = suffix_dedup.repeated_runs.__defaults__, (40, gram, 1 << 12, limit)
        try:
            got = sorted(map(tuple, remove_repeats(docs(rows), 40, gram).collect()), key=str)
        finally:
            suffix_dedup.repeated_runs.__defaults__ = kept
        assert got == _strip(rows, 40)
    assert remove_repeats(docs([]), 40, 26).count() == 0


def _simhash(line):
    words = list(dict.fromkeys(line.split(" ")))
    hashes = [xxhash.xxh64_intdigest(w.encode(), 42) for w in words]
    if len(words) % 2 == 0:  # the least as a signed number counts twice
        hashes.append(min(hashes, key=lambda h: h - (1 << 64) if h >> 63 else h))
    sim = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))
    return sim if len(words) >= line_dedup.LEAST_WORDS else None


def _edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        prior, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            prior, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, prior + (x != y))
    return row[-1]


def _normal(line):
    return "".join("0" if c in "123456789" else c for c in line.lower() if not ("!" <= c <= "~") or c.isalnum()).strip(" ")


def test_line_dedup_against_brute_force(docs):
    draw = random.Random(9)
    bases = [["".join(draw.choice("abcdefghü") for _ in range(5)) for _ in range(draw.randint(9, 40))] for _ in range(12)]
    rows = []
    for i in range(60):
        lines = []
        for _ in range(draw.randint(0, 6)):
            words = list(draw.choice(bases))
            if draw.random() < 0.6:
                words[draw.randrange(len(words))] = draw.choice(["und", "oder", "Wort7", "Wort8"])
            lines.append(draw.choice(["{}", "{}.", "  {}", "{}!"]).format(" ".join(words)))
        lines += draw.choice([[], ["short line"], ["Short  line"], ["", "---"], [f"number {i}"]])
        rows.append((i, "\n".join(lines)))
    places = [(i, k, _normal(line)) for i, t in rows for k, line in enumerate(t.split("\n"))]
    distinct = sorted({n for _, _, n in places if n})
    sims = {n: _simhash(n) for n in distinct}
    root = {n: n for n in distinct}

    def top(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in distinct:
        for b in distinct:
            if a < b and sims[a] is not None and sims[b] is not None and (sims[a] ^ sims[b]).bit_count() <= line_dedup.MOST and _edits(a, b) <= int(0.1 * max(len(a), len(b)) + 1e-9):
                root[top(a)] = top(b)
    first = {}
    for i, k, n in places:
        if n:
            first.setdefault(top(n), (i, k))
    want = {i: "\n".join(line for k, line in enumerate(t.split("\n")) if not _normal(line) or first[top(_normal(line))] == (i, k)) for i, t in rows}
    got = {r.doc_id: r.text for r in dedup_lines(docs(rows)).collect()}
    assert got == want
    sims_got = {(r.doc_id, r.pos): None if r.sim is None else r.sim & (2**64 - 1) for r in hashed_lines(docs(rows)).collect()}
    assert all(sims_got[i, k] == (sims[n] if n else None) for i, k, n in places)


def _joined(docs, pairs):
    """Which of the pairs of lines lost its second line."""
    got = {r.doc_id: r.n_removed for r in dedup_lines(docs([(i, line) for i, line in enumerate(x for p in pairs for x in p)])).collect()}
    assert not any(got[2 * k] for k in range(len(pairs)))
    return [got[2 * k + 1] == 1 for k in range(len(pairs))]


def test_line_dedup_finds_lines_by_edit_similarity_alone(docs):
    draw = random.Random(11)
    word = lambda: "".join(draw.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(draw.randint(3, 9)))
    swapped, typed = [], []
    for n in (10, 12, 20, 30, 50, 100, 200):
        for _ in range(20):
            a = [word() for _ in range(n)]
            b = list(a)
            b[draw.randrange(n)] = word()
            swapped.append((" ".join(a), " ".join(b)))
            c = list(" ".join(a))
            for k in draw.sample(range(len(c)), len(c) // 15):
                c[k] = draw.choice("bcdfg")
            typed.append((" ".join(a), "".join(c)))
    for pairs, least in ((swapped, 0.99), (typed, 0.95)):
        near = [_edits(_normal(a), _normal(b)) <= int(0.1 * max(len(_normal(a)), len(_normal(b))) + 1e-9) and len(min(a, b, key=len)) >= 50 for a, b in pairs]
        got = _joined(docs, pairs)
        assert sum(near) > 100 and sum(g and n for g, n in zip(got, near, strict=True)) >= least * sum(near)


def test_line_dedup_short_and_long_lines(docs):
    draw = random.Random(12)
    pairs, want = [("the quick brown foxes jumped over a gate", "the quick brown foxes jumqed over a gate"), ("abcdefghij", "abcdefghi"), ("abcdefghk", "abcdefghl")], [True, True, False]
    for n in [*range(11, 66)] * 2:
        a = "".join(draw.choice("abcdefghijkl ") for _ in range(n)).strip() + "m" * 3
        for extra in (0, 1):
            b, left = list(a), int(0.1 * len(a) + 1e-9) + extra
            for _ in range(left):
                k, kind = draw.randrange(len(b)), draw.randrange(3)
                b[k : k + (kind > 0)] = [draw.choice("xyz")] if kind < 2 else []
            b = "".join(b).strip()
            if len(max(a, b, key=len)) <= 59:
                pairs.append((f"{a}", b)) if extra == 0 else pairs.append((a[::-1], b[::-1]))
                want.append(_edits(*pairs[-1]) <= int(0.1 * max(map(len, pairs[-1])) + 1e-9))
    words = ["".join(draw.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(6)) for _ in range(300)]
    scattered, cut = list(words), list(words)
    for k in range(5, 300, 30):
        scattered[k] = "qq"  # many shingles change, few characters
    cut[:20] = ["z" * 40] * 20  # few shingles change, many characters
    pairs += [(" ".join(words), " ".join(scattered))]
    want += [True]
    assert _joined(docs, pairs) == want and sum(want) > 80
    assert _joined(docs, [(" ".join(words), " ".join(cut))]) == [False]
    many = [f"{k:05x}".translate(str.maketrans("0123456789", "ghijklmnop")) for k in range(17_000)]
    assert _joined(docs, [(" ".join(many), " ".join([*many[:-1], "changed"]))]) == [True]


def test_line_grams_keep_their_place_in_characters(spark):
    rng = random.Random(5)
    lines = [" ".join("".join(rng.choice("aeobé0日x") for _ in range(rng.randint(0, 9))) for _ in range(n)).strip() for n in (12, 30, 90, 400)]
    rows = spark.createDataFrame([(t,) for t in lines], "line string")
    mask = F.lit(~line_dedup._PLACE).cast("long")
    for kind, (begin, size, _, _) in enumerate(line_dedup.KINDS):
        keys = rows.select("line", F.explode(line_dedup._least_grams(kind)).alias("p")).withColumn("at", F.col("p").bitwiseAND(F.lit(line_dedup._PLACE).cast("long")))
        gram = F.substring(F.concat(F.lit(" "), "line"), F.col("at").cast("int") + (2 if begin else 1), F.lit(size))
        assert keys.count() > 20
        assert keys.filter(F.xxhash64(gram, F.lit(kind)).bitwiseAND(mask) != F.col("p").bitwiseAND(mask)).count() == 0
    # As many words before the gram, but not as many characters: 24 of 96 can't all be edits of one.
    places = [{"chars": 96, "i": 10}, {"chars": 96, "i": 34}]
    a, b = (lambda c, x=x: F.lit(x[c]) for x in places)
    assert not spark.range(1).select(line_dedup._fits(a, b, 0.9)).first()[0]


def test_words_at_equal_places_settle_alike_lines_only(spark):
    rng = random.Random(6)
    pairs = []
    for _ in range(200):
        words = ["".join(rng.choice("abcde") for _ in range(rng.randint(0, 8))) for _ in range(rng.randint(1, 20))]
        other = [w if rng.random() < 0.8 else "".join(rng.choice("abcde") for _ in range(rng.randint(0, 8))) for w in words]
        pairs.append((" ".join(words), " ".join(other[: rng.choice([len(other), len(other) - 1])]), rng.randint(0, 12)))
    got = spark.createDataFrame(pairs, "x string, y string, most int").select("x", "y", "most", line_dedup._by_words("x", "y", "most").alias("settled")).collect()
    assert {r.settled for r in got} == {True, False}
    assert all(_edits(r.x, r.y) <= r.most for r in got if r.settled)


def test_lines_of_one_passage_make_no_rows_but_links(spark):
    rng = random.Random(7)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(3, 9)))
    passage = [word() for _ in range(45)]
    heads = [[word() for _ in range(15)] for _ in range(60)]
    near = [[*h[:4], word(), *h[5:]] for h in heads]
    lines = [" ".join([*h, *passage]) for pair in zip(heads, near, strict=True) for h in pair]
    want = [_edits(a, b) <= int(0.1 * max(len(a), len(b)) + 1e-9) for a, b in zip(lines[::2], lines[1::2], strict=True)]
    # Every two lines share keys of the passage, one of them at two places; only alike ones make a row.
    text = spark.createDataFrame(list(enumerate(lines)), "id long, line string").select("id", "line", line_dedup._counts("line").alias("counts"))
    places = [(key, k, len(line), len(line) - back, k) for k, line in enumerate(lines) for key, back in ((1, 200), (2, 150), (2, 143), (3, 90))]
    rows = spark.createDataFrame(places, "key long, id long, chars int, i int, root long")
    for cell in (1 << 17, 3000):
        got = line_dedup._array_links(line_dedup._cells(rows, text, cell), 0.9).collect()
        assert sorted(map(tuple, got)) == [(2 * k + 1, 2 * k) for k, w in enumerate(want) if w] and sum(want) > 50


def test_arrays_are_searched_in_parts_with_the_same_links(spark):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(3, 9)))
    passage = [word() for _ in range(45)]
    lines = [" ".join([*h, *passage]) for h in ([word() for _ in range(15)] for _ in range(30)) for h in (h, [*h[:4], word(), *h[5:]])]
    text = spark.createDataFrame(list(enumerate(lines)), "id long, line string").select("id", "line", line_dedup._counts("line").alias("counts"))
    places = [(key, k, len(line), len(line) - back, k) for k, line in enumerate(lines) for key, back in ((1, 200), (2, 150), (2, 143), (3, 90))]
    rows = spark.createDataFrame(places, "key long, id long, chars int, i int, root long")
    whole = sorted(map(tuple, line_dedup._array_links(line_dedup._cells(rows, text, 6000), 0.9).collect()))
    stages = line_dedup._searched(rows, text, 0.9, 6000, 600_000)
    got = [tuple(r) for s in stages for r in s.df.collect()]
    # All pairs of arrays at once would be moved as one job.
    assert len(stages) > 1 and sorted(got) == whole and len(whole) > 20


def test_a_stage_leaves_no_shuffle_files(spark):
    before = spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled")
    status = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses
    held = status().size()
    df = spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count()
    stage = Stage(df, "seven")
    # The frame is still held here, so the garbage collection alone could not have freed them.
    assert status().size() <= held and df.columns == ["k", "count"] and stage.df.count() == 7
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == before
    stage.drop()


def test_line_dedup_odd_rows(docs):
    out = dedup_lines(docs(ODD).withColumn("n_lines", F.lit("clash")))
    rows = out.collect()
    assert len(rows) == len(ODD) and out.columns.count("n_lines") == 1
    by = {r.doc_id: r for r in rows if r.doc_id is not None}
    assert by[1].text is None and by[2].text == "" and by[3].text == "   \n\t " and by[4].text == "a b c"
    assert dedup_lines(docs([])).count() == 0
