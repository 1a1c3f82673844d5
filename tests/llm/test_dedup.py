"""Substring, suffix-array and Jaccard operators against brute force."""

import random
from collections import Counter

import numpy as np

from roadtraj.llm import jaccard, substrings, suffixes
from tests.llm.fixtures import documents, frame, sha, words


def test_every_difference_is_covered():
    assert {(a - b) % substrings.PERIOD for a in substrings.COVER for b in substrings.COVER} == set(range(substrings.PERIOD))


def test_substrings(spark):
    rows, w = documents(), substrings.WINDOW
    first = {}
    for i, text in ((r[0], r[1]) for r in rows if r[0] is not None):
        seq = words(text)
        for k in range(len(seq) - w + 1):
            key = tuple(seq[k : k + w])
            first[key] = min(first.get(key, i), i)
    want = []
    for i, text, *_ in rows:
        seq = words(text)
        gone = set()
        for k in range(len(seq) - w + 1):
            if i is not None and first[tuple(seq[k : k + w])] < i:
                gone.update(range(k, k + w))
        want.append((i, len(seq), len(gone), sha(" ".join(x for k, x in enumerate(seq) if k not in gone))))
    got = [(r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substrings.remove_repeats(frame(spark)).collect()]
    assert Counter(got) == Counter(want) and sum(x[2] for x in want) > 100


def test_substring_texts_and_empty_table(spark):
    got = {r.doc_id: r.kept_text for r in substrings.remove_repeats(frame(spark), with_text=True).collect() if r.n_removed}
    assert all(len(words(t)) < 400 for t in got.values())
    assert substrings.remove_repeats(frame(spark, [])).count() == 0


def test_suffix_array():
    rng = random.Random(3)
    for _ in range(1500):
        text = [rng.randrange(1, rng.randrange(2, 6)) for _ in range(rng.randrange(40))]
        order = suffixes.suffix_array(text)
        assert order == sorted(range(len(text) + 1), key=lambda i: text[i:])
        common = suffixes.common_prefixes(text, order)
        for a, b, n in zip(order, order[1:], common[1:], strict=False):
            assert text[a : a + n] == text[b : b + n] and text[a : a + n + 1] != text[b : b + n + 1]


def test_places_order_as_the_suffix_array_does():
    """The pass over places gives the array of the text whose symbols carry their places, and its common prefixes."""
    rng = np.random.default_rng(2)
    for _ in range(60):
        rows, width = int(rng.integers(1, 12)), int(rng.integers(1, 7))
        matrix = rng.integers(0, 3, (rows, width)).astype(np.uint8)
        text = [x for row in matrix for x in [*(place * 300 + int(c) + 2 for place, c in enumerate(row)), 1]]
        order = [i for i in suffixes.suffix_array(text) if i < len(text) and text[i] != 1]
        for place, got, common in suffixes.place_orders(np.ascontiguousarray(matrix.T), 200):
            rest = [matrix[r, place:].tolist() for r in got]
            assert rest == [matrix[i // (width + 1), place:].tolist() for i in order if i % (width + 1) == place]
            for a, b, n in zip(rest, rest[1:], common[1:], strict=False):
                assert n == next((k for k in range(len(a)) if a[k] != b[k]), len(a))


def _byte_twin(rows, length=200):
    seen = Counter()
    data = [(i, (t or "").encode()) for i, t, *_ in rows]
    for _, b in data:
        seen.update(b[k : k + length] for k in range(len(b) - length + 1))
    out = []
    for i, b in data:
        gone = bytearray(len(b))
        for k in range(len(b) - length + 1):
            if seen[b[k : k + length]] > 1:
                gone[k : k + length] = b"\1" * length
        spans = sum(1 for k in range(len(b)) if gone[k] and not (k and gone[k - 1]))
        out.append((i, len(b), sum(gone), spans, sha(bytes(x for x, g in zip(b, gone, strict=True) if not g))))
    return Counter(out)


def _byte_rows():
    rng = random.Random(9)
    base = "".join(rng.choice("abcdefgh é") for _ in range(900))
    texts = [base, base[:450] + "X" + base[451:], base[100:420], "ab" * 300, "z" * 201, base[3:202], base[3:203], base[300:700] * 2]
    for _ in range(30):
        a = rng.randrange(600)
        texts.append("".join(rng.choice("xyz") for _ in range(rng.randrange(300))) + base[a : a + rng.randrange(150, 300)] + "".join(rng.choice("xyz") for _ in range(rng.randrange(300))))
    return documents(2, 30) + [(1000 + i, t, None, None, None) for i, t in enumerate(texts)]


def test_suffix_removal(spark):
    rows = _byte_rows()
    got = Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffixes.remove_repeats(frame(spark, rows)).collect())
    assert got == _byte_twin(rows)


def test_suffix_removal_of_hot_anchors(spark, monkeypatch):
    monkeypatch.setattr(suffixes, "MANY", 5)
    rows = _byte_rows()
    got = Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffixes.remove_repeats(frame(spark, rows)).collect())
    assert got == _byte_twin(rows)
    assert suffixes.remove_repeats(frame(spark, [])).count() == 0


def _components(rows, n, percent):
    lower = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for _, text, *_ in rows:
        seq = words((text or "").translate(lower))
        sets.append({tuple(seq[k : k + n]) for k in range(len(seq) - n + 1)} if len(seq) >= n else ({tuple(seq)} if seq else set()))
    top = list(range(len(rows)))

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    for a, x in enumerate(sets):
        for b in range(a):
            y = sets[b]
            both = len(x & y)
            if x and y and 100 * both >= percent * len(x | y):
                top[find(a)] = find(b)
    least = {}
    for k, r in enumerate(rows):
        if r[0] is not None:
            least[find(k)] = min(least.get(find(k), r[0]), r[0])
    return Counter((r[0], len(sets[k]), least.get(find(k), r[0]) if sets[k] else r[0]) for k, r in enumerate(rows))


def test_jaccard(spark):
    rows = documents()
    for n, percent in ((3, 90), (5, 80)):
        got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join_components(frame(spark, rows), n, percent).collect())
        assert got == _components(rows, n, percent)


def test_linked_sets_share_a_signature():
    """Random pairs at and above the bound, tiny sets and sets with many empty segments included."""
    rng = np.random.default_rng(5)
    tried = 0
    for percent in (80, 90):
        for _ in range(400):
            size = int(rng.integers(1, 60)) if rng.random() < 0.5 else int(rng.integers(60, 900))
            pool = rng.integers(0, 1 << 62, 2 * size + 2).astype(np.uint64)
            apart = int(rng.integers(0, size * (100 - percent) // 100 + 1))
            x = np.unique(pool[:size])
            y = np.unique(np.concatenate([x[apart:], pool[size : size + int(rng.integers(0, apart + 1))]]))
            both = len(np.intersect1d(x, y))
            if not len(y) or 100 * both < percent * (len(x) + len(y) - both):
                continue
            tried += 1
            signs, row = jaccard.segment_signatures(np.concatenate([x, y]), np.array([0, len(x), len(x) + len(y)]), percent)
            assert set(signs[row == 0].tolist()) & set(signs[row == 1].tolist())
    assert tried > 300


def test_linked_sets_share_a_rare_signature():
    """Linked sets share more signatures of a level than a set leaves out, so the rarest of them stays in both."""
    rng = np.random.default_rng(7)
    tried = spared = 0
    for _ in range(400):
        size = int(rng.integers(1, 60)) if rng.random() < 0.5 else int(rng.integers(60, 900))
        pool = rng.integers(0, 1 << 62, 2 * size + 2).astype(np.uint64)
        apart = int(rng.integers(0, size * 20 // 100 + 1))
        x = np.unique(pool[:size])
        y = np.unique(np.concatenate([x[apart:], pool[size : size + int(rng.integers(0, apart + 1))]]))
        both = len(np.intersect1d(x, y))
        if not len(y) or 100 * both < 80 * (len(x) + len(y) - both):
            continue
        tried += 1
        h, row, level, surplus = jaccard.level_signatures(np.concatenate([x, y]), np.array([0, len(x), len(x) + len(y)]), 80)
        for at in np.unique(level):
            own = [level == at, row == 0], [level == at, row == 1]
            shared = np.intersect1d(*(h[a & b] for a, b in own))
            if len(shared):
                assert all(len(shared) > surplus[a & b].max() for a, b in own)
        spared += surplus.max() > 0
    assert tried > 150 and spared > 50


def test_jaccard_grid_of_a_common_passage(spark, monkeypatch):
    """A passage found in all documents does not bring them together in one grid, whose rows grow with the square."""
    monkeypatch.setattr(jaccard, "BLOCK_WEIGHT", 5000)
    placed, join = [], jaccard._with_text
    monkeypatch.setattr(jaccard, "_with_text", lambda rows, texts: (placed.append(rows.count()), join(rows, texts))[1])
    rng = random.Random(11)
    word = lambda: f"w{rng.randrange(10**7)}"
    passage, rows = [word() for _ in range(24)], []
    for i in range(120):
        own = [word() for _ in range(70)]
        rows += [(2 * i, " ".join(own + passage), None, None, None), (2 * i + 1, " ".join(own[1 + i % 3 * 20 :] + passage), None, None, None)]
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join_components(frame(spark, rows)).collect())
    assert got == _components(rows, 5, 80) and len({k[2] for k in got}) == 200
    assert placed[1] < 480


def test_overlaps_are_a_product(monkeypatch):
    monkeypatch.setattr(jaccard, "_DENSE", 3)
    rng = np.random.default_rng(6)
    sets = [np.unique(rng.integers(0, 40, rng.integers(0, 30))).astype(np.uint64) for _ in range(25)]
    got = jaccard.overlaps(np.concatenate(sets), np.concatenate([[0], np.cumsum([len(s) for s in sets])]))
    for a in range(25):
        for b in range(a + 1, 25):
            assert got[a, b] == len(np.intersect1d(sets[a], sets[b]))


def test_jaccard_grid(spark, monkeypatch):
    """Families that share signatures without being linked, and chains between them, over many blocks of the grid."""
    monkeypatch.setattr(jaccard, "BLOCK_WEIGHT", 1000)
    rng = random.Random(8)
    base = [f"w{rng.randrange(10**6)}" for _ in range(120)]
    rows = []
    for i in range(60):
        near = list(base)
        for _ in range(rng.randrange(0, 5)):
            near[rng.randrange(120)] = f"edit{rng.randrange(40)}"
        rows.append((i, " ".join(near), None, None, None))
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join_components(frame(spark, rows), 3, 90).collect())
    assert got == _components(rows, 3, 90) and 3 < len({k[2] for k in got}) < 60


def test_jaccard_blocks(spark, monkeypatch):
    """A group in many blocks, linked only through its centre."""
    monkeypatch.setattr(jaccard, "BLOCK_WEIGHT", 1500)
    rng = random.Random(4)
    centre = [f"w{rng.randrange(10**6)}" for _ in range(60)]
    rows = [(0, " ".join(centre), None, None, None)]
    for i in range(1, 40):
        near = list(centre)
        near[rng.randrange(60)] = f"edit{i}"
        rows.append((i, " ".join(near), None, None, None))
    got = Counter((r.doc_id, r.n_shingles, r.component_id) for r in jaccard.join_components(frame(spark, rows), 3, 90).collect())
    assert got == _components(rows, 3, 90)


def test_keep_one(spark):
    kept = jaccard.keep_one(frame(spark))
    found = {r.doc_id: r.component_id for r in jaccard.join_components(frame(spark)).collect()}
    ids = [r.doc_id for r in kept.select("doc_id").collect() if r.doc_id is not None]
    assert set(ids) == {d for d, c in found.items() if d is not None and d == c} and kept.columns == frame(spark).columns
    assert jaccard.keep_one(frame(spark, [])).count() == 0


def test_materialize_leaves_no_shuffle_files(spark):
    """Disk is given back when a table is written, not when the driver next collects garbage."""
    import os
    import time

    from roadtraj.llm.scratch import materialize, release

    blocks = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager()

    def shuffled():
        found = blocks.getAllBlocks()
        return {b.toString() for b in map(found.apply, range(found.size())) if b.isShuffle()}

    before = shuffled()
    table = materialize(spark.range(20_000).groupBy("id").count(), "t")
    for _ in range(50):
        if not shuffled() - before:
            break
        time.sleep(0.2)
    assert not shuffled() - before and table.count() == 20_000
    release(table)
    assert not os.path.exists(table._scratch.removeprefix("file://"))
