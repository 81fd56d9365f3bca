import itertools
import random
from pathlib import Path

import pyarrow as pa

from tiersort.llm import simhash
from tiersort.llm.common import components, shared_dir
from tiersort.llm.queries import op2_simhash
from helpers import DATA, plain_components, plain_fingerprint

TEXTS = [(1, None), (2, ""), (3, "One two"), (4, "one  TWO"), (5, "a b c d e f g"), (6, "a b c d e f g"), (7, "É é È " * 40), (8, "x\x0by\x1cz w"),
         (9, " \t\n"), (10, "word " * 70000)]


def test_masks_cover():
    for radius in (1, 2, 3):
        masks = simhash.covering_masks(radius)
        assert len(masks) == 2 ** (radius + 1) - 1
        for bits in itertools.islice(itertools.combinations(range(64), radius), 0, None, 7):
            assert any(all(not m >> b & 1 for b in bits) for m in masks)
        assert all(16 <= m.bit_count() <= 44 for m in masks)


def test_fingerprints_edge_cases(spark):
    df = spark.createDataFrame([(i, t, "x") for i, t in TEXTS], "doc_id long, text string, fp string")
    got = {r.id: r.fp & (2 ** 64 - 1) for r in simhash.fingerprints(df).collect()}
    assert got == {i: plain_fingerprint(t) for i, t in TEXTS}
    assert simhash.classes(simhash.fingerprints(df.limit(0))).count() == 0


def test_classes_match_all_pairs_with_large_buckets(spark):
    rng = random.Random(3)
    base = [rng.getrandbits(64) for _ in range(40)]
    fps = [b ^ sum(1 << rng.randrange(64) for _ in range(rng.randrange(6))) for b in base for _ in range(4)]
    hub = rng.getrandbits(64)  # many fingerprints that agree on most bits: a bucket over the pairwise bound
    fps += [hub ^ (1 << a) ^ (1 << b) for a, b in itertools.islice(itertools.combinations(range(64), 2), 300)]
    fps = [f & (2 ** 64 - 1) for f in fps]
    rows = [(i, f - 2 ** 64 if f >= 2 ** 63 else f) for i, f in enumerate(fps)]
    got = {r.id: r.component for r in simhash.classes(spark.createDataFrame(rows, "id long, fp long")).collect()}
    edges = [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 2]
    assert got == plain_components(range(len(fps)), edges)


def test_components_of_long_paths(spark):
    path = [(i, i + 1) for i in range(0, 300)] + [(1000 + i, 1000) for i in range(50)]
    got = {r.id: r.component for r in components(spark.createDataFrame(path, "u long, v long")).collect()}
    assert got == plain_components({x for e in path for x in e}, path)
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_query_matches_brute_force(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text").collect()
    fps = {r.doc_id: plain_fingerprint(r.text) for r in docs}
    ids = sorted(fps)
    edges = [(a, b) for a, b in itertools.combinations(ids, 2) if (fps[a] ^ fps[b]).bit_count() <= 2]
    want = plain_components(ids, edges)
    got = op2_simhash(spark, DATA).collect()
    assert sorted((r.doc_id, r.fingerprint, r.component_id) for r in got) == [(i, f"{fps[i]:016x}", want[i]) for i in ids]


def test_near_classes_catch_edited_copies(spark):
    rng = random.Random(5)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randrange(3, 8)))
    rows, n = [], 0
    for g in range(30):
        base = [word() for _ in range(300)]
        for copy in range(4):
            w = list(base)
            for at in rng.sample(range(300), copy):  # up to three words changed
                w[at] = word()
            rows.append((n, " ".join(w), g))
            n += 1
    df = spark.createDataFrame(rows + [(n, None, None), (n + 1, "", None)], "doc_id long, text string, id int")
    got = {r.id: r.component for r in simhash.near_classes(df).collect()}
    assert all(got[i] == i // 4 * 4 for i in range(n))
    assert got[n] == got[n + 1] == n  # null and empty texts are copies of each other


def test_near_classes_are_those_of_all_pairs(spark):
    rng = random.Random(9)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(6))
    texts = []
    for _ in range(25):
        base = [word() for _ in range(300)]
        for changed in (0, 6, 7, 9, 12):  # similarities of about 0.82, 0.79, 0.73 and 0.66 to the first
            w = list(base)
            for at in rng.sample(range(0, 300, 6), changed):
                w[at] = word()
            texts.append(w)
            if changed == 12:  # an edited copy of a text that is unlike the first one
                texts.append([*w[:-1], word()])
    sets = [{tuple(w[i:i + 5]) for i in range(len(w) - 4)} for w in texts]
    edges = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "doc_id long, text string")
    got = {r.id: r.component for r in simhash.near_classes(df).collect()}
    assert got == plain_components(range(len(texts)), edges)


def test_unlike_members_of_a_band_are_never_rows(spark, monkeypatch):
    """Texts of one body that resemble each other at 0.6 to 0.78: no pair of them leaves a join."""
    rng = random.Random(11)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(6))
    base, texts = [word() for _ in range(150)], []
    for _ in range(120):
        w = list(base)
        for at in rng.sample(range(2, 150, 6), 3):
            w[at] = word()
        texts.append(w)
    texts.append([*texts[7][:-1], word()])
    sets = [{tuple(w[i:i + 5]) for i in range(len(w) - 4)} for w in texts]
    edges = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])]
    made, real = [], simhash.similar
    monkeypatch.setattr(simhash, "similar", lambda pairs, *a: made.append(pairs.count()) or real(pairs, *a))
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "doc_id long, text string")
    got = {r.id: r.component for r in simhash.near_classes(df).collect()}
    assert got == plain_components(range(len(texts)), edges) and got[120] == 7
    assert sum(made) < len(texts) * (len(texts) - 1) / 8  # against first members only, not each other


def test_large_groups_are_taken_apart_without_losing_links(spark, monkeypatch):
    """Blocks, groups over ``most`` texts and components off the driver give the classes of all pairs."""
    rng = random.Random(13)
    word = lambda: "".join(rng.choice("abcdefghijklmnop") for _ in range(6))
    texts = []
    for size in (40, 9, 3):
        base = [word() for _ in range(150)]
        for k in range(size):
            w = list(base)
            for at in rng.sample(range(2, 150, 6), k % 4):
                w[at] = word()
            texts.append(w)
    sets = [{tuple(w[i:i + 5]) for i in range(len(w) - 4)} for w in texts]
    edges = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])]
    want = plain_components(range(len(texts)), edges)
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(texts)], "doc_id long, text string")
    monkeypatch.setattr(simhash, "BLOCK", 4)
    for options in ({}, {"most": 10}, {"most": 10, "few": 0}):
        assert {r.id: r.component for r in simhash.near_classes(df, **options).collect()} == want, options


def test_links_of_blocks_are_a_forest_of_all_pairs():
    rng = random.Random(17)
    sets = [sorted(rng.sample(range(12), rng.randrange(6, 12))) for _ in range(60)]
    edges = [(i, j) for i, j in itertools.combinations(range(60), 2) if i % 2 != j % 2
             and 10 * len({*sets[i]} & {*sets[j]}) >= 8 * len({*sets[i]} | {*sets[j]})]
    t = pa.table({"a": [0] * 60, "b": [1] * 60, "id": range(60), "block": [i % 2 for i in range(60)], "shingles": sets})
    got = simhash.alike(8)(t).to_pylist()
    assert len(got) < 60 and plain_components(range(60), [(r["u"], r["v"]) for r in got]) == plain_components(range(60), edges)


def test_near_texts_take_few_jobs_and_leave_no_sets(spark):
    """A driver of 1.5 GB keeps what it knows of each job, and each staged set of shingles is more than its text."""
    texts = [" ".join(f"w{g}x{i if i != c * 40 else -c}" for i in range(200)) for g in range(5) for c in range(4)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    before = set(Path(shared_dir(spark).removeprefix("file:")).glob("tiersort-*/sketch"))
    spark.sparkContext.setJobGroup("near", "near_texts")
    try:
        found = simhash.near_texts(df)
        assert found.select("class").distinct().count() == 5
        jobs = spark.sparkContext.statusTracker().getJobIdsForGroup("near")
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(jobs) < 60
    assert set(Path(shared_dir(spark).removeprefix("file:")).glob("tiersort-*/sketch")) == before
