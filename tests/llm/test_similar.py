"""The pipeline's near-duplicate stage against all pairs compared by their whole shingle sets."""

import random
import time

import pytest

import corpus_pipeline
from cohort_engine.llm import common, quality_rules, simhash, similar

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def _kept(texts):
    """Of each group of texts that pairs at 0.8 or more connect, the smallest id, by comparing all pairs."""
    words = {i: (t or "").lower().split() for i, t in texts.items()}
    sets = {i: set(zip(*(w[k:] for k in range(5)), strict=False)) if len(w) >= 5 else {tuple(w)} for i, w in words.items()}
    root = {i: i for i in texts}
    for a in sorted(sets):
        for b in sorted(sets):
            both = len(sets[a] & sets[b])
            if a < b and root[a] != root[b] and 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                x, y = root[a], root[b]
                root = {k: min(x, y) if v in (x, y) else v for k, v in root.items()}
    return set(root.values())


def test_stage_by_brute_force(spark, data):
    docs = quality_rules.keep_clean(spark.read.parquet(f"{data}/documents.parquet")).cache()
    got = [r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, data).collect()]
    assert len(got) == len(set(got)) and set(got) == _kept({r["doc_id"]: r["text"] for r in docs.collect()})


@pytest.mark.parametrize("seed", [1, 2])
def test_edited_copies(spark, data, seed):
    """Copies with edits on both sides of the limit, chains of them, and a group that no single member is near to all of."""
    r = random.Random(seed)
    texts = {}
    for _ in range(12):
        words = [f"w{r.randrange(10**6)}" for _ in range(r.choice((20, 60, 200)))]
        for _ in range(r.choice((2, 5, 40))):
            texts[len(texts)] = " ".join(words)
            words = list(words)
            for k in r.sample(range(len(words)), r.choice((1, 1, 2, 3))):
                words[k] = f"x{r.randrange(10**6)}"
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], SCHEMA)
    assert {x["doc_id"] for x in corpus_pipeline.near_duplicates(spark, df, data).collect()} == _kept(texts)


def test_odd_rows(spark):
    text = "one two three four five six seven eight nine ten"
    rows = [(7, text), (3, text.upper()), (None, text), (5, None), (4, " \n"), (None, "no id here"), (3, text.upper()), (9, "one"), (8, "ONE")]
    out = similar.keep_one(spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], SCHEMA))
    assert sorted((r["doc_id"] or 0, r["text"]) for r in out.collect()) == [(0, "no id here"), (3, text.upper()), (4, " \n"), (8, "ONE")]


def test_fingerprints_alone_find_near_copies(spark, monkeypatch):
    """The stage links by multi-index hashing of fingerprints, also where no two texts share minima."""
    # one number for a text, made of all its hashes
    monkeypatch.setattr(similar, "segments", lambda hashes: hashes.view("int64").sum(keepdims=True))
    r = random.Random(3)
    texts = {}
    for group in range(20):
        words = [f"w{r.randrange(10**6)}" for _ in range(400)]
        texts[2 * group] = " ".join(["first", *words])
        texts[2 * group + 1] = " ".join(["other", *words])
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], SCHEMA)
    assert {x["doc_id"] for x in similar.keep_one(df).collect()} == _kept(texts)


@pytest.mark.parametrize("dense", [1, 3, 32])
def test_candidates_by_brute_force(spark, dense):
    r = random.Random(4)
    prints = []
    for _ in range(25):
        base, size = r.getrandbits(64), r.randrange(50, 60)
        for _ in range(6):
            prints.append((base ^ sum(1 << b for b in r.sample(range(64), r.randrange(9))), size + r.randrange(20)))
    signed = [(i, f - (1 << 64) if f >> 63 else f, n) for i, (f, n) in enumerate(prints)]
    got = [(x["a"], x["b"]) for x in simhash.candidates(spark.createDataFrame(signed, "node bigint, fp bigint, n int"), 16, (4, 5), dense).collect()]
    segment = [sum(s) for s in simhash.WIDE]
    near, five = set(), set()
    for b, (y, m) in enumerate(prints):
        for a, (x, n) in enumerate(prints[:b]):
            if 5 * min(n, m) >= 4 * max(n, m) and (x ^ y).bit_count() <= 16 and any(((x ^ y) & s).bit_count() <= 1 for s in segment):
                near.add((a, b))
                five |= {(a, b)} if (x ^ y).bit_count() <= 5 else set()
    assert len(got) == len(set(got)) and len(five) > 50
    if dense == 32:
        assert set(got) == near and five <= near
    else:  # members of full buckets are paired with one of them
        assert set(got) and all(any((prints[a][0] ^ prints[b][0]) & s == 0 for s in segment) for a, b in set(got) - near)


def test_links_of_a_group_grow_with_its_members(spark, monkeypatch):
    """A large group of near copies gives few links a text, not all of its pairs, and is one group."""
    r = random.Random(5)
    base = [f"w{r.randrange(10**6)}" for _ in range(300)]
    texts = {}
    for i in range(300):
        words = list(base)
        for k in r.sample(range(300), 2):
            words[k] = f"x{r.randrange(10**6)}"
        texts[i] = " ".join(words)
    given, found = [], similar.components

    def counted(edges):
        given.append(edges.where("a != b").distinct().count())
        return found(edges)

    monkeypatch.setattr(similar, "components", counted)
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], SCHEMA)
    assert {x["doc_id"] for x in similar.keep_one(df).collect()} == _kept(texts) == {0}
    assert sum(given) <= 7 * len(texts)


@pytest.mark.parametrize("dense", [1, 3, 32])
def test_stars_and_the_pairs_apart_connect_what_candidates_connect(spark, dense):
    r = random.Random(6)
    prints = []
    for _ in range(20):
        base, size = r.getrandbits(64), r.randrange(50, 60)
        for _ in range(8):
            prints.append((base ^ sum(1 << b for b in r.sample(range(64), r.randrange(9))), size + r.randrange(20)))
    signed = [(i, f - (1 << 64) if f >> 63 else f, n) for i, (f, n) in enumerate(prints)]
    df = spark.createDataFrame(signed, "node bigint, fp bigint, n int")
    stars = simhash.stars(df, 16, (4, 5), dense)
    first = {x["node"]: x["root"] for x in simhash.components(stars).collect()}
    grouped = spark.createDataFrame([(*row, first.get(row[0], row[0])) for row in signed], "node bigint, fp bigint, n int, root bigint")
    rest = [(x["a"], x["b"]) for x in simhash.candidates(grouped, 16, (4, 5), dense, "root").collect()]
    # not by size, as full buckets are paired without it where nothing else is asked
    whole = [(x["a"], x["b"]) for x in simhash.candidates(df, 16, (4, 5), dense).collect() if 5 * min(prints[x["a"]][1], prints[x["b"]][1]) >= 4 * max(prints[x["a"]][1], prints[x["b"]][1])]
    assert rest and all(first.get(a, a) != first.get(b, b) for a, b in rest)

    def joined(pairs):
        root = {i: i for i in range(len(prints))}
        for a, b in pairs:
            x, y = root[a], root[b]
            root = {k: min(x, y) if v in (x, y) else v for k, v in root.items()}
        return root

    assert joined([(x["a"], x["b"]) for x in stars.collect()] + rest) == joined(whole)


def _shuffle_files(spark):
    """How many files of shuffles this session has on its disk."""
    files = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return files.mkString("\n").count("/shuffle_")


def test_shuffles_leave_no_files(spark):
    """What the rounds of the stage have shuffled goes as they end, not when the driver happens to collect its garbage."""
    r = random.Random(7)
    texts = {}
    for _ in range(20):
        words = [f"w{r.randrange(10**6)}" for _ in range(60)]
        for _ in range(6):
            texts[len(texts)] = " ".join(words)
            words[r.randrange(60)] = f"x{r.randrange(10**6)}"
    df = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in texts.items()], SCHEMA)
    # files of earlier tests may go meanwhile, so only those that are new count
    before = _shuffle_files(spark)
    kept = similar.keep_one(df)
    until = time.time() + 20
    while (left := _shuffle_files(spark) - before) > 0 and time.time() < until:
        time.sleep(0.5)
    assert left <= 0 and {x["doc_id"] for x in kept.collect()} == _kept(texts)


def test_the_setting_is_taken_back(spark):
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    spark.conf.set(name, "false")
    numbers = spark.range(100).groupBy("id").count()
    assert common.cut(numbers).count() == 100 and common.has_rows(numbers) and not common.has_rows(numbers.where("id < 0"))
    assert spark.conf.get(name) == "false"


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_components_of_chains_and_stars(spark, seed):
    r = random.Random(seed)
    numbers = r.sample(range(10**6), 80)
    edges = [(numbers[k], numbers[k + 1]) for k in range(30)]
    edges += [(numbers[40], x) for x in numbers[41:60]] + [(r.choice(numbers[60:]), r.choice(numbers[60:])) for _ in range(15)]
    root = {x: x for e in edges for x in e if e[0] != e[1]}
    for a, b in (e for e in edges if e[0] != e[1]):
        x, y = root[a], root[b]
        root = {k: min(x, y) if v in (x, y) else v for k, v in root.items()}
    df = spark.createDataFrame(edges, "a bigint, b bigint")
    got = [(x["node"], x["root"]) for x in simhash.components(df).collect()]
    assert len(got) == len(root) and dict(got) == root
    assert simhash.components(df.where("a < 0")).count() == 0
