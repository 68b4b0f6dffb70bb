"""Copies by contiguous edits, groups of copies and the shingles' order, against exact comparison of all pairs."""

import random

import numpy as np

from quorumgrad.llm import simhash

from .test_brute_force import shingles


def words(pick, n):
    return [f"w{pick.randrange(3000)}" for _ in range(n)]


def similarity(a, b):
    return len(shingles(a) & shingles(b)) / len(shingles(a) | shingles(b))


def kept_by_all_pairs(texts):
    root = list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for b in range(len(texts)):
        for a in range(b):
            if 5 * len(shingles(texts[a]) & shingles(texts[b])) >= 4 * len(shingles(texts[a]) | shingles(texts[b])):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i for i in range(len(texts)) if find(i) == i}


def kept(spark, texts):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    return {r.doc_id for r in simhash.deduplicated_similar(spark, df).collect()}


def test_cut_appended_and_replaced_blocks(spark):
    pick = random.Random(7)
    texts, near = [], 0
    for i in range(60):
        base = words(pick, pick.randrange(150, 900))
        n = len(base)
        if i % 3 == 0:
            copy = base[: n - int(n * (0.12 + 0.004 * (i % 30)))]
        elif i % 3 == 1:
            copy = base + words(pick, int(n * (0.12 + 0.006 * (i % 30))))
        else:
            at, m = pick.randrange(n // 2), int(n * (0.06 + 0.002 * (i % 30)))
            copy = base[:at] + words(pick, m) + base[at + m :]
        texts += [" ".join(base), " ".join(copy)]
        near += 0.8 <= similarity(*texts[-2:]) < 0.88
    assert near >= 30
    assert kept(spark, texts) == kept_by_all_pairs(texts)


def test_groups_of_versions_and_long_lists(spark, monkeypatch):
    """Two chains of versions in one list and texts that share a block: every pair of a list is tried, in parts too."""
    pick = random.Random(11)
    texts = []
    for _ in range(2):
        base = words(pick, 200)
        for _ in range(40):
            at = pick.randrange(180)
            texts.append(" ".join([*base[:at], *words(pick, pick.randrange(1, 19)), *base[at + pick.randrange(19) :]]))
    block = words(pick, 60)
    texts += [" ".join([*block, *words(pick, pick.randrange(5, 40))]) for _ in range(40)]
    want = kept_by_all_pairs(texts)
    assert 3 < len(want) < 60
    assert kept(spark, texts) == want
    monkeypatch.setattr(simhash, "LONG", 4)
    monkeypatch.setattr(simhash, "BLOCK", 8)
    assert kept(spark, texts) == want


def test_order_and_size_change_no_pair(spark, monkeypatch):
    """The same copies are found with any shingles called common, and boilerplate makes no list."""
    pick = random.Random(13)
    notice = words(pick, 25)
    texts = []
    for _ in range(60):
        base = words(pick, pick.randrange(100, 300))
        texts += [" ".join([*base, *notice]), " ".join([*base[: int(len(base) * pick.uniform(0.75, 1))], *notice])]
    want = kept_by_all_pairs(texts)
    assert 60 < len(want) < 110
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    found = simhash.common_shingles(df)
    last = {int(h) for h in simhash.shingle_set(" ".join(notice).encode())}
    assert last <= set(found[-len(last):].tolist())
    heads = [h for r in simhash.with_heads(df, found).collect() for h in r.head]
    assert not {(1 << 62) + len(found) - 1 - i for i in range(len(last))} & set(heads)
    assert kept(spark, texts) == want
    some = np.unique(np.concatenate([simhash.shingle_set(t.encode())[::3] for t in texts]))
    monkeypatch.setattr(simhash, "common_shingles", lambda docs: np.random.default_rng(1).permutation(some))
    assert kept(spark, texts) == want


def test_sketches_never_part_copies(spark):
    """The bits in which two parity sketches differ are no more than the shingles that only one text has, of any sizes."""
    from pyspark.sql import functions as F

    pick = random.Random(17)
    rows, apart = [], []
    for i in range(60):
        n = pick.choice([1, 5, 200, 900, 1000, 1023, 1024, 1025, 1100, 2000, 2047, 2048, 2049, 2300, 5000])
        a = np.unique(np.array([pick.getrandbits(62) for _ in range(n)], np.int64))
        b = np.unique(np.concatenate([a[: max(1, int(len(a) * pick.uniform(0.8, 1)))], np.array([pick.getrandbits(62) for _ in range(int(n * pick.uniform(0, 0.15)))], np.int64)]))
        rows.append((i, simhash.parity(a).tolist(), simhash.parity(b).tolist(), len(a), len(b)))
        apart.append(len(np.setxor1d(a, b)))
    df = spark.createDataFrame(rows, "i int, x array<long>, y array<long>, nx int, ny int")
    got = [r.d for r in df.withColumn("d", simhash._apart(F.col("x"), F.col("y"))).orderBy("i").collect()]
    assert all(0 <= d <= most for d, most in zip(got, apart, strict=True))
    assert len({len(r[1]) for r in rows}) == 3 and any(len(r[1]) != len(r[2]) for r in rows)
    small = [(d, most) for d, most, r in zip(got, apart, rows) if r[3] < 2049 and most > 20]
    assert all(d > 0.6 * most for d, most in small)


def test_a_large_group_of_versions_makes_few_pairs(spark, monkeypatch):
    """Versions half of whose pairs are below the threshold: found whole, with far fewer rows than pairs."""
    pick = random.Random(19)
    base = words(pick, 150)
    texts = []
    for _ in range(400):
        own = list(base)
        for at in pick.sample(range(150), pick.choice([2, 3, 4, 5, 9])):
            own[at] = f"v{pick.randrange(10**6)}"
        texts.append(" ".join(own))
    made = []
    real = simhash.long_pairs
    monkeypatch.setattr(simhash, "long_pairs", lambda long: made.append(real(long)) or made[-1])
    assert kept(spark, texts) == kept_by_all_pairs(texts)
    lists = simhash.LONG
    assert made and made[0].count() < 400 * lists


def test_fingerprints_and_their_lists_go_first(spark, monkeypatch):
    """Copies whose fingerprints link are found by those and left out of what follows; others are found after them."""
    pick = random.Random(23)
    texts = []
    for i in range(40):
        base = words(pick, 400)
        copy = [*base[:200], f"v{i}", *base[201:]] if i % 2 else base[: pick.randrange(330, 390)]
        texts += [" ".join(base), " ".join(copy)]
    prints = [simhash.fingerprint(t.encode()) for t in texts]
    near = {i for i in range(0, 80, 2) if (prints[i] ^ prints[i + 1]).bit_count() <= 3 and similarity(texts[i], texts[i + 1]) >= 0.8}
    assert 10 < len(near) < 30
    made, linked = [], []
    pairs, links = simhash.short_pairs, simhash.links
    monkeypatch.setattr(simhash, "short_pairs", lambda short: made.append(pairs(short)) or made[-1])
    monkeypatch.setattr(simhash, "links", lambda rows, bits: linked.append(links(rows, bits)) or linked[-1])
    assert kept(spark, texts) == kept_by_all_pairs(texts)
    name = {simhash.node_of(simhash.shingle_set(t.encode())): i for i, t in enumerate(texts)}
    of = {p - (p >> 63 << 64): i for i, p in enumerate(prints)}
    by_lists = {min(of[r.a], of[r.b]) for r in linked[0].collect()} | {i for i in near if prints[i] == prints[i + 1]}
    assert near <= by_lists
    after = {min(name[r.a], name[r.b]) for r in made[0].select("a", "b").distinct().collect()}
    assert not near & after and after & (set(range(0, 80, 2)) - near)
