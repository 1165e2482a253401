import random
import re

import numpy as np

from lwgraph.llm import near_dedup as nd


def lower(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def brute(rows, k, percent):
    sets = []
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(t))
        sets.append({tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    root = {i: i for i, _ in rows if i is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for x in range(len(rows)):
        for y in range(x):
            a, b = sets[x], sets[y]
            if a and b and rows[x][0] is not None and rows[y][0] is not None and 100 * len(a & b) >= percent * len(a | b):
                p, q = sorted((find(rows[x][0]), find(rows[y][0])))
                root[q] = p
    return sorted(((i, len(s), find(i) if i is not None else None) for (i, _), s in zip(rows, sets, strict=True)), key=str)


def planted(seed, copies=40):
    rnd = random.Random(seed)
    vocab = ["w%d" % i for i in range(400)] + ["é", "naïve", " x"]
    sent = lambda n: [rnd.choice(vocab) for _ in range(n)]
    rows, i = [], 0
    passage = sent(60)

    def add(words):
        nonlocal i
        rows.append((i * 2 + 1, rnd.choice([" ", "\n", "\t "]).join(words)))
        i += 1

    for _ in range(30):
        add(sent(rnd.randint(0, 120)))
    for _ in range(40):  # a passage that many share
        add(sent(40) + passage + sent(40))
    for _ in range(3):  # groups of near copies around the threshold
        base = sent(130)
        for _ in range(copies):
            w = list(base)
            for _ in range(rnd.randint(0, 4)):
                w[rnd.randrange(len(w))] = rnd.choice(vocab).upper()
            add(w)
    base = sent(100)
    for j in range(12):  # a chain
        add(base[j * 2 :] + sent(0) + ["t%d" % x for x in range(j * 2)])
    rows += [(900, None), (901, ""), (902, " \n "), (903, "one two"), (904, "ONE two"), (905, "one"), (None, rows[0][1]), (907, rows[75][1]), (907, rows[75][1])]
    return rows


def check(spark, rows, words, percent, **options):
    docs = spark.createDataFrame([(i, t, 0) for i, t in rows], "doc_id long, text string, n_shingles int").repartition(3)
    got = sorted((tuple(r) for r in nd.components(docs, words=words, percent=percent, **options).collect()), key=str)
    assert got == brute(rows, words, percent)


def test_against_brute_force(spark):
    check(spark, planted(1), 4, 85)


def test_against_brute_force_other_limits(spark):
    check(spark, planted(2, copies=25), 5, 80)


def test_oversized_buckets_give_the_same_answer(spark):
    check(spark, planted(3, copies=30), 4, 85, bucket_tokens=200)


def test_blocks_of_long_postings_on_both_sides(spark, monkeypatch):
    import functools

    monkeypatch.setattr(nd, "across", functools.partial(nd.across, block_rows=7))
    monkeypatch.setattr(nd, "CHUNK", 5)
    check(spark, planted(4, copies=25), 4, 85)


def test_keep_one_tells_texts_of_one_id_apart(spark):
    a, b, c = (" ".join(f"{x}{i}" for i in range(40)) for x in "abc")
    rows = [(1, a, 9), (2, a + " more", 9), (2, b, 9), (None, c, 9), (None, c + " more", 9), (None, "short", 9), (5, None, 9), (6, None, 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, component_id int")
    kept = nd.keep_one(docs)
    assert kept.columns == docs.columns
    got = sorted(((r.doc_id, r.text) for r in kept.collect()), key=str)
    assert (1, a) in got and (2, a + " more") not in got and (2, b) in got and (None, "short") in got and (5, None) in got and (6, None) in got
    assert len([t for _, t in got if t and t.startswith(c)]) == 1 and len(got) == 6


def test_empty_table(spark):
    assert nd.components(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_parity_bound_never_exceeds_the_difference():
    rng = np.random.default_rng(0)
    for _ in range(200):
        a = np.unique(rng.integers(0, 2**64, rng.integers(1, 300), dtype=np.uint64))
        b = np.unique(np.concatenate([a[rng.random(len(a)) < 0.8], rng.integers(0, 2**64, rng.integers(0, 90), dtype=np.uint64)]))
        if len(b):
            assert nd.least_difference(nd.parity_bits(a), nd.parity_bits(b)) <= len(np.setxor1d(a, b))
