import hashlib
import random

import numpy as np

from lwgraph.llm import suffix_dedup as sd


def brute(rows, length):
    first = {}
    for i, t in rows:
        b = (t or "").encode()
        if i is not None:
            for p in range(len(b) - length + 1):
                w = b[p : p + length]
                first[w] = min(first.get(w, i), i)
    out = []
    for i, t in rows:
        b = (t or "").encode()
        gone = [False] * len(b)
        if i is not None:
            for p in range(len(b) - length + 1):
                if first[b[p : p + length]] < i:
                    gone[p : p + length] = [True] * length
        spans = sum(g and not (k and gone[k - 1]) for k, g in enumerate(gone))
        out.append((i, len(b), sum(gone), spans, hashlib.sha256(bytes(c for c, g in zip(b, gone) if not g)).hexdigest()))
    return out


def planted(seed=3):
    rnd = random.Random(seed)
    alphabet = ["ab", "cde", "f ", "gh", "é", "x\n", "\x00"]
    word = lambda n: "".join(rnd.choice(alphabet) for _ in range(n))
    passages = [word(40) for _ in range(6)]
    rows = []
    for i in range(120):
        t = word(rnd.randint(0, 60))
        for _ in range(rnd.randint(0, 3)):
            q = rnd.choice(passages)
            a = rnd.randint(0, 8)
            t += q[a : len(q) - rnd.randint(0, 8)] + word(rnd.randint(0, 12))
        rows.append((i * 3, t))
    rows += [(500, rows[5][1]), (501, rows[5][1]), (501, rows[5][1]), (502, None), (503, ""), (None, rows[5][1]), (504, "a" * 49), (505, "a" * 300), (506, "a" * 50), (504, "z" * 60 + "a" * 49)]
    return rows


def test_against_brute_force(spark):
    rows = planted()
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, n_bytes int").repartition(3)
    key = lambda r: tuple(str(x) for x in r)
    got = sorted((tuple(r) for r in sd.remove_repeats(docs).collect()), key=key)
    assert got == sorted(brute(rows, 50), key=key)


def test_empty_table(spark):
    assert sd.remove_repeats(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def maximal_repeats(texts, length):
    """Plain enhanced suffix array over all texts: (string, [(text, start)]) of every maximal repeat."""
    every = sorted(((t[i:], n, i) for n, t in enumerate(texts) for i in range(len(t))), key=lambda x: (x[0], x[1], x[2]))
    lcp = [0]
    for (x, *_), (y, *_) in zip(every, every[1:]):
        k = 0
        while k < min(len(x), len(y)) and x[k] == y[k]:
            k += 1
        lcp.append(k)
    found = []
    for depth, a, z in sd.interval_tree(lcp):
        if depth >= length:
            at = [(n, i) for _, n, i in every[a : z + 1]]
            if len({texts[n][i - 1 : i] if i else (n,) for n, i in at}) > 1:
                found.append((every[a][0][:depth], sorted(at)))
    return found


def test_interval_tree():
    assert sd.interval_tree([0, 1, 3, 0, 0, 2]) == [(3, 1, 2), (1, 0, 2), (2, 4, 5)]
    groups = dict(maximal_repeats([b"xxabcdefyy", b"zzabcdefww", b"qabcdeq", b"abcabcabc"], 3))
    assert groups[b"abcdef"] == [(0, 2), (1, 2)] and groups[b"abcde"] == [(0, 2), (1, 2), (2, 1)]
    assert groups[b"abc"] == [(0, 2), (1, 2), (2, 1), (3, 0), (3, 3), (3, 6)] and groups[b"abcabc"] == [(3, 0), (3, 3)]
    assert b"bcdef" not in groups


def test_suffix_groups_equal_a_plain_suffix_array():
    """Groups of one block of stretches are its maximal repeats, where a stretch's start counts as a byte of its own."""
    rnd = random.Random(8)
    for case in range(30):
        base = bytes(rnd.choice(b"ab") for _ in range(90))
        cuts = sorted({base[a : a + rnd.randint(50, 80)] for a in (rnd.randint(0, 10) for _ in range(8))} | {bytes(rnd.choice(b"ab\x00") for _ in range(60)), b"a" * 70, b"\x00" * 64})
        stretches = [c for c in cuts if len(c) >= 50]
        size = np.array([len(c) for c in stretches])
        text = np.frombuffer(b"".join(stretches), np.uint8)
        got = []
        for depth, n, stretch, place in sd.suffix_groups(text, np.cumsum(size) - size, size, np.zeros(len(size), np.uint64), 50, windows=rnd.choice([1, 20, 10_000])):
            for d, members in zip(depth, np.split(np.stack([stretch, place], 1), np.cumsum(n)[:-1]), strict=True):
                g, p = members[0]
                got.append((stretches[g][p : p + d], sorted(map(tuple, members.tolist()))))
        assert sorted(got) == sorted(maximal_repeats(stretches, 50)), case


def test_equal_hashes_of_unequal_strings_change_nothing(monkeypatch):
    """With a hash that has two values, every answer still follows the bytes."""
    rnd = random.Random(9)
    words = [bytes(rnd.choice(b"ab") for _ in range(56)) for _ in range(6)]
    stretches = [w[a : a + 52] for w in words for a in (0, 2)] + words
    size = np.array([len(c) for c in stretches])
    text, begin = np.frombuffer(b"".join(stretches), np.uint8), np.cumsum(size) - size
    keys = np.zeros(len(size), np.uint64)

    def collected():
        out = [(d.tolist(), n.tolist(), g.tolist(), p.tolist()) for d, n, g, p in sd.suffix_groups(text, begin, size, keys, 50)]
        members = [sorted(zip(g[a : a + k], p[a : a + k])) + [d] for ds, ns, g, p in out for d, k, a in zip(ds, ns, np.cumsum(ns) - ns)]
        return sorted(members, key=str), sd._distinct(text, begin, size, keys)[0]

    want, same = collected()
    monkeypatch.setattr(sd, "mix64", lambda x: x & np.uint64(1))
    got, other = collected()
    assert got == want and len(set(zip(same, other))) == len(set(same)) == len(set(other))


def test_repeat_groups_of_a_table(spark):
    rows = [(i, t) for i, t in planted(5)[:70]] + [(900, "q" * 200), (901, None), (None, "q" * 90), (902, "q" * 70)]
    texts = {i: (t or "").encode() for i, t in rows if i is not None}
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, depth int").repartition(3)
    groups = {}
    for r in sd.repeat_groups(docs, part_bytes=20_000).collect():
        groups.setdefault((r.group_id, r.depth), []).append((r.doc_id, r.start))
    names, held = list(texts), {}
    for (_, depth), at in groups.items():
        strings = {texts[d][p : p + depth] for d, p in at}
        assert len(strings) == 1 and len(at) > 1 and len(set(at)) == len(at) and depth >= 50
        held.setdefault(strings.pop(), set()).update(at)
    for s, at in held.items():  # all occurrences of the string are listed somewhere with it or a longer one
        assert at <= {(d, p) for d, t in texts.items() for p in range(len(t)) if t.startswith(s, p)}
    # every repeat of the plain suffix array is covered by groups, and they alone give the removed bytes
    covered = {(d, p + k) for (_, depth), at in groups.items() for d, p in at for k in range(depth)}
    for s, at in maximal_repeats(list(texts.values()), 50):
        if len({n for n, _ in at}) > 1:
            assert all((names[n], p + k) in covered for n, p in at for k in range(len(s)))
    gone = set()
    for (_, depth), at in groups.items():
        least = min(d for d, _ in at)
        gone |= {(d, p + k) for d, p in at if d > least for k in range(depth)}
    want = {r[0]: r[2] for r in brute([r for r in rows if r[0] is not None], 50)}
    assert {i: sum(d == i for d, _ in gone) for i in want} == want


def test_one_hot_passage(spark):
    """A passage that all documents share, in many surroundings, and very long texts."""
    rnd = random.Random(3)
    passage = "".join(rnd.choice("abcdefgh ") for _ in range(120))
    rows = [(i, "".join(rnd.choice("xyz") for _ in range(rnd.randint(0, 30))) + passage[: rnd.randint(60, 120)] + str(i) * 9) for i in range(300)]
    rows += [(1000, "long " * 20000), (1001, passage * 50), (1002, "long " * 300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    key = lambda r: tuple(str(x) for x in r)
    assert sorted((tuple(r) for r in sd.remove_repeats(docs, part_bytes=30_000).collect()), key=key) == sorted(brute(rows, 50), key=key)
