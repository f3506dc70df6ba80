import hashlib
import random
from collections import defaultdict

import numpy as np
from cases import awkward, empty, texts
from pyspark.sql import functions as F

from pairbundle.llm import exact_dedup, simhash


def by_text(rows):
    groups = defaultdict(list)
    for k, t in rows:
        groups[t].append(k)
    return groups


def test_exact_awkward(spark):
    got = exact_dedup.exact_groups(awkward(spark), block_bytes=64).drop("text_key").collect()
    groups = by_text(texts())
    largest = {t: max((k for k in ks if k is not None), default=None) for t, ks in groups.items()}
    want = sorted(repr((k, largest[t], len(groups[t]), k == largest[t], hashlib.sha256(t.encode()).hexdigest())) for k, t in texts())
    assert sorted(repr(tuple(r)) for r in got) == want
    assert exact_dedup.exact_groups(empty(spark)).count() == 0


def test_exact_without_trust_in_hashes(spark):
    """All blocks share their hashes: names come from the contents."""
    rng = random.Random(1)
    rows = [(k, "".join(rng.choice("ab") for _ in range(rng.choice([3, 4, 8, 9, 16])))) for k in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.keep_id for r in exact_dedup.exact_groups(df, block_bytes=4, hashes=lambda b: (F.length(b) * 0, F.length(b) * 0)).collect()}
    groups = by_text(rows)
    assert got == {k: max(groups[t]) for k, t in rows}


def brute(marks, radius=4):
    fp = np.array(marks, np.uint64)
    parent = list(range(len(fp)))

    def root(k):
        while parent[k] != k:
            k = parent[k]
        return k

    for a, b in zip(*np.nonzero(np.bitwise_count(fp[:, None] ^ fp[None, :]) <= radius)):
        parent[root(a)] = root(b)
    return [root(k) for k in range(len(fp))]


def by_definition(text):
    import xxhash

    words = text.encode().translate(bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")).split()
    shingles = [b" ".join(words[k : k + 4]) for k in range(max(1, len(words) - 3))] if words else []
    hashes = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash_awkward(spark):
    got = simhash.near_duplicates(awkward(spark)).drop("text_key").collect()
    rows = texts()
    marks = [by_definition(t) for _, t in rows]
    roots = brute(marks)
    least = {r: min((rows[k][0] for k in range(len(rows)) if roots[k] == r and rows[k][0] is not None), default=None) for r in set(roots)}
    want = sorted(repr((rows[k][0], f"{marks[k]:016x}", least[roots[k]])) for k in range(len(rows)))
    assert sorted(repr(tuple(r)) for r in got) == want
    assert simhash.near_duplicates(empty(spark)).count() == 0


def test_links_against_brute_force(spark):
    """Random marks, a chain of near ones and a dense ball; small tiles make groups that are dealt as tile pairs."""
    rng = random.Random(3)
    marks = [rng.getrandbits(64) for _ in range(300)]
    x = marks[0]
    for _ in range(40):
        x ^= (1 << rng.randrange(64)) | (1 << rng.randrange(64)) | (1 << rng.randrange(64))
        marks.append(x)
    marks += [marks[1] ^ (1 << a) ^ (1 << b) for a in range(0, 30) for b in range(30, 44)]
    marks = sorted(set(marks))
    signed = [m - (1 << 64) if m >> 63 else m for m in marks]
    df = spark.createDataFrame([(m,) for m in signed], "fp long")
    roots = brute(marks)
    for options in ({}, {"tile": 16}, {"blocks": 6}, {"blocks": 7, "tile": 50}):
        labels = {r.node: r.label for r in simhash.components(simhash.tile_links(df, **options)).collect()}
        got = [labels.get(s, s) for s in signed]
        assert len(set(got)) == len(set(roots)) and all((got[a] == got[a + 1]) == (roots[a] == roots[a + 1]) for a in range(len(marks) - 1))
        assert len(set(zip(got, roots))) == len(set(roots))


def test_forest_is_small():
    rng = np.random.default_rng(0)
    base = np.uint64(rng.integers(0, 2**63))
    ball = np.unique(np.array([base ^ np.uint64(1 << int(a)) ^ np.uint64(1 << int(b)) for a, b in rng.integers(0, 60, (3000, 2))], np.uint64))
    u, v = simhash.forest(ball, None, 4)
    assert len(u) < 20 * len(ball)
