import random
import zlib
from collections import Counter

import numpy as np
import pytest
from cases import awkward, empty, texts

from pairbundle.llm import grammar, packing
from pairbundle.llm.tokens import PieceEncoder, tokenizer_path


def fresh(name, special_strings=False):
    """The library's own tokenizer, set up as the vocabularies' description says, or left as it loads."""
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizer_path(name))
    if not special_strings:
        t.encode_special_tokens = True
    return t


SPECIAL = ["<|endoftext|> don't  stop", "a<|endoftext|>", "<|startoftext|>x <|endoftext|> é", "<|ENDOFTEXT|>", "< |endoftext|>", "<|endoftext|", "e\u0301<|endoftext|>漢"]


@pytest.mark.parametrize("special_strings", [False, True])
@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_pieces_equal_whole_texts(name, special_strings):
    rng = random.Random(2)
    rows = [t for _, t in texts() if len(t) < 9000] + [*SPECIAL, "\x1c a\x85b", "İ ΑΣ Σ", "e\u0301 x", "'s 't", "a\r\n\r\nb", "   ", "１２"]
    rows += ["".join(rng.choice(" \n\ta bc'1.,;éÀ-%sStTlLrRe\u0301") for _ in range(rng.randint(0, 40))) for _ in range(2000)]
    e, t = PieceEncoder(tokenizer_path(name), limit=50, special_strings=special_strings), fresh(name, special_strings)
    for _ in range(2):
        ids, n = e.encode(rows)
        ends = np.cumsum(n)
        want = t.encode_batch(rows, add_special_tokens=False)
        assert all(ids[b - k : b].tolist() == w.ids for b, k, w in zip(ends, n, want))
    assert e.encode([])[0].size == 0


def coded(name, end):
    t = fresh(name)
    return [(k, np.array([*t.encode(x, add_special_tokens=False).ids, end], "<u4")) for k, x in texts()]


def test_grammar_output(spark, tmp_path):
    path = f"file://{tmp_path}/shards"
    grammar.write_shards(awkward(spark).selectExpr("doc_id", "coalesce(text, '') AS text"), path, shard_tokens=500)
    got = sorted(((r.doc_id if r.doc_id is not None else -1, r.n_tokens, r.ids_crc32) for r in grammar.read_shards(spark, path).collect()))
    assert got == sorted((k if k is not None else -1, len(a), zlib.crc32(a.tobytes())) for k, a in coded("byte_bpe_50k.json", 0))
    rows = sorted(grammar.read_shards(spark, path).collect(), key=lambda r: r.start)
    assert [r.start for r in rows] == np.cumsum([0, *(r.n_tokens for r in rows)])[:-1].tolist()
    assert [r.doc_id or 0 for r in rows] == sorted(r.doc_id or 0 for r in rows)
    nothing = f"file://{tmp_path}/none"
    grammar.write_shards(empty(spark).select("doc_id", "text"), nothing)
    assert grammar.read_shards(spark, nothing).count() == 0


@pytest.mark.parametrize("seed", range(6))
def test_grammar_random_access(seed):
    rng = np.random.default_rng(seed)
    n = rng.integers(1, 60, 80)
    ids = rng.integers(0, [1, 2, 4, 40, 400, 50000][seed], n.sum()).astype(np.uint32)
    shard = grammar.Shard(grammar.encode_shard(np.arange(80), ids, n, 1 << 16, rounds=8, per_round=16, min_count=2))
    assert (shard.all_ids() == ids).all()
    ends = np.cumsum(n)
    for k in (0, 11, 79):
        own = ids[ends[k] - n[k] : ends[k]]
        assert (shard.document(k) == own).all()
        assert [shard.token(k, j) for j in range(len(own))] == own.tolist()
    assert (shard.sizes >= 2).all()


def frequent_pairs(seq, last, least):
    pairs = Counter((a, b) for a, b, end in zip(seq[:-1].tolist(), seq[1:].tolist(), last[:-1].tolist()) if not end)
    return [p for p, n in pairs.items() if n >= least]


@pytest.mark.parametrize("seed", range(4))
def test_repair_leaves_no_frequent_pair(seed):
    """More distinct pairs than hash slots, pairs that nest deeper than a few rounds reach, runs of one id, and few rules a round."""
    rng = np.random.default_rng(seed)
    phrases = [rng.integers(0, 50000, 200) for _ in range(40)]
    parts = [rng.integers(0, 50000, 200_000), *(phrases[k] for k in rng.integers(0, 40, 400)), np.zeros(500, int)]
    ids = np.concatenate(parts).astype(np.uint32)
    last = rng.random(len(ids)) < 0.01
    last[-1] = True
    for least, options in ((6, {}), (3, {"min_count": 3, "per_round": 50})):
        seq, ends, rules = grammar.repair(ids, last.copy(), 1 << 16, **options)
        assert not frequent_pairs(seq, ends, least)
        assert int(ends.sum()) == int(last.sum())
        assert len({tuple(r) for r in rules.tolist()}) == len(rules)


def test_pairs_are_counted_exactly():
    """Against a counter, with more pairs than slots: a frequent pair counts in full whatever shares its slot."""
    rng = np.random.default_rng(5)
    ids = np.concatenate([rng.integers(0, 30, 300_000), rng.integers(0, 60000, 3_000_000)]).astype(np.uint32)
    some, group, n, pairs = grammar.count_pairs(ids[:-1], ids[1:], 5)
    got = {(int(pairs[g]) >> 32, int(pairs[g]) & 0xFFFFFFFF): int(n[g]) for g in np.flatnonzero(n >= 5)}
    want = Counter(zip(ids[:-1].tolist(), ids[1:].tolist()))
    assert got == {p: k for p, k in want.items() if k >= 5}
    assert (pairs[group] == (ids[:-1][some].astype(np.uint64) << np.uint64(32) | ids[1:][some])).all()


def test_packing(spark):
    got = packing.packed_documents(awkward(spark), capacity=64).collect()
    want = []
    for k, a in coded("word_bpe_49k.json", 1):
        want += [(k if k is not None else -1, j, s, len(a[s : s + 64]), zlib.crc32(a[s : s + 64].tobytes())) for j, s in enumerate(range(0, len(a), 64))]
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.piece, r.start, r.length, r.ids_crc32) for r in got) == sorted(want)
    check_bins(got, 64)
    assert packing.packed_documents(empty(spark)).count() == 0


def check_bins(rows, capacity):
    bins: dict = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in bins.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= capacity
    return len(bins)


@pytest.mark.parametrize("seed", range(4))
def test_plan_holds_every_piece(seed):
    rng = np.random.default_rng(seed)
    lengths = rng.integers(1, [20, 100, 60, 101][seed], 3000) + [0, 0, 41, 0][seed]
    lengths = np.minimum(lengths, 100)
    found = packing.plan(dict(Counter(lengths.tolist())), 100)
    held = Counter()
    for pattern, times in found.patterns:
        assert sum(pattern) <= 100 and times > 0
        for length in pattern:
            held[length] += times
    assert held == Counter(lengths.tolist())
    bins, bound = sum(found.bins()), -(-int(lengths.sum()) // 100)
    order = np.sort(lengths)[::-1]
    room: list = []
    for x in order.tolist():  # first fit decreasing, by hand
        k = next((j for j, r in enumerate(room) if r >= x), None)
        if k is None:
            room.append(100 - x)
        else:
            room[k] -= x
    assert bound <= bins <= 1.02 * len(room) + 1
    assert found.bound <= bins + 1e-6


@pytest.mark.parametrize("seed", range(3))
def test_program_reaches_its_gap_and_makes_the_plan(seed):
    """The value is a feasible cover of every length, the bound holds for the best whole plan, and most bins are the program's."""
    rng = np.random.default_rng(seed)
    lengths = np.clip(rng.lognormal([2.5, 3.0, 3.5][seed], 0.8, 20_000).astype(int), 1, 255)
    demand = np.bincount(lengths, minlength=257).astype(np.int64)
    cover = packing.fractional(demand, 256)
    assert cover.bound <= cover.value <= 1.03 * cover.bound + 1e-9
    assert sum(cover.use.values()) == pytest.approx(cover.value)
    got = np.zeros(257)
    for pattern, x in cover.use.items():
        assert sum(pattern) <= 256
        np.add.at(got, list(pattern), x)
    assert (got[demand > 0] >= demand[demand > 0] * (1 - 1e-9)).all()
    found = packing.plan({k: int(n) for k, n in enumerate(demand) if n}, 256)
    ours, rest = found.bins()
    assert ours > 2 * rest and -(-int(lengths.sum()) // 256) <= ours + rest <= 1.002 * lengths.sum() / 256 + 1


def test_program_with_scarce_and_plentiful_lengths():
    found = packing.plan({3000: 10**9, 1096: 5 * 10**8, 7: 3})
    assert found.value <= 1.0 * 1.03 * 10**9 and sum(found.bins()) == 10**9
    assert packing.plan({}).patterns == [] and sum(packing.plan({1: 1}).bins()) == 1 and sum(packing.plan({4096: 5}).bins()) == 5


def test_knapsack_against_all_patterns():
    rng = np.random.default_rng(4)
    price = np.zeros(25)
    price[rng.choice(np.arange(1, 25), 9, replace=False)] = rng.random(9)
    best = packing.knapsack(price, 24)

    def most(c):
        return max([0.0, *(price[k] + most(c - k) for k in range(1, c + 1) if price[k])])

    assert [round(float(b), 9) for b in best] == [round(float(most(c)), 9) for c in range(25)]
    price[price == 0] = -np.inf
    assert sum(price[k] for k in packing.pattern_for(price, best, 24)) == pytest.approx(best[24])


def test_fill_uses_many_copies():
    spare = np.zeros(101, np.int64)
    spare[3], spare[50] = 40, 1
    assert sum(packing._fill(spare, 100)) == 99 and sum(packing._fill(spare, 98)) == 98
    assert packing._fill(np.zeros(11, np.int64), 10) == []
