import random

import pytest

from repeatfold.kernels import baselines, brute, gated, reach, suffix, tree
from repeatfold.kernels.assemble import MARK, unfold
from repeatfold.kernels.typing import left_greedy, pick, pick_simple
from repeatfold.sources.tables import adversarial_text, adversarial_text2
from repeatfold.workloads.methods import FIXTURES


def units(count, longest=60, seed=42):
    rng = random.Random(seed)
    for _ in range(count):
        sigma = rng.choice([1, 2, 3, 5])
        yield [97 + rng.randrange(sigma) for _ in range(rng.randint(0, longest))]


def engines(c, tie="leftmost"):
    sa, lcp = suffix.order_of(c)
    return [brute.run(c, tie=tie), reach.run(c, sa, lcp, tie=tie), tree.run(c, sa, lcp, tie=tie)]


@pytest.mark.parametrize("name", FIXTURES)
def test_hand_fixtures(name):
    text, residual, factors, kinds = FIXTURES[name]
    for f in engines([ord(x) for x in text]):
        assert "".join("#" if x == MARK else chr(x) for x in f.residual) == residual
        assert ";".join(f"{a},{n}" for a, n in f.factors) == factors
        assert ",".join(map(str, f.kinds)) == kinds


@pytest.mark.parametrize("tie", ["leftmost", "lex"])
def test_engines_agree_and_round_trip(tie):
    for c in units(250):
        outs = [(f.residual, f.factors, f.kinds, [(s.len, s.first, s.picks) for s in f.steps]) for f in engines(c, tie)]
        assert outs[0] == outs[1] == outs[2]
        assert unfold(*outs[0][:3]) == c


def test_order_is_sorted_suffixes():
    for c in units(100):
        sa, lcp = suffix.order_of(c)
        assert sa == sorted(range(len(c)), key=lambda p: c[p:])
        for r in range(1, len(c)):
            a, b = c[sa[r - 1] :], c[sa[r] :]
            assert lcp[r] == next((k for k in range(min(len(a), len(b))) if a[k] != b[k]), min(len(a), len(b)))


def branching(s):
    after = {}
    for i in range(len(s)):
        for j in range(i + 2, len(s) + 1):
            after.setdefault(tuple(s[i:j]), set()).add(s[j] if j < len(s) else None)
    return {x for x, v in after.items() if len(v) > 1}


def test_tree_equals_a_fresh_tree_after_each_step():
    for c in units(60, 26, 7):
        sa, lcp = suffix.order_of(c)

        def check(t, alive):
            now, i = [], 0
            while i < len(t.text):
                now.append(t.text[i])
                i += 1
                if i <= len(alive) and not alive[i - 1]:
                    while i < len(alive) and not alive[i] and t.text[i] > MARK:
                        i += 1
            assert branching(now) == {tuple(t.label[t.at[v] : t.at[v] + d]) for d, b in t.buckets.items() for v in b}

        f = tree.run(c, sa, lcp, tie="bucket", check=check)
        assert unfold(f.residual, f.factors, f.kinds) == c


def test_invariants_of_steps():
    for c in units(200):
        sa, lcp = suffix.order_of(c)
        f = reach.run(c, sa, lcp)
        lens = [s.len for s in f.steps]
        assert lens == sorted(lens, reverse=True) and len(lens) <= len(c) / 2
        assert all(s.picks for s in f.steps) and sum(len(s.starts) for s in f.steps) <= 2 * len(c)
        pairs = [p for p in zip(f.residual, f.residual[1:]) if MARK not in p]
        assert len(pairs) == len(set(pairs)) or not [p for p in set(pairs) if pairs.count(p) > 1 and p[0] != p[1]]


def test_simple_keeps_half_and_decodes():
    for c in units(200):
        sa, lcp = suffix.order_of(c)
        for order in ("ends_first", "scan", "hash"):
            for f in (reach.run(c, sa, lcp, mode="simple", order=order), tree.run(c, sa, lcp, mode="simple", order=order)):
                assert unfold(f.residual, f.factors, f.kinds) == c
        for s in reach.steps_of(len(c), sa, lcp, mode="simple"):
            starts = sorted(s.starts)
            bound = next((p + s.len - 1 for p, k in s.picks if k == 1), starts[0] + s.len - 1)
            greedy = left_greedy(starts, s.len, bound)
            if len(greedy) > 1:
                assert sum(k == 3 for _, k in s.picks) >= max(-(-len(greedy) // 2), 2)


def test_typing_of_the_half_bound_example():
    starts = [0, 6, 9, 13]
    assert pick(starts, 5) == [(6, 3), (13, 3)]
    assert pick_simple([9, 13, 0, 6], 5) == [(6, 3), (13, 3)]


@pytest.mark.parametrize(("r", "s", "alpha", "beta", "accepted"), [(78, 60, 30, 80, False), (79, 30, 30, 80, True), (79, 29, 30, 80, False), (80, 15, 30, 80, True), (80, 14, 30, 80, False), (79, 60, 30, 80.5, True), (79, 59, 30, 80.5, False)])
def test_gate_on_the_family(r, s, alpha, beta, accepted):
    for text, blocks in ((adversarial_text(r, s), 1), (adversarial_text2(r, s), 2)):
        c = [ord(x) for x in text]
        f = gated.run(c, *suffix.order_of(c), alpha=alpha, beta=beta)
        assert len(f.kinds) == (blocks * s if accepted else 0)
        assert unfold(f.residual, f.factors, f.kinds) == c
        g = reach.run(c, *suffix.order_of(c))
        assert len(g.kinds) == blocks * s


def test_trivial_gate_misses_a_repeat_that_is_not_maximal():
    c = [ord(x) for x in FIXTURES["not_maximal"][0]]
    f = gated.run(c, *suffix.order_of(c), alpha=0, beta=2)
    assert "".join("#" if x == MARK else chr(x) for x in f.residual) == "qabcrvwxyas#bct$"


def test_baselines_decode():
    for c in units(200):
        sa, lcp = suffix.order_of(c)
        z = baselines.lz77(c, sa, lcp)
        assert baselines.lz77_decode(z) == c == baselines.lz77_decode(baselines.lz77_apart(c))
        p = 0
        for src, n, _ in z:  # each factor is the longest with an earlier start
            longest = max((k for q in range(p) for k in range(len(c) - p + 1) if c[q : q + k] == c[p : p + k]), default=0)
            assert n == max(1, longest) and (src < 0) == (longest == 0)
            p += n
        for rules, start in (baselines.pair_grammar(c), baselines.longest_grammar(c, sa, lcp)):
            assert baselines.expand(rules, start) == c
        rules, start = baselines.pair_grammar(c)
        assert max(baselines.disjoint_pairs(start).values(), default=0) < 2


def test_worked_grammars_and_factors():
    c = [ord(x) for x in FIXTURES["worked"][0]]
    sa, lcp = suffix.order_of(c)
    assert [p + 1 for p in sa] == [20, 7, 17, 4, 1, 12, 8, 15, 18, 5, 2, 13, 9, 19, 6, 16, 3, 14, 10, 11]
    assert lcp == [0, 0, 1, 3, 4, 4, 3, 1, 0, 2, 3, 3, 2, 0, 1, 2, 4, 2, 1, 0]
    assert [n for _, n, _ in baselines.lz77(c, sa, lcp)] == [1, 1, 1, 4, 3, 1, 4, 4, 1]
    rules, start = baselines.longest_grammar(c, sa, lcp)
    assert (len(start), sum(map(len, rules.values()))) == (10, 7)
    rules, start = baselines.pair_grammar(c)
    assert (len(start), sum(map(len, rules.values()))) == (8, 6)
    cut = {"".join(chr(x) for x in c[sa[lo] : sa[lo] + p]) for p, lo, hi in suffix.maximal_repeats(c, sa, lcp)}
    assert cut == {"a", "c", "ca", "abc", "abca", "cabc"}


def test_tree_choice_is_not_quadratic():
    """Pairs that stand twice: one bucket holds a third as many nodes as the text has symbols."""
    from repeatfold.kernels import reach, suffix, tree

    per = {}
    for k in (1_000, 8_000):
        codes = [x for part in (10**6, 2 * 10**6) for i in range(k) for x in (2 * i, 2 * i + 1, part + i)]
        sa, lcp = suffix.order_of(codes)
        for tie in ("leftmost", "lex"):
            f = tree.run(codes, sa, lcp, tie=tie)
            want = reach.run(codes, sa, lcp, tie=tie)
            assert (f.residual, f.factors, f.kinds) == (want.residual, want.factors, want.kinds)
            per.setdefault(tie, []).append(sum(s.select_work for s in f.steps) / len(codes))
            assert f.cells < 20 * len(codes)
    assert all(b < 1.2 * a for a, b in per.values())


def test_grammar_with_bodies():
    import random

    from repeatfold.kernels import baselines, suffix

    rng = random.Random(9)
    smaller = 0
    for _ in range(200):
        codes = [rng.randrange(3) for _ in range(rng.randint(0, 120))]
        order = suffix.order_of(codes)
        plain, full = baselines.longest_grammar(codes, *order), baselines.longest_grammar_bodies(codes, *order)
        assert baselines.expand(*full) == codes
        line = list(full[1])
        for k, body in enumerate(full[0].values()):
            line += [-(1 << 40) - k, *body]
        assert all(n < 2 for pair, n in baselines.disjoint_pairs(line).items()) and all(len(b) > 1 for b in full[0].values())
        size = lambda g: len(g[1]) + sum(map(len, g[0].values()))
        smaller += size(full) <= size(plain)
    assert smaller > 100
