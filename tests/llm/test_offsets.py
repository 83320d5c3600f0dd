"""Silent passages vote for false offsets."""

import numpy as np

from ctxviews.llm import chroma


def noisy_copy():
    """A recording with two silent passages, and a copy with bit errors of which one passage is half spared."""
    rng = np.random.default_rng(1)
    a = rng.integers(0, 1 << 32, 150, dtype=np.uint32)
    a[:40] = a[80:110] = 7
    b = a ^ (np.uint32(1) << rng.integers(8, 32, 150).astype(np.uint32))
    b[80:110:2] = 7
    return a, b


def test_true_offset_is_found_below_a_false_peak():
    a, b = noisy_copy()
    votes = lambda o: int((a[max(0, o) : min(150, 150 + o)] == b[max(0, -o) : min(150, 150 - o)]).sum())
    assert max(votes(o) for o in range(-100, 0)) >= votes(0) >= chroma.LEAST_VOTES
    (q, offset, v, errors), = chroma.QueryBlock([4], [a]).align(b)
    assert (q, offset, v) == (4, 0, votes(0)) and errors == chroma.bit_errors(a, b, 0)[0]


def test_align_brute_force():
    rng = np.random.default_rng(2)
    prints = [rng.choice(np.array([7, 7, 7, 9, 1 << 20, 3 << 12], np.uint32), n) for n in (5, 30, 60, 90)]
    for p in prints:
        want = []
        for k, q in enumerate(prints):
            ok = []
            for o in range(-len(p) + 1, len(q)):
                lo, hi = max(0, o), min(len(q), len(p) + o)
                v = int((q[lo:hi] == p[lo - o : hi - o]).sum())
                errors, overlap = chroma.bit_errors(q, p, o)
                if v >= chroma.LEAST_VOTES and errors <= chroma.MOST_ERRORS and overlap >= min(chroma.LEAST_OVERLAP, len(p), len(q)):
                    ok.append((errors, -overlap, -v, o))
            if ok:
                e, _, v, o = min(ok)
                want.append((k, o, -v, e))
        assert list(chroma.QueryBlock([0, 1, 2, 3], prints).align(p)) == want
