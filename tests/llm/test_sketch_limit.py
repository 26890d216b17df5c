"""The sketch rules out fewer pairs at the threshold than the bands miss."""

from math import comb

from simweave.llm import minhash_dedup as N


def test_sketch_keeps_pairs_at_the_threshold():
    agree = (1 + N.SIMILARITY) / 2
    dropped = sum(comb(N.SKETCH_BITS, k) * agree**k * (1 - agree) ** (N.SKETCH_BITS - k) for k in range(N.LEAST_AGREE))
    assert dropped < 1e-9 < (1 - N.SIMILARITY**N.ROWS) ** N.BANDS
