"""Cases of the findings of round 2 that stayed open: the kernel over lists."""

import numpy as np
import pytest

from bigtopics.operators import sampling


@pytest.mark.parametrize("topics", [4, 16])
def test_f2_f3_f16_lists_give_the_labels_of_the_arrays_from_piece_to_piece(topics):
    rng, v = np.random.default_rng(1), 60
    docs = np.repeat(np.arange(90), 7)
    words, z, u, a = rng.integers(0, v, 630), rng.integers(0, topics, 630), rng.random(630), rng.random(topics)
    theta, phi, psi = sampling.count_arrays(docs, words, z, topics, v)
    tables, totals = (sampling.Rows.of(phi), sampling.Lists(sampling.Rows.of(phi), topics), sampling.Lists(phi.copy(), topics)), [psi.copy() for _ in range(3)]
    for lo in (0, 350):
        now = slice(lo, 350 if not lo else 630)
        got = [sampling.sample_buckets(sampling.Block(docs[now], words[now], z[now], sampling.Table(theta.copy()), t, p), a, 0.01, v, u[now]) for t, p in zip(tables, totals, strict=True)]
        assert (got[0] == got[1]).all() and (got[0] == got[2]).all() and (got[0] != z[now]).any()
    assert all((t.dense(topics) == tables[0].dense(topics)).all() for t in tables)
    assert all((p == totals[0]).all() and p.sum() == 630 for p in totals)
