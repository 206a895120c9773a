"""Cases of the findings of round 2 that stayed open: queries of one length predicted together."""

import numpy as np
import pandas as pd

from bigtopics.operators import predict


def asked(k, queries=80, words=30):
    rng = np.random.default_rng(8)
    model = [np.sort(rng.choice(k, int(rng.integers(0, 4)), replace=False)) for _ in range(words)]
    n = [rng.integers(1, 9, len(t)) for t in model]
    best, own = rng.integers(-1, k, words), [rng.integers(0, words, int(rng.integers(1, 6))).tolist() for _ in range(queries)]
    ids = [None if d == 5 else d - 3 for d in range(queries)]
    f = pd.DataFrame({"doc_id": pd.array(ids, dtype="Int64"), "best_topic": [[int(best[w]) for w in q] for q in own], "topics": [[model[w] for w in q] for q in own], "counts": [[n[w] for w in q] for q in own]})
    rows = [[(model[w], n[w].astype(float)) for w in q] for q in own]
    return f, rows, [np.array([best[w] if best[w] >= 0 else 2 for w in q]) for q in own], rng.integers(20, 60, k).astype(float), rng.random(k)


def by_row(got):
    out = {}
    for r, t, x in zip(*(y.tolist() for y in got), strict=True):
        out.setdefault(r, {})[t] = round(x, 9)
    return out


def test_f7_f20_queries_sampled_together_equal_queries_sampled_alone():
    f, rows, _, psi, alpha = asked(6)
    got = by_row(predict._sample_together(f, psi, alpha, 0.01, 30, 2, most=40, seed=7))
    for i, (doc, q) in enumerate(zip(f["doc_id"], rows, strict=True)):
        rng = np.random.Generator(np.random.Philox(np.random.SeedSequence([7, 1 << 64 if doc is pd.NA else int(doc) % (1 << 64)])))
        mean = predict.sample_query(q, psi, alpha, 0.01, 30, rng)
        assert got[i] == {k: round(mean[k], 9) for k in np.flatnonzero(mean).tolist()}, i


def test_f8_trials_solved_together_equal_trials_solved_alone():
    f, rows, best, psi, alpha = asked(6)
    got = by_row(predict._solve_together(f, psi, alpha, 0.01, 30, 2, most=40, trials=3, seed=7, pruned=True))
    for i, (doc, q, b) in enumerate(zip(f["doc_id"], rows, best, strict=True)):
        rng = np.random.Generator(np.random.Philox(np.random.SeedSequence([7, 1 << 64 if doc is pd.NA else int(doc) % (1 << 64)])))
        starts = [None, *([int(t[int(rng.integers(len(t)))]) if len(t) else int(x) for (t, _), x in zip(q, b, strict=True)] for _ in range(2))]
        z = np.concatenate([predict.ascend(q, b, psi, alpha, 0.01, 30, start=s)[0] for s in starts])
        assert got[i] == {int(k): round(n / 3, 9) for k, n in zip(*np.unique(z, return_counts=True), strict=True)}, i
