"""Work that a chunk of texts is spared when it is scored."""

import numpy as np

from blockgraph.llm import ppm


def test_scoring_takes_token_keys_without_counts():
    texts = [b"One two two", b"", b" \n", b"three ONE \xc3\xa9", b"two"]
    assert (ppm._own_token_keys(texts) == ppm._own_tokens(texts, [True, False, True, False, True])[0]).all()
    assert ppm._own_token_keys([]).tolist() == ppm._own_tokens([], [])[0].tolist() == [ppm.END_KEY]


def test_shares_sort_shorts(monkeypatch):
    rng = np.random.default_rng(2)
    kinds, sort = [], np.argsort
    monkeypatch.setattr(np, "argsort", lambda x, **k: (kinds.append(x.dtype.itemsize), sort(x, **k))[1])
    for buckets, size in ((51, 2), (1 << 16, 2), ((1 << 16) + 9, 8)):
        place = rng.integers(0, buckets, 5000)
        got = dict(ppm._shares(place, buckets))
        assert kinds.pop() == size
        assert all((i == np.flatnonzero(place == q)).all() for q, i in got.items()) and sum(map(len, got.values())) == 5000
