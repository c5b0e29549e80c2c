"""The replicated search on more edges than a worker may hold."""

from graphsieve.operators.baselines import replicated_enumerate, shares_of
from graphsieve.operators.sieve import enumerate_matches, sieve
from graphsieve.sources.graphs import build
from graphsieve.workloads import WORKLOADS


def test_cells(spark, sf):
    g, t = build(spark, sf, "trade"), WORKLOADS["w2"][1]
    want = sorted(map(tuple, enumerate_matches(sieve(g, t)).collect()))
    for most in (500, 1 << 40):  # 500 was refused
        assert sorted(map(tuple, replicated_enumerate(g, t, most).collect())) == want and want


def test_shares():
    sizes = {(0, 1): 3_000, (0, 2): 18_000, (1, 2): 6_000}
    assert shares_of(sizes, 3, 1 << 20) == [1, 1, 1]
    shares = shares_of(sizes, 3, 1_000)
    assert sum(n / shares[a] / shares[b] for (a, b), n in sizes.items()) <= 1_000
