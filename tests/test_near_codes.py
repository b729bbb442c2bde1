"""Near-duplicate codes against brute force."""
import numpy as np

from signgraph.plans import index_queries


def test_near_codes(spark):
    r = np.random.default_rng(3)
    codes = []
    for p in r.integers(0, 1 << 62, 30).tolist():
        s = int(r.integers(0, 1 << 62))
        for flips in (0, 0, 1, 2, 3):
            q = p
            for bit in r.choice(62, flips, replace=False).tolist():
                q ^= 1 << bit
            codes.append((q, s ^ int(r.integers(0, 2))))
    least = {}
    for i, c in enumerate(codes):
        least.setdefault(c, i)
    want = {(least[c], i, 0, "copy") for i, c in enumerate(codes) if least[c] != i}
    for (p, s), a in least.items():
        for (q, z), b in least.items():
            x = p ^ q
            if a < b and x.bit_count() <= 2:
                want.add((a, b, sum((1 + (s >> k & 1)) * (1 + (z >> k & 1)) for k in range(62) if x >> k & 1), "near"))
    got = index_queries.near_codes(spark.createDataFrame([(i, [p], [s]) for i, (p, s) in enumerate(codes)], "vec_id long, p array<long>, s array<long>")).collect()
    assert {tuple(x) for x in got} == want and len(got) == len(want)
    assert any(k == "near" and d > 0 for _, _, d, k in want) and any(k == "copy" for *_, k in want)
