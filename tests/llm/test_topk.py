import numpy as np

from latticecube.llm import topk


def brute(rows, k):
    use = {}
    out = []
    for i, v in rows:
        if i is not None and v and all(x is not None and np.isfinite(x) for x in v):
            use.setdefault(i, []).append(np.floor(64 * np.array(v, np.float64)).astype(np.int64))
    for q, qs in use.items():
        if q % 20 == 0:
            for qv in qs:
                got = sorted((-int(qv @ c), i) for i, cs in use.items() if i != q for c in cs if len(c) == len(qv))[:k]
                out += [(q, i, -s) for s, i in got]
    return sorted(out)


def run(spark, rows, k=20, drop=1):
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    v = topk.quantised(df, 64)
    return topk.top_k(v.where("vec_id % 20 = 0"), v, k, drop)


def test_against_brute_force(spark):
    rng = np.random.default_rng(3)
    rows = [(i, rng.normal(0, 0.2, 16).astype(np.float32).tolist()) for i in range(3000)]
    rows += [(3000 + i, rows[7][1]) for i in range(300)]  # ties
    rows += [(9000, None), (9020, []), (9040, [float("nan")] * 16), (9060, [None] + [0.1] * 15), (None, [0.1] * 16), (9080, [1.0, 2.0]), (9081, [3.0, -2.0])]
    for drop in (0, 1, 2):
        got = run(spark, rows, drop=drop).collect()
        assert sorted((r.query_id, r.vec_id, r.score) for r in got) == brute(rows, 20)
    for q in {r.query_id for r in got}:
        own = sorted((r for r in got if r.query_id == q), key=lambda r: r["rank"])
        assert [r["rank"] for r in own] == list(range(1, len(own) + 1))
        assert [(-r.score, r.vec_id) for r in own] == sorted((-r.score, r.vec_id) for r in own)


def test_few_and_none(spark):
    assert run(spark, [(0, [1.0]), (1, [2.0]), (2, [-1.0])]).count() == 2
    assert run(spark, []).count() == 0


def test_bitmap_sums_are_exact():
    rng = np.random.default_rng(0)
    values = rng.integers(-40, 40, (500, 9))
    block = topk.SlicedBlock(values)
    q = rng.integers(-40, 40, 9)
    sums = block.score_slices(q)
    bits = [np.unpackbits(s.view(np.uint8), bitorder="little")[:500].astype(np.int64) for s in sums]
    got = sum(b << p for p, b in enumerate(bits))
    full = (1 << block.digits) - 1
    want = np.where(q > 0, (values - block.low) * q, (full - (values - block.low)) * -q).sum(axis=1)
    assert (got == want).all()
