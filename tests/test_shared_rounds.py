"""Settings that go the same way share their rounds, and give what each gives alone."""

import numpy as np

from evenpart.operators import partition as P


def test_rounds_are_made_once(spark, monkeypatch):
    rng = np.random.default_rng(2)
    x = rng.normal(size=(120, 3)) + 3.0 * np.eye(3)[np.arange(120) % 3]
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vid long, x array<double>").cache()
    settings = [{"eps": 0.35, "pick": "max_gap"}, {"eps": 0.35, "pick": "max_gap", "keep": "last_valid", "min_parts": 3}, {"eps": 0.35, "pick": "first"}]
    run = lambda s, **more: P.practical_loop(v, s["eps"], 2, 20, sigma=2.0, **{"min_parts": 4, **{k: z for k, z in s.items() if k != "eps"}}, **more)
    show = lambda got: (got.k, [{k: round(z, 9) if isinstance(z, float) else z for k, z in r.items() if k != "seconds"} for r in got.trace], sorted(map(tuple, got.assign.collect())))
    alone = [show(run(s)) for s in settings]
    asked, check = [], P.check_pairs
    monkeypatch.setattr(P, "check_pairs", lambda a, eps, checker, *more, **named: asked.append((eps, checker, named.get("only") is not None)) or check(a, eps, checker, *more, **named))
    memo: dict = {}
    counts = []
    for s, want in zip(settings, alone, strict=True):
        before = len(asked)
        assert show(run(s, memo=memo)) == want
        counts.append(len(asked) - before)
    assert counts[0] > 1 and counts[1] == 0  # the same way: nothing is checked again
    first = (0.35, "codegree", False)
    assert asked[: counts[0]].count(first) >= 1 and asked[counts[0] :].count(first) < asked[: counts[0]].count(first)  # the first round is shared
