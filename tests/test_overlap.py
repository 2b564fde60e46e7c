"""Links by shared groups, counted without listing them, against brute force."""

import numpy as np

from seedspread.operators.overlap import linked_members


def test_links_and_components_match_brute_force(spark):
    rng = np.random.default_rng(8)
    pairs = {(int(m), f"g{g}") for m, g in zip(rng.integers(0, 120, 260), rng.integers(0, 110, 260), strict=True)} | {(m, "hot") for m in range(200, 240)} | {(m, "hot2") for m in range(200, 240)} | {(239, "g5")}
    rows = sorted(pairs) + sorted(pairs)[:9] + [(None, "g1"), (3, None)]
    near = {}
    for g in {g for _, g in pairs}:
        own = {m for m, h in pairs if h == g}
        for m in own:
            near.setdefault(m, set()).update(own - {m})
    near = {m: o for m, o in near.items() if o}
    low = {m: m for m in near}
    for _ in near:
        low = {m: min([low[m], *(low[o] for o in near[m])]) for m in near}
    frame = spark.createDataFrame(rows, "m long, g string")
    for size in (20_000, 3):
        got = {r["m"]: (r["n_links"], r["component"]) for r in linked_members(frame, size).collect()}
        assert got == {m: (len(near[m]), low[m]) for m in near}
    assert linked_members(frame.filter("m is null")).count() == 0
    # 200,000 members of one group stand for 4e10 links
    many = linked_members(spark.range(200_000).selectExpr("id as m", "'g' as g"))
    assert many.filter("n_links = 199999 and component = 0").count() == 200_000
