"""The vector search over several shards and regions against brute force, on vectors that have links."""

import numpy as np
import pytest

from sightline.llm import embed_dedup

KIND = "vec_id long, embedding array<float>, label int"


def plain(rows, least=0.93):
    """n_links and component of each vector by all pairs."""
    near = {i: [] for i, *_ in rows}
    for label in {r[2] for r in rows}:
        ids = np.array([r[0] for r in rows if r[2] == label])
        x = np.array([r[1] for r in rows if r[2] == label], np.float32).astype(float)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
        for i, hits in zip(ids.tolist(), x @ x.T >= least):
            near[i] = [j for j in ids[hits].tolist() if j != i]
    comp = {}
    for i in sorted(near):
        if i not in comp:
            comp[i], work = i, [i]
            while work:
                for j in near[work.pop()]:
                    if j not in comp:
                        comp[j] = i
                        work.append(j)
    return {i: (len(near[i]), comp[i]) for i in near}


def made(rng, groups, copies, noise, dim=16, spread=1.0):
    out, base = [], rng.normal(size=(3, dim))
    for g in range(groups):
        centre = base[g % 3] + spread * rng.normal(size=dim)
        for _ in range(copies):
            out.append((len(out), (centre + rng.normal(size=dim) * noise).tolist(), 7))
    return out


@pytest.mark.parametrize("region_rows", [60, 300])
def test_regions_lose_no_link(spark, region_rows):
    rng = np.random.default_rng(region_rows)
    rows = made(rng, 130, 7, 0.2)
    rows += [(len(rows) + k, rows[k][1], 7) for k in range(0, 60, 3)]  # copies
    rows += [(len(rows) + k, rows[0][1], 7) for k in range(200)]  # a hot vector
    rows += [(len(rows) + k, (np.array(rows[0][1]) + rng.normal(size=16) * 0.05).tolist(), 7) for k in range(400)]  # a hot spot, larger than a region
    found, recall = embed_dedup.near_vectors(spark.createDataFrame(rows, KIND), region_rows=region_rows, query_rows=100)
    got = {r.vec_id: (r.n_links, r.component_id) for r in found.collect()}
    want = plain(rows)
    assert sum(n for n, _ in want.values()) > 2000
    assert sum(min(got[i][0], n) for i, (n, _) in want.items()) >= 0.999 * sum(n for n, _ in want.values()) and recall > 0.99
    assert all(got[i][0] <= want[i][0] for i in want)
    assert np.mean([got[i][1] == want[i][1] for i in want]) > 0.99


def test_odd_vectors(spark):
    assert embed_dedup.near_vectors(spark.createDataFrame([], KIND))[0].count() == 0
    rows = [(1, [1.0, 0.0], 1, "a"), (1, [1.0, 0.0], 1, "b"), (2, None, 1, "c"), (3, [1.0, 0.0, 0.0], 1, "d"), (4, [0.0, 0.0], None, "e"), (5, [1.0, 0.001], 1, "f")]
    more = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int, rep string")
    got = sorted((r.vec_id, r.n_links, r.component_id) for r in embed_dedup.near_vectors(more)[0].collect())
    assert got == [(1, 2, 1), (1, 2, 1), (2, 0, 2), (3, 0, 3), (4, 0, 4), (5, 2, 1)]
    named = spark.createDataFrame([(1, [1.0, 0.0], "x"), (2, [1.0, 0.0], "x"), (3, [1.0, 0.0], "y")], "vec_id long, embedding array<double>, label string")
    assert sorted((r.vec_id, r.component_id) for r in embed_dedup.near_vectors(named)[0].collect()) == [(1, 1), (2, 1), (3, 3)]
