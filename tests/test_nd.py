import numpy as np
import pytest

from knnscope.operators import cluster_nd
from knnscope.operators.service import Budget


@pytest.fixture(scope="module")
def blobs():
    rng = np.random.default_rng(3)
    centres = np.array([[-2.0, -2, -2], [2, 2, 2], [2, -2, 1]])
    x = np.concatenate([c + rng.normal(size=(150, 3)) * 0.25 for c in centres] + [rng.uniform(-4, 4, (40, 3))])
    return np.arange(len(x)), x, np.repeat([0, 1, 2, -1], [150, 150, 150, 40])


def test_clusters_in_three_dimensions(spark, blobs):
    ids, x, label = blobs
    s = cluster_nd.MemoryKnnServiceNd(ids, x, 8, Budget(600))
    model = cluster_nd.cluster_nd(s, [-4.0] * 3, 8.0, 3, 4, 4, 0.8)
    assert s.budget.used <= 600 and model.info["calls"] == s.budget.used
    df = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x)] + [(9000, [9.0, 0.0, 0.0]), (9001, None), (9002, [1.0])], "id long, v array<double>")
    got = {r.id: r.cluster_id for r in model.assign(df).collect()}
    assert got[9000] is None and got[9001] is None and got[9002] is None
    kinds = [{got[i] for i in ids[label == c].tolist()} - {None} for c in range(3)]
    assert all(len(k) >= 1 for k in kinds) and not kinds[0] & kinds[1] and not kinds[1] & kinds[2]
    inside = sum(got[i] is not None for i in ids[label >= 0].tolist())
    assert inside > 0.6 * 450


def test_the_distributed_service_answers_as_the_arrays_do(spark, blobs):
    ids, x, _ = blobs
    df = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x)] + [(9001, None), (9003, [float("nan")] * 3)], "id long, v array<double>").repartition(3)
    places = [(0.0, 0.0, 0.0), (2.0, 2.0, 2.0), (-9.0, 1.0, 1.0)]
    a = cluster_nd.KnnServiceNd(df, 7).probe(places)
    b = cluster_nd.MemoryKnnServiceNd(ids, x, 7).probe(places)
    for p, q in zip(a, b):
        assert p.ids.tolist() == q.ids.tolist() and p.radius == pytest.approx(q.radius)
