"""Embedding groups where many vectors crowd together."""

import math

import numpy as np
import pytest

from fewbit.llm import embedding_dedup


@pytest.mark.parametrize("cone, spread", [(2500, 5500), (6000, 0)])
def test_links_inside_a_dense_cone(spark, cone, spread):
    rng = np.random.default_rng(1)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    x = unit(np.vstack([unit(rng.standard_normal(64)) + 0.5 * unit(rng.standard_normal((cone, 64))), rng.standard_normal((spread, 64))]))
    for i in range(0, 400, 2):  # pairs just above the threshold
        other = unit(x[i + 1] - (x[i + 1] @ x[i]) * x[i])
        x[i + 1] = 0.905 * x[i] + math.sqrt(1 - 0.905**2) * other
    x = x.astype(np.float32)
    data = spark.createDataFrame([(i, v) for i, v in enumerate(x.tolist())], "vec_id long, embedding array<float>")
    got = {r.vec_id: r for r in embedding_dedup.embedding_groups(data).collect()}
    u = unit(x.astype(float))
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    component = np.arange(len(u))
    while (low := np.where(near.any(1), np.minimum(component, np.where(near, component, len(u)).min(1)), component)).tolist() != component.tolist():
        component = low
    assert [got[i].n_links for i in range(len(u))] == near.sum(1).tolist()
    assert [got[i].component_id for i in range(len(u))] == component.tolist()
