"""Queries of the compared methods read the whole stream."""

import numpy as np
import pytest

from cellstream import catalog_methods
from tests.conftest import SMALL


def test_masked_gradient_and_rank_read_all_months(spark):
    rows = catalog_methods._log_flow(spark, SMALL).toPandas()
    months = int(rows["t"].max()) + 1
    assert months > 24
    m = catalog_methods.methods.MaskedGradientCp(catalog_methods.TensorSpec((25, 25), 12, 2), 60)
    b = catalog_methods.methods.BayesRobustStream(catalog_methods.TensorSpec((25, 25), 12, 6))
    for t in range(months):
        p = rows[rows["t"] == t]
        for method in (m, b):
            method.feed(p[["i1", "i2"]].to_numpy(np.int64), p["y"].to_numpy())
    assert catalog_methods.b8_run(spark, SMALL).first()["loss"] == pytest.approx(float(m.run()), rel=1e-2)
    assert catalog_methods.b4_effective_rank(spark, SMALL).first()["rank"] == b.effective_rank
