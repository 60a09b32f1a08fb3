import math

import numpy as np
from pyspark.sql import functions as F

from plate_engine.functions.special import digamma, digamma_np, log_gamma, log_gamma_np


def test_fixed_values_and_recurrence(spark):
    grid = np.geomspace(1e-3, 1e8, 400)
    got = np.array(spark.createDataFrame([(float(x),) for x in grid], "x double").select(digamma(F.col("x")), log_gamma(F.col("x"))).collect())
    assert np.allclose(got[:, 0], digamma_np(grid), rtol=1e-12, atol=1e-12)
    assert np.allclose(got[:, 1], [math.lgamma(x) for x in grid], rtol=4e-12, atol=1e-11)
    assert np.allclose(log_gamma_np(grid), got[:, 1], rtol=1e-12, atol=1e-11)
    assert np.allclose(digamma_np(grid + 1), digamma_np(grid) + 1 / grid, rtol=1e-11, atol=1e-11)
    for x, y in ((1.0, -0.5772156649015329), (0.5, -1.9635100260214235), (0.01, -100.56088545786867)):
        assert abs(digamma_np(np.array([x]))[0] - y) < 1e-11
