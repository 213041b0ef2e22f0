"""Equal-depth cells against plain percentiles."""

import numpy as np
from pyspark.sql import functions as F

from packvec.operators import quantizers as qz


def test_equal_depth_is_exact_without_gathering_values(spark):
    rng = np.random.default_rng(3)
    x = {0: rng.standard_normal(5001), 1: rng.integers(0, 3, 4000).astype(float), 2: np.array([7.0]), 3: np.exp(3 * rng.standard_normal(3000))}
    values = spark.createDataFrame([(i, d, float(v)) for d, a in x.items() for i, v in enumerate(a)] + [(9, 0, None)], "vec_id long, dim int, x double").repartition(5)
    plan = spark.createDataFrame([(0, 3, 8), (1, 3, 8), (2, 2, 4), (3, 4, 16)], "dim int, bits int, cells long")
    found = qz.equal_depth(values, plan, accuracy=200)  # brackets of about 100 values
    got = {r["dim"]: r["edges"] for r in found.collect()}
    for d, b in ((0, 3), (1, 3), (2, 2), (3, 4)):
        assert np.allclose(got[d], np.quantile(x[d], np.arange(2**b + 1) / 2**b), rtol=0, atol=1e-8), d
    assert " percentile(" not in found._jdf.queryExecution().toString()
    codes = qz.encode(values.where(F.col("x").isNotNull()), found)
    assert codes.count() == sum(map(len, x.values()))
