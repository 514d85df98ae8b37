import math

from pyspark.sql import functions as F

from lakejoin.operators import quality


def error(spark, n, theta):
    return spark.range(1).select(quality.sketch_error(F.lit(n), F.lit(theta))).first()[0]


def test_one_shared_value_that_is_seen(spark):
    """It is seen once in 1 / theta times, far oftener than four standard errors say."""
    theta = 4096 / 90_000
    assert 1 / theta - 1 > 4 * math.sqrt(1 / theta - 1)
    assert 1 / theta - 1 <= error(spark, 1, theta)


def test_many_shared_values_have_four_standard_errors(spark):
    for n, theta in ((40_000, 0.05), (1_000_000, 0.004)):
        four = 4 * math.sqrt(n * (1 / theta - 1))
        assert four <= error(spark, n, theta) <= 1.2 * four
    assert error(spark, 5, 1.0) == 0
