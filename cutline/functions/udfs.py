"""Pandas UDFs beside the native expressions. Annotations are real types here, which pandas_udf reads."""

import pandas as pd
from pyspark.sql.functions import pandas_udf


def projector(cx: int, cy: int):
    """x * cx + y * cy of fixed-point positions."""

    @pandas_udf("long")
    def project(x: pd.Series, y: pd.Series) -> pd.Series:
        return x * cx + y * cy

    return project


@pandas_udf("double")
def least_expansion(size: pd.Series, small: pd.Series) -> float:
    return round(float((size / small).min()), 6)
