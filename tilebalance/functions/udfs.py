"""Arrow-batched functions: group lookup by cut keys, a grouped spread, a lattice table function."""

from collections.abc import Sequence

from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def group_of(cuts: Sequence[int]):
    """Column function: the number of the last cut at or before a value.  The cuts travel once with the task."""
    import numpy as np

    keys = np.asarray(cuts)

    @pandas_udf("int")
    def run(v):
        import pandas as pd

        return pd.Series(np.searchsorted(keys, v.to_numpy(), side="right") - 1)

    return run


def spread():
    import pandas as pd

    def run(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return F.pandas_udf(run, "double")


@udtf(returnType="tx: int, ty: int")
class Lattice:
    """Tiles of an nx by ny lattice."""

    def eval(self, nx: int, ny: int):
        for y in range(ny):
            for x in range(nx):
                yield x, y
