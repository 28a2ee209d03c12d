"""Python functions callable from SQL: a fill as a table function and a clustering aggregate."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import LongType

from frontfill.functions.lattice import CENTRE


@udtf(returnType="seq bigint, x0 bigint, x1 bigint")
class FillDisc:
    """``SELECT * FROM fill_disc(h)``: the sequential fill of the standard disc from its centre; small fills only."""

    def eval(self, h: int):
        import numpy as np

        from frontfill.functions.directions import directions
        from frontfill.functions.domain import disc
        from frontfill.functions.kernel import front_fill
        from frontfill.functions.spacing import Constant

        start = np.array([[CENTRE, CENTRE]], np.int64)
        f = front_fill(start, np.arange(1), Constant(h).at, disc().mask, directions(2), h)
        for i, (x, y) in enumerate(np.concatenate([start, f.x]).tolist()):
            yield i, x, y


@pandas_udf(LongType())
def widest_gap(v: pd.Series) -> int:
    """Largest step between neighbours in sorted order."""
    s = v.dropna().sort_values().to_numpy()
    return int((s[1:] - s[:-1]).max()) if len(s) > 1 else 0


def register(spark) -> None:
    spark.udtf.register("fill_disc", FillDisc)
    spark.udf.register("widest_gap", widest_gap)
