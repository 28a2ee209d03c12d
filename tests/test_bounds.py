"""A loop that meets its bound before the work is done raises instead of returning part of the points."""

import numpy as np
import pytest

from frontfill.functions import domain as D
from frontfill.functions import spacing as S
from frontfill.functions.lattice import CENTRE
from frontfill.plans import baselines, fill

MIDDLE = np.array([[CENTRE, CENTRE]], np.int64)


@pytest.mark.parametrize("alone", [True, False])
def test_phased_fill_raises(spark, alone):
    with pytest.raises(Exception, match="phased fill did not finish"):
        fill.fill_phased(spark, D.disc(), S.Constant(400_000), limit=32, one_task=alone, max_stages=2).count()


def test_baseline_raises():
    with pytest.raises(RuntimeError, match="did not finish"):
        baselines.voronoi_kd_arrays(D.disc(), S.Constant(400_000), MIDDLE, max_rounds=1)
