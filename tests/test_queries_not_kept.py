"""The queries of F6, F8 to F12, F14, F15, F21 and F23 as registered, where K is too large to keep: what their engines hold before the first sweep is points."""

import pytest

from kernmill.operators import engines, gram
from kernmill.plans.layout import StoreSpec
from kernmill.workloads import tables

NAMES = ("fit_mixed_rowsplit_k10", "fit_mixed_symmetric_k10", "fit_regrid_h1d_k10", "fit_tile_2d_k10", "fit_window_disk_k10", "rings_poly", "traffic_mixed", "assign_holdout", "history_decrease", "lobes_linear")


class Swept(Exception):
    pass


@pytest.mark.parametrize("name", NAMES)
def test_points_stand_for_k(spark, sf_dir, name, monkeypatch):
    def first(self, labels, sizes):
        raise Swept(self)

    monkeypatch.setattr(StoreSpec, "keeps", lambda self, n: False)
    monkeypatch.setattr(engines.Engine, "sweep", first)
    with pytest.raises(Swept) as found:
        tables.QUERIES[name](spark, sf_dir)
    (run,) = found.value.args
    (held,) = run.held
    run.close()
    assert held.columns == [c.split()[0] for c in gram.PLACED.split(", ")]
    assert [item for _, item in run.traffic] == ["points"]
