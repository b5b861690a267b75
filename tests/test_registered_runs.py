"""What the registered experiments ask for; and that the coded ones decode."""

import pytest

from posterior_mesh import experiments as ex
from posterior_mesh import registry
from posterior_mesh.operators import models, protocols

CURVES = [f"paper_{kind}_{case}" for kind in ("errors", "curve") for case in ("5_2", "40_2", "40_4")]
VARIANTS = ["errors_weights_exact", "errors_weights_uniform", "errors_weights_diagonal", "errors_coded_warmup", "errors_coded_recompute", "errors_last_round", "error_quantiles_5_2", "curves_side_by_side_5_2"]


@pytest.mark.parametrize("name", [*CURVES, *VARIANTS, "linear_errors", "crossover_whole"])
def test_registered_experiments_have_all_runs_and_times(monkeypatch, name):
    asked = {}

    def take(*args, runs=None, grid=(), **options):
        asked.update(runs=runs, grid=grid)

    for f in ("paper_errors", "paper_curves", "linear_errors", "crossover"):
        monkeypatch.setattr(ex, f, take)
    monkeypatch.setattr(registry, "rounded", lambda df: df)
    monkeypatch.setattr(ex, "side_by_side", lambda df: df)
    monkeypatch.setattr(registry.metrics, "curve_quantiles", lambda df: df)
    registry.QUERIES[name](None, "")
    assert asked["runs"] == 50 and tuple(asked["grid"]) == (1.0, 2.0, 5.0, 10.0, 20.0, 50.0, 100.0)


def test_coded_errors_are_of_decoded_sums(spark, monkeypatch):
    asked, decode = [], protocols.decode
    monkeypatch.setattr(protocols, "decode", lambda *args: asked.append(args[2]) or decode(*args))
    rows = ex.errors_of(spark, protocols.ProtocolSpec("coded_sum", 5, 2, warmup=3), models.toeplitz_subposteriors(spark, 5), [2.0]).collect()
    assert len(asked) == 1 and len(rows) == 1 and rows[0]["err"] is not None
