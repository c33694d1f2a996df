"""Every query with SQL against DuckDB on the smallest tables; the fits that SQL can't follow have rows."""

import pytest
from conftest import same_rows

from nodeweave import queries as q
from nodeweave.operators import experiments as exp

#: Sweeps are tested on one cell below.
SWEEPS = [k for k in q.QUERIES if k.startswith("scenario")]
FITS = [k for k in q.QUERIES if k not in q.ORACLES and k not in SWEEPS]


@pytest.mark.parametrize("name", sorted(set(q.ORACLES) - set(SWEEPS)))
def test_query_matches_sql(spark, sf, duck, name):
    assert same_rows(q.QUERIES[name](spark, sf), duck, q.ORACLES[name]) > 0


@pytest.mark.parametrize("name", FITS)
def test_fit_has_rows(spark, sf, name):
    assert q.QUERIES[name](spark, sf).count() > 0


def test_sweep(spark, sf, duck, monkeypatch):
    """A sweep cut to one short setting, by its registered queries: every method, measure and generator, once and ten times."""
    small = [dict(n=120, p=20, k=3, sigma=0.0, setting=120)]
    monkeypatch.setattr(exp, "SCENARIOS", {"samples": small})
    assert same_rows(q.QUERIES["scenario_coverage"](spark, sf), duck, q._keys_sql()) == len(exp.GENERATORS) * len(exp.METHODS) * 6
    rows = q.QUERIES["scenario_samples"](spark, sf).collect()
    assert len(rows) == len(exp.GENERATORS) * len(exp.METHODS) * 6 and all(r["runs"] == 10 for r in rows)


def test_a_cell_equals_the_distributed_path(spark, sf):
    """Both forms of the proposal: a task's local fit and the distributed one have one loss."""
    from nodeweave.functions.states import Options, fit_local
    from nodeweave.sources.planted import draw, plant_truth

    cell = dict(n=200, p=16, k=3, sigma=0.5, setting=200)
    keys = spark.read.parquet(f"{sf}/events.parquet")
    ids = sorted(r[0] for r in keys.select("event_id").collect())[:200]
    for generator in exp.GENERATORS:
        for form in (exp.MIXTURE, exp.PRINTED):
            form = form | {"max_iter": 4}
            model, _, truth = exp.distributed_cell(spark, keys, "event_id", cell, generator=generator, form=form)
            x, _ = draw(plant_truth(2, 3, 16, 0, construction=generator), ids, 0.5, 0)
            assert model.loss == pytest.approx(fit_local(x, Options(m=2, k=3, **form), ids).loss, rel=1e-8)


def test_entry(spark):
    import __spark_entry__ as e

    rows = e.entry(spark)
    assert rows.count() > 0 and set(e.oracle_sql()) <= set(e.queries())
