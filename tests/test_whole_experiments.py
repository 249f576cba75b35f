"""Cases in which a query once did less than the whole job."""

from cubefactor import registry
from cubefactor.registry import experiments


def test_every_user_and_event_type_gets_hours(spark, sf_dir):
    cells = [(r["i1"], r["i2"], r["i3"]) for r in experiments.planted_events(spark, sf_dir).cells.collect()]
    users, types, hours = ({c[k] for c in cells} for k in range(3))
    got = registry.queries()["recommend_hours"](spark, sf_dir).collect()
    rows = {}
    for r in got:
        rows.setdefault((r["i1"], r["i2"]), []).append(r["i3"])
    seen = set(cells)
    for u in users:
        for e in types:
            free = {h for h in hours if (u, e, h) not in seen}
            own = rows.get((u, e), [])
            assert len(own) == len(set(own)) == min(3, len(free)) and set(own) <= free


def test_scaling_reaches_the_last_step_of_the_grid(monkeypatch):
    monkeypatch.setattr(experiments, "_scaled", lambda spark, sf, **factor: factor)
    grid = {"scale_observations": ("cells", {3000, 10_000, 30_000, 100_000}), "scale_length": ("length", {300, 1000, 3000, 10_000}), "scale_rank": ("rank", {3, 10})}
    for query, (name, values) in grid.items():
        assert values <= set(experiments.QUERIES[query](None, None)[name])
