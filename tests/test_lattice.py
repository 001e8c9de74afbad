import pytest

from tideline import queries as Q


@pytest.mark.parametrize("name", ["fusion_rounds", "work_efficiency", "astar_lazy"])
def test_queries_on_long_paths_run_on_the_fine_lattice(monkeypatch, name):
    asked = []

    def road(s, d, days=28, *rest):
        asked.append(days)
        raise LookupError

    monkeypatch.setattr(Q.G, "g_road", road)
    with pytest.raises(LookupError):
        Q.entries()[0][name](None, "")
    assert asked and max(asked) <= 28
