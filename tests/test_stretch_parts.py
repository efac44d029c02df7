import micro

from sparkgraphs.check import certificates as cert
from sparkgraphs.model.graph import from_arcs


def test_stretch_parts_sources_only_where_a_step_is_large(spark, monkeypatch):
    """All sources start together (there was a block for each 64 of a million vertices); small steps are parted, with the same counts."""
    g = micro.cycle(spark, 40)
    h = from_arcs(g.half().where("NOT (src = 4 AND dst = 5) AND src <> 20"), g.vertices)
    kept = []
    keep = cert.Rounds.keep
    monkeypatch.setattr(cert.Rounds, "keep", lambda *a, **k: kept.append(1) or keep(*a, **k))
    assert cert.stretch(g, h, g.half(), 3, 1 << 20) == 2
    assert len(kept) < 20
    full = from_arcs(g.half().where("NOT (src = 4 AND dst = 5)"), g.vertices)
    assert [cert.stretch(g, full, g.half(), limit, most) for limit, most in ((38, 1 << 20), (39, 1 << 20), (3, 30), (39, 3))] == [1, 0, 1, 0]
