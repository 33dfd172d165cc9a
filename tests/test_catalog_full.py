"""The wide views are searched in full, not by single parents or not at all."""

from types import SimpleNamespace

from parsieve.plans import catalog


def test_wide_views_are_searched_in_full(monkeypatch):
    seen = []
    monkeypatch.setattr(catalog, "load", lambda spark, sf, view: view)
    monkeypatch.setattr(catalog.lookup, "flat", lambda mps: mps)
    monkeypatch.setattr(catalog, "find_parent_sets", lambda view, **o: seen.append((view, o.get("max_parents"))) or SimpleNamespace(mps=None))
    for name in ("mps_emb64_capped", "mps_emb16", "mps_star20"):
        catalog.queries()[name](None, "")
    assert seen == [("emb64", 3), ("emb16", None), ("star20", None)]
