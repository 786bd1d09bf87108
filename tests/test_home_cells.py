"""Searches from few leaves make the cells of these alone, and they are those of all cells."""

from floorwalk.operators import labels
from floorwalk.operators.range import placed_points
from floorwalk.plans import border
from floorwalk.sources import venue as V


def test_cells_of_few_leaves(spark, small, monkeypatch):
    base = V.build_venue(spark, small)
    venue = V.Venue(spark, small, base.floors, base.variant, base.partitions, base.doors, base.moves)
    tree = border.build_border_tree(venue)
    placed = placed_points(base, V.query_points(base)).where("qid < 2")
    homes = labels._homes(tree, placed)
    monkeypatch.setattr(border, "FEW", 0)
    few = {kind: {tuple(r) for r in tree.home_cells(kind, homes).collect()} for kind in ("deep_out", "deep_in", "leaf_pairs")}
    found = {tuple(r) for r in labels.tree_labels(venue, placed, None, False, True).collect()}
    assert "deep_out" not in tree.__dict__ and "leaf_pairs" not in tree.__dict__
    for kind, rows in few.items():
        assert rows == {tuple(r) for r in getattr(tree, kind).join(homes, "leaf", "left_semi").collect()} and rows
    assert found == {tuple(r) for r in labels.graph_labels(venue, placed).collect()}
