"""What the workloads report, on the smallest tables: the behaviour that the measures must show."""

import pytest

from proxigraph.plans import registry, workloads


@pytest.fixture(autouse=True)
def short(monkeypatch):
    monkeypatch.setattr(workloads, "WIDTHS", (10, 80))
    monkeypatch.setattr(workloads, "EPS", (0.1, None))
    monkeypatch.setattr(workloads, "LIST_ITERATIONS", 2)
    for name, kw in {"alpha": {"degree": 16, "width": 32}, "layered": {"m": 8, "width": 32}, "tree_mst": {"trees": 6, "leaf": 60}, "descent": {"trees": 3, "leaf": 60, "k": 15, "degree": 24}}.items():
        monkeypatch.setitem(workloads.BUILDS, name, kw)


def run(spark, small_dir, name):
    return [r.asDict() for r in registry.queries()[name](spark, small_dir).collect()]


def by(rows, metric):
    return {(r["method"], tuple(sorted(r["params"].items()))): r["value"] for r in rows if r["metric"] == metric}


def test_curves(spark, small_dir):
    rows = run(spark, small_dir, "w01_curves_qps")
    assert {r["method"].split("/")[0] for r in rows} == {*workloads.BUILDS, "inverted"} and {r["method"].split("/")[1] for r in rows} == {"emb", "doc", "web"}
    best = {}
    for r in rows:
        best[r["method"]] = max(best.get(r["method"], 0), r["recall"])
        assert r["qps"] > 0
    assert all(v >= 0.9 for v in best.values())
    wide = {r["method"]: r["recall"] for r in rows if r["params"].get("width") == "80" and "eps" not in r["params"]}
    slim = {r["method"]: r["recall"] for r in rows if r["params"].get("width") == "10" and "eps" not in r["params"]}
    assert all(wide[m] >= slim[m] for m in wide) and any(r["front"] for r in rows)


def test_old_and_new(spark, small_dir):
    rows = run(spark, small_dir, "w06_old_and_new")
    assert {r["method"] for r in rows} == set(workloads.BUILDS)
    for r in rows:
        if r["variant"] == "original":
            assert r["threads"] == 1 and abs(r["over_original"] - 1) < 1e-9
    assert {r["threads"] for r in rows if r["variant"] == "ours"} == {1, 2, 4}


def test_other_distribution_and_ranges(spark, small_dir):
    rows = run(spark, small_dir, "w08_out_of_distribution")
    assert {r["queries"] for r in rows} == {"same", "other"} and {r["method"].split("/")[1] for r in rows} == {"emb", "doc"}
    assert all(r["recall"] >= 0.8 and r["comps_slowdown"] > 0 for r in rows if r["reached"])
    ranges = {(r["queries"], r["variant"]): r for r in run(spark, small_dir, "w09_range_queries")}
    assert {q for q, _ in ranges} == {"near copies", "passages"}
    assert ranges["near copies", "flood"]["range_recall"] >= ranges["near copies", "beam"]["range_recall"]


def test_doubling_is_as_good_as_sequential(spark, small_dir):
    got = by(run(spark, small_dir, "w12_doubling_and_sequential"), "recall")
    for carrier in ("emb", "doc"):
        one, two = (got[f"{k}/{carrier}", (("width", "100"),)] for k in ("doubling", "sequential"))
        assert one >= two - 0.01 and got[f"one shot/{carrier}", (("width", "100"),)] < 0.5


def test_visited_widths_and_bytes(spark, small_dir):
    rows = run(spark, small_dir, "w15_visited_tables")
    recall, comps = by(rows, "recall"), by(rows, "dist_comps")
    for w in ("20", "50"):
        key = {v: ("alpha", (("visited", v), ("width", w))) for v in ("exact", "lossy", "seen")}
        assert recall[key["exact"]] == recall[key["lossy"]] == recall[key["seen"]]
        assert comps[key["seen"]] <= comps[key["exact"]] <= comps[key["lossy"]]
    both = by(run(spark, small_dir, "w16_width_and_eps"), "dist_comps")
    assert both["alpha", (("eps", "0.0"), ("width", "50"))] <= both["alpha", (("eps", "None"), ("width", "50"))]
    bytes_ = by(run(spark, small_dir, "w10_bytes_and_floats"), "recall")
    assert abs(bytes_["byte", (("width", "100"),)] - bytes_["float", (("width", "100"),)]) < 0.1


def test_lists_hashes_trees_and_rounds(spark, small_dir):
    lists = by(run(spark, small_dir, "w17_list_plateau"), "recall")
    emb = [v for (m, p), v in sorted(lists.items(), key=lambda x: int(x[0][1][0][1])) if m == "emb"]
    assert emb == sorted(emb) and emb[-1] == 1.0
    hashes = by(run(spark, small_dir, "w18_hash_baseline"), "recall")
    assert max(v for (m, _), v in hashes.items() if m == "sign") < 0.9
    mst = by(run(spark, small_dir, "w13_restricted_mst"), "recall")
    assert mst["near 10", (("width", "100"),)] >= mst["near None", (("width", "100"),)] - 0.05
    assert all(r["value"] >= 0.5 for r in run(spark, small_dir, "w14_descent_caps") if r["metric"] == "recall")
    assert all(r["value"] > 0 for r in run(spark, small_dir, "w20_prompt_retrieval"))
    prints = run(spark, small_dir, "w11_determinism")
    assert len({(r["method"], r["print"], r["edges"]) for r in prints}) == len(workloads.BUILDS)
