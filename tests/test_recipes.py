"""The recipes: every stage and every ablation changes what comes out."""

import pytest

from qacurate.queries import REGISTRY

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def collected(spark):
    kept = {}

    def get(name):
        if name not in kept:
            kept[name] = REGISTRY.queries[name](spark, SF).collect()
        return kept[name]

    return get


@pytest.mark.parametrize(("name", "by", "stages"), [("textbook_recipe", "subject", ["pairs", "dedup", "filter", "decontaminate"]), ("mixture_recipe", "dataset", ["raw", "dedup", "decontaminate", "selection", "length"])])
def test_every_stage_removes_rows(collected, name, by, stages):
    total = sorted((r.stage_no, r.stage, r.n) for r in collected(name) if r[by] == "total")
    assert [s for _, s, _ in total] == stages
    assert all(a[2] > b[2] > 0 for a, b in zip(total, total[1:], strict=False))


def test_sources_that_are_done_only_lose_by_length(collected):
    textbook = [r.n for r in sorted(collected("mixture_recipe")) if r.dataset == "textbook"]
    assert len(set(textbook)) == 1
    assert not any(r.dataset == "C" for r in collected("mixture_recipe"))


def test_every_ablation_changes_the_outcome(collected):
    rows = {r.variant: r for r in collected("recipe_ablation")}
    full = rows["full"]
    assert rows["without decontamination"].n > full.n
    assert rows["without supplement"].n_lacking > full.n_lacking
    assert rows["without refinement"].answer_words < rows["without supplement"].answer_words
    assert rows["weaker refiner"].answer_words != full.answer_words


def test_leak_removal_is_seen_in_every_source(collected):
    rows = collected("decontam_before_after")
    assert {r.dataset for r in rows} == {"A", "B"} and all(0 < r.n_leaked < r.n_before and r.score_before != r.score_after for r in rows)


def test_selections_differ_at_equal_size(collected):
    sizes = {(r.dataset, r.strategy): r.n for r in collected("strategy_sizes")}
    for source in ("A", "B", "textbook"):
        assert sizes[source, "difficulty"] == sizes[source, "length"] == sizes[source, "random"] < sizes[source, "all"]
    for r in collected("strategy_overlap"):
        assert r.n < sizes[r.dataset, "difficulty"] or "all" in (r.s1, r.s2)
    bands = [r.mean for r in collected("difficulty_scores")]
    assert min(bands) < 1 and max(bands) > 9
