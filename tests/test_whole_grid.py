"""The benchmark queries ask for every database, generator, style, difficulty and sample."""

import pytest
from askcheck import workloads
from askcheck.functions.taxonomy import DIFFICULTIES, STYLES, SUBCATEGORIES
from askcheck.plans import agents
from askcheck.sources.tables import DATABASES
from pyspark.sql import functions as F


class Asked(Exception):
    pass


BENCHMARK = "w_overall_table w_mode_impact w_per_category w_bottlenecks w_dialogue_table w_specialised_writer"
CASCADE = "w_cascade_report w_single_judge w_cascade_without_execution w_generator_awareness w_static_dialogue w_full_simulation"


def test_sets_are_all_databases():
    assert sorted(sum(workloads.SETS.values(), [])) == sorted(DATABASES)


@pytest.mark.parametrize("name", [*BENCHMARK.split(), *CASCADE.split()])
def test_queries_ask_for_the_whole_grid(monkeypatch, name):
    seen = []

    def build(spark, generators, db_ids=None, samples=1, styles=(), difficulties=()):
        seen.extend(db_ids or DATABASES)
        assert len(generators) == 3 and samples == 3 and styles == STYLES and difficulties == DIFFICULTIES
        raise Asked

    def run(spark, sf, sets, given, modes=agents.MODES):
        assert sets == workloads.SETS and len(given) == (2 if name == "w_specialised_writer" else 8)
        workloads.questions_of(None, db_ids=sum(sets.values(), []), **workloads.GRID)

    monkeypatch.setattr(workloads.generation, "build", build)
    monkeypatch.setattr(workloads, "register_views", lambda *a: None)
    monkeypatch.setattr(workloads, "stored", lambda spark: None)
    if name in BENCHMARK:
        monkeypatch.setattr(workloads, "benchmark_run", run)
    with pytest.raises(Asked):
        getattr(workloads, name)(None, "")
    assert set(seen) == set(DATABASES)


def test_the_grid_of_questions_is_whole(spark):
    # one database alone needn't have a question of every kind
    got = workloads.questions_of(spark, 0.0, **workloads.GRID).agg(*(F.countDistinct(c) for c in ("generator", "subcategory", "style", "difficulty_asked", "sample_no")))
    assert tuple(got.first()) == (3, len(SUBCATEGORIES), len(STYLES), len(DIFFICULTIES), 3)
