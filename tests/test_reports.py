"""Reports of a stand-in benchmark against plain Python on the same judged conversations, turns and verdicts."""

from collections import defaultdict

import pytest

from askcheck import workloads
from askcheck.functions.taxonomy import TYPE_OF
from askcheck.plans import agents, measures, validation


@pytest.fixture(scope="module")
def bench(spark, sf):
    roster = [agents.BaselineAgent("oracle"), agents.BaselineAgent("noisy", 0.4, 0.8, 0.2), agents.FixedAgent("always_clarify", "clarification"), agents.FixedAgent("always_feedback", "feedback")]
    grid = dict(workloads.GRID)
    workloads.GRID.update(samples=1, styles=("formal",), generators=workloads._GENERATORS[:1], difficulties=("simple",))
    try:
        judged, turns, questions = workloads.benchmark_run(spark, sf, {"A": ["eval_items"], "B": ["geo"]}, roster)
    finally:
        workloads.GRID.update(grid)
    return judged.cache(), turns.cache(), questions


def pct(num, den):
    return round(100.0 * num / den, 4) if den else None


def plain_score(rows):
    ex = [r for r in rows if r.qtype != "unanswerable" or r.final_kind == "sql"]
    fb = [r for r in rows if r.qtype == "unanswerable" or r.final_kind == "feedback"]
    out = {"ex": pct(sum(r.correct and r.final_kind == "sql" and r.qtype != "unanswerable" for r in ex), len(ex)), "fb": pct(sum(r.correct and r.final_kind == "feedback" and r.qtype == "unanswerable" for r in fb), len(fb))}
    for name, kind in (("ex_ans", "answerable"), ("ex_amb", "ambiguous")):
        own = [r for r in rows if r.qtype == kind]
        out[name] = pct(sum(r.correct and r.final_kind == "sql" for r in own), len(own))
    return out


def grouped(rows, *by):
    out = defaultdict(list)
    for r in rows:
        out[tuple(r[c] for c in by)].append(r)
    return out


def close(a, b):
    return a == b or (a is not None and b is not None and abs(a - b) < 1e-3)


def mean(values):
    values = [v for v in values if v is not None]
    return sum(values) / len(values) if values else None


def test_overall_table(bench):
    judged = bench[0].collect()
    for r in workloads.overall_of(bench[0]).collect():
        rows = [x for x in judged if x.agent == r.agent and x["set"] == r["set"]]
        seen = [x for x in rows if x["mode"] == "predicted"]
        assert close(r.rec, pct(sum(TYPE_OF[x.predicted] == x.qtype for x in seen), len(seen))) and close(r.cls, pct(sum(x.predicted == x.subcategory for x in seen), len(seen))) and r.cls <= r.rec
        a, b = plain_score(seen), plain_score([x for x in rows if x["mode"] == "ground_truth"])
        assert all(close(x, y) for x, y in zip((r.ex, r.fb, r.ex_oracle, r.fb_oracle), (a["ex"], a["fb"], b["ex"], b["fb"]), strict=True))
    assert {len(v) for v in grouped(judged, "set", "mode", "agent").values()} == {len([x for x in judged if x["set"] == s and x["mode"] == "predicted" and x.agent == "oracle"]) for s in "AB"}


def test_mode_impact_and_categories(bench):
    judged = bench[0].collect()
    scores = {k: plain_score(v) for k, v in grouped(judged, "set", "mode", "agent").items()}
    for r in measures.mode_impact(measures.score(bench[0], "set", "mode", "agent")).collect():
        for m in ("ex_ans", "ex_amb", "fb"):
            assert close(r[m], mean(s[m] for k, s in scores.items() if k[:2] == (r["set"], r["mode"])))
    for r in measures.per_category(bench[0]).collect():
        own = grouped([x for x in judged if (x["set"], x["mode"], x.subcategory) == (r["set"], r["mode"], r.subcategory)], "agent")
        assert close(r.value, mean(plain_score(v)["fb" if r.metric == "FB" else "ex"] for v in own.values()))


def test_dialogue_table(bench):
    judged, turns, _ = bench
    about = {r.conv_id: r for r in judged.collect()}
    amb = turns.join(judged.filter("qtype = 'ambiguous'").select("conv_id", "mode"), "conv_id")
    by_conv = grouped([t for t in turns.collect() if about[t.conv_id].qtype == "ambiguous"], "conv_id")
    got = {r["mode"]: r for r in measures.dialogue_statistics(amb, "mode").collect()}
    rate = {r["mode"]: r for r in measures.air(amb, "mode").collect()}
    for mode in agents.MODES:
        talks = [sorted(v, key=lambda t: t.turn) for k, v in by_conv.items() if about[k[0]]["mode"] == mode]
        assert got[mode].n_conv == len(talks) and close(got[mode].avg_turns, mean(sum(t.role == "system" for t in v) for v in talks))
        assert close(got[mode].clar_pct, pct(sum(any(t.kind == "clarification" for t in v) for v in talks), len(talks)))
        replies = [t.relevancy for v in talks for t in v if t.relevancy]
        assert close(got[mode].relevant_pct, pct(replies.count("relevant"), len(replies)))
        ends = []
        for v in talks:
            first = next((i for i, t in enumerate(v) if t.relevancy == "relevant"), None)
            if first is not None and first + 1 < len(v) and v[first + 1].kind is not None:
                ends.append(v[first + 1].kind in ("sql", "feedback"))
        assert (rate[mode].n_conv, rate[mode].n_terminal) == (len(ends), sum(ends)) if ends else mode not in rate
        assert all(len([t for t in v if t.role == "system"]) <= 4 for v in talks)


def test_rejections(spark, sf):
    raw = workloads.stored(spark)(workloads.questions_of(spark, 0.3, ["eval_items"]), "raw")
    workloads.register_views(spark, sf)
    kept, log = validation.run_cascade(raw, validation.Context(spark), workloads.stored(spark))
    told, rows = {r.obj_id: r.subcategory for r in raw.collect()}, log.collect()
    for r in validation.rejection_report(log, raw).collect():
        own = [x for x in rows if x.stage == r.stage and r.subcategory in (None, told[x.obj_id])]
        assert (r.n_in, r.n_rejected, r.rejected_pct) == (len(own), sum(not x.kept for x in own), pct(sum(not x.kept for x in own), len(own)))
    gone = {x.obj_id: x.stage for x in rows if not x.kept}
    assert {r.obj_id for r in kept.collect()} == set(told) - set(gone)
    assert all(x.stage <= gone.get(x.obj_id, 99) for x in rows)
