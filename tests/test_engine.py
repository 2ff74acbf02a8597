"""Formulas, worked examples and properties of the engine."""

import glob
import itertools
import json
import os

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from narrative_engine import registry
from narrative_engine.fixtures import CLAUSES, STYLE_PARTS
from narrative_engine.operators import attribution as at
from narrative_engine.operators import explanation as ex
from narrative_engine.operators import grading as gr
from narrative_engine.operators import samples
from narrative_engine.operators import writing as wr
from narrative_engine.operators.claims import Reading
from narrative_engine.plans import experiments as xp
from narrative_engine.plans.pipeline import NarrativePipeline
from narrative_engine.sources import formats
from narrative_engine.settings import PUBLISHED_CONFUSION, SET_ASIDE, TECHNIQUES
from narrative_engine.staging import release, shared_dir, staged

EXPL = "array<struct<feature:string,value:string,value_num:double,contribution:double>>"
HOUSE = [("living area", "2090", 2090.0, 16382.07), ("material rating", "5", 5.0, -10203.0)]


def read(spark, expl, text, reading=Reading(), means=None):
    df = spark.createDataFrame([(expl, text)], f"expl {EXPL}, text string")
    usual = F.create_map(*[F.lit(v) for kv in means.items() for v in kv]) if means else None
    return df.select(gr.claims(F.col("text"), F.col("expl"), reading, usual).alias("r"))


def judge(spark, expl, text, policy=gr.AccuracyPolicy(), complete=gr.CompletenessPolicy(), reading=None, means=None):
    rows = read(spark, expl, text, reading or Reading(policy.tolerance), means)
    return tuple(rows.select(gr.accuracy(F.col("r"), policy), gr.completeness(F.col("r"), complete)).first())


def test_conciseness_boundaries(spark):
    df = spark.createDataFrame([(30, 3), (45, 3), (60, 3), (61, 3), (5, 0), (0, 3)], "l int, f int")
    got = [r[0] for r in df.select(gr.conciseness(F.col("l"), F.col("f"), F.lit(10.0))).collect()]
    assert got == [4.0, 2.0, 0.0, 0.0, 0.0, 4.0]


def test_conciseness_never_rises(spark):
    df = spark.range(0, 80).select(gr.conciseness(F.col("id"), F.lit(3), F.lit(10.0)).alias("s"))
    got = [r[0] for r in df.collect()]
    assert got == sorted(got, reverse=True)


def test_total_grade_range(spark):
    df = spark.range(1).select(gr.total_grade(F.lit(1), F.lit(2), F.lit(4), F.lit(4.0)), gr.total_grade(F.lit(0), F.lit(0), F.lit(0), F.lit(0.0)))
    assert tuple(df.first()) == (16.0, 0.0)


def test_published_totals_agree(spark):
    assert xp.published_totals(spark).where("NOT agrees").count() == 0


def test_published_agreement(spark):
    got = {r["metric"]: (r["n"], r["agreement"]) for r in xp.agreement(xp.published_confusion(spark)).collect()}
    assert got == {"accuracy": (50, 0.96), "completeness": (50, 0.96)}
    assert sum(n for m, h, _, n in PUBLISHED_CONFUSION if m == "accuracy" and h == 0) == 16


def test_alert_for_every_draw_vector(spark):
    rows = [(list(map(float, v)),) for v in itertools.product((0, 1, 2), repeat=5)]
    df = spark.createDataFrame(rows, "d array<double>")
    for r in df.select("d", gr.consistency_alert(F.col("d")).alias("alert"), gr.mean_draw(F.col("d")).alias("m")).collect():
        assert r["alert"] == (max(r["d"].count(x) for x in set(r["d"])) < 4)
        assert abs(r["m"] - sum(r["d"]) / 5) < 1e-12


@pytest.mark.parametrize("said,ok", [("16,000", 1), ("$16,000", 1), ("16382.07", 1), ("16,382.07", 1), ("32764", 0), ("14,000", 0), ("160,00", 0)])
def test_tolerance(spark, said, ok):
    assert judge(spark, HOUSE, f"The living area of 2090 raises the price by about {said}.")[0] == ok


FLAT = [("size", "1203", 1203.0, 10203.0), ("upper floor", "0", 0.0, -4782.0)]


@pytest.mark.parametrize("text", [
    "Its size of 1,203 feet pushed up the guess by $10,203, and an upper floor of 0 feet took from it $4,782.",
    "A size of 1203 adds to the guess by around $10,200, while the lack of an upper floor lowers it by some $4,700.",
])
def test_precise_and_casual_wordings_are_accurate_and_complete(spark, text):
    assert judge(spark, FLAT, text) == (1, 2)


def test_names_inside_longer_names(spark):
    rates = [("interest rate", "7", 7.0, -3.0), ("rate", "1", 1.0, 5.0)]
    assert judge(spark, rates, "An interest rate of 7 lowers the price by 3. A rate of 1 raises it by 5.") == (1, 2)
    assert judge(spark, rates, "An interest rate of 7 raises the price by 3. A rate of 1 raises it by 5.") == (0, 2)
    assert judge(spark, rates, "An interest rate of 7 lowers the price by 3.") == (1, 0)
    assert judge(spark, [("rate", "1", 1.0, 5.0)], "Corporate debt of 9 matters. A rate of 1 raises it.")[0] == 0


def test_absence_tells_a_value(spark):
    support = [("family support", "no", None, -0.4)]
    assert judge(spark, support, "The lack of family support makes passing less likely.") == (1, 2)
    assert judge(spark, support, "Without family support, passing is less likely.") == (1, 2)
    assert judge(spark, support, "Family support (yes) makes passing less likely.")[0] == 0
    assert judge(spark, [("family support", "yes", None, 0.4)], "No family support makes passing more likely.")[0] == 0
    assert judge(spark, support, "With little family support, one is more likely to fail.") == (1, 1)


def test_invented_features_and_numbers(spark):
    assert judge(spark, HOUSE, "The garage with 3 doors raised the price by 99999. The living area of 2090 raised it.")[0] == 0
    assert judge(spark, HOUSE, "The garage raised the price. The living area of 2090 raised it.")[0] == 1
    assert judge(spark, HOUSE, "The garage raised the price. The living area of 2090 raised it.", reading=Reading(others=("garage",)))[0] == 0
    assert judge(spark, HOUSE, "The garage with 3 doors raised the price by 99999.", policy=gr.AccuracyPolicy(invented_is_error=False))[0] == 1


def test_numbers_belong_to_their_item_of_a_list(spark):
    marks = [("math", "5", 5.0, 0.1), ("reading", "7", 7.0, 0.2)]
    assert judge(spark, marks, "The scores of 5 in math and 7 in reading make passing more likely.") == (1, 2)
    assert judge(spark, marks, "The scores of 7 in math and 5 in reading make passing more likely.")[0] == 0
    assert judge(spark, marks, "math 5 raises the odds by 0.10, reading 7 raises the odds by 0.20.", complete=gr.CompletenessPolicy(require_contrib=True)) == (1, 2)


def test_comparisons_against_usual_values(spark):
    size = [("metadata size", "120", 120.0, -0.3)]
    text = "The smaller metadata size makes malice less likely."
    assert judge(spark, size, text) == (1, 1)
    assert judge(spark, size, text, means={"metadata size": 200.0})[0] == 1
    assert judge(spark, size, text, means={"metadata size": 90.0})[0] == 0
    assert read(spark, size, text).first()["r"]["found"][0]["value_state"] == "comparative"
    assert judge(spark, size, "The metadata size is larger than usual, which makes malice less likely.", means={"metadata size": 200.0})[0] == 0


def test_aliases_and_steps(spark):
    reading = Reading(aliases={"living area": ("floor space",)})
    assert judge(spark, HOUSE[:1], "The floor space of 2090 raises the price.", reading=reading) == (1, 2)
    row = read(spark, HOUSE, "The living area of 2090 raises the price by 16,000.").select(gr.accuracy_steps(F.col("r")).alias("s"), gr.checklist(F.col("r")).alias("k")).first()
    assert row["s"] == ["living area: value exact, contribution approx, direction right", "material rating: value absent, contribution absent, direction untold"]
    assert [(k["listed"], k["done"]) for k in row["k"]] == [(True, True), (False, False)]


def test_direction_of_two_positive_features(spark):
    expl = [("cap", "flat", None, 0.15), ("stalk", "broad", None, 0.06)]
    assert judge(spark, expl, "The cap (flat) and the stalk (broad) make harm more likely.") == (1, 2)
    assert judge(spark, expl, "The cap (flat) and the stalk (broad) make harm less likely.")[0] == 0
    assert judge(spark, expl, "The lack of a cap is odd.", policy=gr.AccuracyPolicy.asked_yes_no())[0] == 1


SAMPLE = ("(size, 1203, 10203.00), (upper floor, 0, -4782.00)", "Hello! The size of 1203 increased the guess by $10,203. The upper floor of 0 decreased the guess by $4,782. Bye!")


def test_samples_become_exemplars():
    e = samples.derived("1", *SAMPLE)
    assert (e.lead, e.joiner, e.tail, e.omits) == ("Hello! ", ". ", ". Bye!", False)
    assert e.clauses[1] == samples.Clause("The {f} of {v} {d} the guess by ${t}", "increased", "decreased")
    bare = samples.derived("2", "size, 120, -120", "The model cut its guess: a size of 120 lowered it by 120.")
    assert (bare.lead, bare.clauses[0].slots, bare.clauses[0].up) == ("The model cut its guess: ", "a {f} of {v} {d} it by {r}", "raised")
    with pytest.raises(ValueError):
        samples.derived("3", "size, 120, -120", "Nothing to see.")


def test_authored_styles_are_read_as_they_were_written(study):
    """Narratives of other entries in a style read from one narrative are those its author would write."""
    hand = study.hand.collect()
    exemplars = {r["style"]: r["hand"] for r in study.styles.collect()}
    for style, own in CLAUSES.items():
        lead, up, down, joiner, tail = STYLE_PARTS[style]
        assert len(exemplars[style]) == 5 and [e["omits"] for e in exemplars[style]] == [f == "omits" for _, f in own]
        for e, (slots, _) in zip(exemplars[style], own):
            assert (e["joiner"], e["tail"]) == (joiner, tail)
            for k, c in enumerate(e["clauses"]):
                for phrase, whole in ((c["up"], up), (c["down"], down)):
                    assert (e["lead"] if k == 0 else "") + c["c"].replace("{d}", phrase) == (lead if k == 0 else "") + slots.replace("{d}", whole), (style, c)
    assert len(hand) == 45


def test_pipeline_from_samples(spark):
    pipe = NarrativePipeline(2, "The model guesses prices", [SAMPLE])
    attr = [("size", "900", 900.0, -2500.4), ("upper floor", "3", 3.0, 70.0), ("door", "red", None, 1.0)]
    df = spark.createDataFrame([("a", attr)], f"row_id string, attr {EXPL}")
    assert dict(map(tuple, pipe.to_mapping(df).collect())) == {"a": "Hello! The size of 900 decreased the guess by $2,500. The upper floor of 3 increased the guess by $70. Bye!"}
    graded = pipe.graded(df).first()
    assert (graded["a"], graded["c"]) == (1, 2) and graded["f"] >= 3
    prompt = pipe.prompts(df).first()["prompt"]
    assert SAMPLE[0] in prompt and SAMPLE[1] in prompt and "The model guesses prices" in prompt and "{f}" not in prompt
    assert pipe.guarded(df, 99.0).first()["shown"].startswith("size")


def test_new_application(spark, sf):
    app = registry._new_application(spark, sf)
    with pytest.raises(ValueError):
        app.shown()
    app.narrated(registry.day_author)
    assert len(app.pipeline.samples) == 5 and app.shown().where("shown LIKE 'Today%'").count() == app.explained.count()


def test_prompts_hold_the_samples(study):
    row = wr.build_prompt(study.prompts().where("technique = 8")).first()
    assert len(row["exemplars"]) == 4 and all(e["text"] in row["prompt"] and e["expl_text"] in row["prompt"] for e in row["exemplars"])
    assert "{f}" not in row["prompt"] and "{v}" not in row["prompt"]


def test_other_kinds_of_explanation(spark):
    df = spark.createDataFrame([("(rain, stay in), (sun, go out)", "If there's RAIN, stay in.")], "e string, text string")
    kind = ex.EXPLANATION_KINDS["rules"]
    row = df.select(ex.kind_completeness("rules", kind.parse(F.col("e")), F.col("text")).alias("c"), kind.serialize(kind.parse(F.col("e"))).alias("back")).first()
    assert (row["c"], row["back"]) == (1, "(rain, stay in), (sun, go out)")


def test_more_metrics_and_a_judge_that_errs(study):
    rows = study.prompts().where("technique = 8")
    extra = {"short": gr.Metric(lambda df: F.when(F.col("n_words") < 20, 1.0).otherwise(0.0), 2.0)}
    got = gr.graded(rows, study.refs, metrics=extra, judge=gr.Judge(error=0.2), key=("style", "row_id")).select("a", "c", "f", "s", "short", "total", "alert").collect()
    assert all(abs(r["total"] - (4 * r["a"] + 2 * r["c"] + r["f"] + r["s"] + 2 * r["short"])) < 1e-9 for r in got) and {r["alert"] for r in got} == {True, False}
    assert any(0 < r["a"] < 1 for r in got)


def test_alignment_counts_chunks(spark):
    rows = [("1", "the cat sat on the mat", "the cat sat on the mat"), ("2", "on the mat sat the cat", "the cat sat on the mat"), ("3", "x", "y"), ("4", "", "y")]
    got = {r["id"]: r for r in gr.unigram_alignment(spark.createDataFrame(rows, "id string, text string, reference string")).collect()}
    assert (got["1"]["n_match"], got["1"]["n_chunks"]) == (6, 1) and abs(got["1"]["score"] - (1 - 0.5 / 216)) < 1e-12
    assert got["2"]["n_match"] == 6 and got["2"]["n_chunks"] > 2 and got["2"]["score"] < got["1"]["score"] and got["3"]["score"] == got["4"]["score"] == 0.0


def test_logistic_and_sums(spark, sf):
    assert registry.additivity(spark, sf).first()["n_off"] == 0
    assert registry.logistic(spark, sf).agg(F.sum("n")).first()[0] > 0


def test_coalitions_of_a_score_that_is_not_linear(spark):
    """Exact averages against a direct enumeration of all orders, on three background rows."""
    score = lambda x: x[:, 0] * x[:, 1] + np.maximum(x[:, 2], 0.0)
    rows, background = np.array([[1.0, 2.0, -1.0], [0.5, -3.0, 2.0]]), np.array([[0.0, 1.0, 1.0], [2.0, 0.0, -2.0], [1.0, 1.0, 0.0]])
    df = spark.createDataFrame([(str(k), *map(float, r)) for k, r in enumerate(rows)], "row_id string, a double, b double, c double")
    got = {r["row_id"]: r["contributions"] for r in at.attribute_coalition(df, ["a", "b", "c"], score, background).collect()}
    for k, x in enumerate(rows):
        want = np.zeros(3)
        for order in itertools.permutations(range(3)):
            for b in background:
                now = b.copy()
                for i in order:
                    before = score(now[None])[0]
                    now[i] = x[i]
                    want[i] += (score(now[None])[0] - before) / 18
        assert np.allclose(got[str(k)], want)
    sampled = {r["row_id"]: r["contributions"] for r in at.attribute_sampled(df, ["a", "b", "c"], score, background, m=4000).collect()}
    assert all(np.allclose(sampled[k], got[k], atol=0.15) for k in got)


def test_completeness_levels(spark):
    full = "The living area of 2090 raises the price by 16382.07. The material rating of 5 lowers the price by 10203."
    assert judge(spark, HOUSE, full) == (1, 2)
    assert judge(spark, HOUSE, full, complete=gr.CompletenessPolicy(require_contrib=True)) == (1, 2)
    bare = "The living area of 2090 raises the price. The material rating of 5 lowers the price."
    assert judge(spark, HOUSE, bare) == (1, 2)
    assert judge(spark, HOUSE, bare, complete=gr.CompletenessPolicy(require_contrib=True)) == (1, 1)
    assert judge(spark, HOUSE, "The living area of 2090 raises the price by 16382.07.") == (1, 0)
    assert judge(spark, HOUSE, "The living area raises the price. The material rating of 5 lowers the price.") == (1, 1)
    assert judge(spark, HOUSE, bare, policy=gr.AccuracyPolicy(levels=3))[0] == 2
    assert judge(spark, HOUSE, "The living area raises the price.", policy=gr.AccuracyPolicy.plain())[0] == 0


def test_serialise_and_parse(spark):
    df = spark.createDataFrame([([("a, b", "x", None, 1.5), ("c", "-2", -2.0, -0.25)],)], f"expl {EXPL}")
    t = df.select(ex.serialize_explanation("expl").alias("t"))
    assert t.first()[0] == "(a, b, x, 1.50), (c, -2, -0.25)"
    back = t.select(ex.parse_explanation("t").alias("p")).first()["p"]
    assert [(p["feature"], p["value"], p["contribution"]) for p in back] == [("a, b", "x", 1.5), ("c", "-2", -0.25)]
    bare = spark.createDataFrame([("size, 120, -120",)], "t string").select(ex.parse_explanation("t").alias("p")).first()["p"]
    assert [(p["feature"], p["value_num"], p["contribution"]) for p in bare] == [("size", 120.0, -120.0)]


def test_top_is_free_of_order(spark):
    attr = [("a", "1", 1.0, 2.0), ("b", "1", 1.0, -3.0), ("c", "1", 1.0, 2.0), ("d", "1", 1.0, 0.5)]
    df = spark.createDataFrame([(p,) for p in map(list, itertools.permutations(attr))], f"attr {EXPL}")
    assert {tuple(x["feature"] for x in r["expl"]) for r in ex.top_contributions(df).collect()} == {("b", "a", "c")}


def test_lmax_is_nine_tenths_of_the_longest(spark):
    df = spark.createDataFrame([("s", "one two three four", HOUSE), ("s", "one two", HOUSE)], f"style string, text string, expl {EXPL}")
    assert abs(gr.derive_longest(df).first()["longest"] - 0.9 * 2) < 1e-12


@pytest.fixture(scope="module")
def study(spark, sf):
    return registry.study(spark, sf)


@pytest.fixture(scope="module")
def grid(study):
    return staged(study.grid().drop("claims"))


def test_grid_shape_and_counts(study, grid):
    assert grid.count() == grid.select("style", "row_id", "technique").distinct().count()
    wrong = study.prompts().where("size(exemplars) <> least(h, size(hand)) + least(b, size(boot))")
    assert wrong.count() == 0 and {t[0] for t in TECHNIQUES} == {r[0] for r in grid.select("technique").distinct().collect()}


def test_evaluation_never_sees_exemplar_entries(study):
    used = study.entries.where(f"place <= {SET_ASIDE}").select("style", "row_id")
    assert study.prompts().join(used, ["style", "row_id"]).count() == 0


def test_bootstrapped_exemplars_pass_the_gate(study):
    assert study.accepted.where("a < 1 OR c < 2 OR f < 4 OR s < 3.5").count() == 0


def test_few_shot_beats_zero_shot_and_costs_correctness(grid):
    by = {r["technique"]: r for r in xp.technique_scores(grid).collect()}
    assert by[8]["total"] > by[1]["total"] and by[8]["fluency"] > by[1]["fluency"] and by[8]["conciseness"] > by[1]["conciseness"]
    assert by[6]["accuracy"] < by[1]["accuracy"] and by[6]["completeness"] < by[1]["completeness"]
    assert by[8]["accuracy"] + by[8]["completeness"] >= by[4]["accuracy"] + by[4]["completeness"]


def test_guard_shows_nothing_under_the_threshold(grid):
    rows = gr.guarded(grid, 14.0)
    assert rows.where("NOT rejected AND total < 14").count() == 0
    assert rows.where(F.col("rejected") & (F.col("shown") == F.col("text"))).count() == 0


def test_noise_is_found(spark, study):
    rows = gr.graded(wr.noisy(study.prompts().where("technique = 1")), study.refs)
    assert rows.where("mistake AND a = 1").count() == 0 and rows.where("NOT mistake AND a = 0").count() == 0


def test_replay_and_backend(spark, study):
    class Upper:
        def complete(self, prompts):
            return [p[:5].upper() for p in prompts]

    rows = wr.build_prompt(study.prompts().where("technique = 1")).limit(5)
    cache = wr.completed(wr.plan_calls(rows), Upper)
    assert wr.replayed(rows, cache).where("text IS NULL").count() == 0


def test_bootstrapped_exemplars_are_new(study):
    hand = study.hand.select("style", "row_id", "text")
    pool = study.pool()
    assert pool.join(hand, ["style", "row_id"]).count() == 0 and pool.select("style", "one.text").distinct().count() == pool.count()
    short = {r["style"]: r for r in study.short_styles().collect()}
    assert all(r["reached"] == (r["in_pool"] == 5) and r["in_pool"] <= r["accepted"] <= r["candidates"] for r in short.values())


def test_staged_tables_can_go(spark):
    df = staged(spark.range(5))
    folder = df.inputFiles()[0].split("file:")[-1].rsplit("/", 1)[0]
    folder = "/" + folder.lstrip("/")
    assert os.path.isdir(folder) and shared_dir(spark).split(":")[-1].rstrip("/").lstrip("/") in folder
    release(df)
    assert not os.path.isdir(folder)


def test_remote_backend(tmp_path):
    import http.server
    import json
    import threading

    calls = []

    class Model(http.server.BaseHTTPRequestHandler):
        def do_POST(self):
            got = json.loads(self.rfile.read(int(self.headers["Content-Length"])))["prompts"]
            calls.append(len(got))
            if len(calls) == 1:
                return self.send_error(503)
            body = json.dumps({"texts": [p.upper() for p in got]}).encode()
            self.send_response(200)
            self.send_header("Content-Length", str(len(body)))
            self.end_headers()
            self.wfile.write(body)

        def log_message(self, *_):
            pass

    server = http.server.HTTPServer(("127.0.0.1", 0), Model)
    threading.Thread(target=server.serve_forever, daemon=True).start()
    backend = wr.RemoteBackend(f"http://127.0.0.1:{server.server_port}", batch=2, pause=0.01)
    assert backend.complete(["a", "b", "c"]) == ["A", "B", "C"] and calls == [2, 2, 1]
    server.shutdown()


def test_budget_guard(spark, sf, study):
    costs = xp.prompt_costs(study.prompts())
    assert xp.BudgetGuard(1000.0).check(costs) > 0
    with pytest.raises(RuntimeError):
        xp.BudgetGuard(0.0).check(costs)


def test_plans_push_down_and_stay_in_the_jvm(spark, sf, capsys):
    registry.queries()["pushdown_range"](spark, sf).explain("formatted")
    assert "PushedFilters: [" in capsys.readouterr().out
    registry.narrated(spark, sf, "basket").explain()
    plan = capsys.readouterr().out
    assert "Python" not in plan and "Arrow" not in plan and "CartesianProduct" not in plan


def test_prose_is_read_once_for_each_explanation(spark, sf, capsys):
    rows = xp.explained(registry.features(spark, sf, "basket"), "basket").select("row_id", "expl")
    rows = staged(rows.limit(40).unionByName(rows.limit(40).withColumn("row_id", F.concat(F.lit("again "), "row_id"))))
    by_row = registry.judged(rows.withColumn("text", registry.wr.zero_shot(F.col("expl"))))
    columns = ["expl", "text", "a", "c", "n_words", "s", "total", "rejected"]
    once = registry.told_once(rows)
    assert sorted(map(repr, once.select(columns).collect())) == sorted(map(repr, by_row.select(columns).collect()))
    assert once.select("row_id").distinct().count() == rows.count() == 80
    capsys.readouterr()
    registry.narrated(spark, sf, "basket").explain()  # the narratives come from a table; words aren't counted row by row
    assert "regexp_extract_all" not in capsys.readouterr().out


def test_whole_grid_counts_equal_narratives(study):
    rows = study.entries.where(f"place > {SET_ASIDE} AND place <= {SET_ASIDE + 3}")
    rows = staged(rows.unionByName(rows))  # every row twice: the same narratives, counted twice
    whole = staged(study.whole_grid(rows))
    got = sorted(map(tuple, xp.technique_scores(whole, "n").collect()))
    assert got == sorted(map(tuple, xp.technique_scores(study.grid(rows)).collect())) and len(got) == len(TECHNIQUES)
    assert whole.count() < sum(r[4] for r in got) == rows.count() * len(TECHNIQUES)


def test_whole_grid_reads_each_narrative_once(study, monkeypatch):
    read = []
    graded = gr.graded
    monkeypatch.setattr(gr, "graded", lambda df, styles, **more: read.append(staged(df)) or graded(read[-1], styles, **more))
    study.whole_grid(study.entries.where(f"place > {SET_ASIDE}"))
    assert read[0].count() == read[0].select("style", "expl", "text").distinct().count()


def test_texts_in_bulk_are_read_as_one_by_one(spark, study):
    odd = [
        "", "No.  lack of any ship lag; the parts of 12 raises 3 and about lowers 1,234,567 by 7!", "line count, 12, and balance: higher  parts without a raise, region ASIA more likely to fail by 12%",
        "While priority of 1-URGENT (7) is larger than usual but roughly -4 by 3.5.\nÉté — İ", "status status by by 7 no yes yes 0 . , ; reduces | @u@ $12", "1,2,345 cuts the count. Larger line count pushed up 12; lower than usual",
    ]
    expl = [[("parts", "12", 12.0, 7.0), ("line count", "none", None, -3.5)], [("count", "1,234,567", 1234567.0, None), ("priority", "1-URGENT", None, 0.0), ("ship lag", "0", 0.0, -4.0)], [("status", "yes", None, -12.0), ("region", None, None, 1.0)], []]
    kind = "style string, text string, expl array<struct<feature:string,value:string,value_num:double,contribution:double>>"
    rows = spark.createDataFrame([("basket_a", t, e) for t in odd for e in expl], kind)
    some = study.prompts(study.entries.where(f"place > {SET_ASIDE} AND place <= {SET_ASIDE + 4}")).select("style", "text", F.transform("expl", lambda x: F.struct(*[x[c].alias(c) for c in ("feature", "value", "value_num", "contribution")])).alias("expl"))
    rows = staged(rows.unionByName(some))
    for reading in (Reading(), Reading(aliases={"parts": ("pieces", "count")}, others=("balance", "region"), up=("no raise",))):
        one, bulk = (gr.graded(rows, study.refs, reading=reading, bulk=b).select(F.to_json(F.struct("*")).alias("row")) for b in (False, True))
        columns = lambda df: sorted(json.dumps(json.loads(r["row"]), sort_keys=True) for r in df.collect())
        assert columns(one) == columns(bulk)


@pytest.mark.parametrize("name,read", [("published_agreement", {"labels", "documents"}), ("published_totals", {"documents"}), ("source_fixture", {"orders"})])
def test_tables_are_read(spark, sf, monkeypatch, name, read):
    seen = set()
    for module in (registry, formats):
        monkeypatch.setattr(module, "table", lambda s, f, t: seen.add(t) or registry.features.__globals__["table"](s, f, t))
    rows = registry.queries()[name](spark, sf)
    assert seen == read and rows.count() > 0


@pytest.fixture(scope="module")
def one_study(study, grid):
    """The study is built once for the comparisons; each query builds its own otherwise."""
    kept = registry.study, registry.grid
    registry.study, registry.grid = lambda *_: study, lambda *_: grid
    yield
    registry.study, registry.grid = kept


def test_prompt_log(spark, study, tmp_path):
    rows = wr.build_prompt(study.prompts().where("technique <= 2")).limit(20)
    formats.prompt_log(rows.unionByName(rows), f"file://{tmp_path}/log")
    assert spark.read.json(f"file://{tmp_path}/log").count() == rows.select("prompt").distinct().count()


def test_sketches_are_close(spark, sf):
    for name in ("agg_sketch_distinct", "agg_sketch_merged"):
        assert all(abs(r["about"] - r["parts"]) <= 0.06 * r["parts"] for r in registry.queries()[name](spark, sf).collect())


def _views(sf):
    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    return con


@pytest.mark.parametrize("name", sorted(registry.oracles()))
def test_matches_sql(spark, sf, one_study, name, tmp_path):
    df = registry.queries()[name](spark, sf)
    df.write.parquet(str(tmp_path / "q"))
    con = _views(sf)
    con.sql(f"create view s_ as select * from '{tmp_path}/q/*.parquet'")
    con.sql(f"create table o_ as {registry.oracles()[name]}")
    cols = ", ".join(f'"{c}"' for c in df.columns)
    assert con.sql(f"(select {cols} from s_ except all select {cols} from o_) union all (select {cols} from o_ except all select {cols} from s_)").fetchall() == []
