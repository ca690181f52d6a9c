"""One query for each experiment workload; ``queries`` wires them to names."""

from __future__ import annotations

import functools
import itertools
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fixtrace.functions import ctree, store
from fixtrace.functions.text import squash
from fixtrace.operators import backtrack, baselines, detectors, extraction, judge, reach, similarity, versions
from fixtrace.operators import measures as m
from fixtrace.operators.asof import last_before
from fixtrace.operators.cost import StageTimer, time_ratio
from fixtrace.plans import natural, reports
from fixtrace.plans.lab import BLAME, METHODS, PER_VERSION, WEAKNESS, Lab, lab_of

Query = Callable[[SparkSession, str], DataFrame]


def rounded(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.round(n, 6) for n in names})


def w01_dataset_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    n = lambda df, name: df.groupBy("repo_id").agg(F.count("*").alias(name))
    out = lab.project
    for part in (n(lab.commit, "n_commits"), n(lab.version_tag, "n_tags"), n(lab.fix_case, "n_cases")):
        out = out.join(part, "repo_id", "left")
    return out.select("repo_id", "name", "domain", *(F.coalesce(c, F.lit(0)).alias(c) for c in ("n_commits", "n_tags", "n_cases")))


def w02_patch_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    big = F.col("added") + F.col("deleted") > 50
    return lab_of(spark, sf_dir).fix_case.groupBy("patch_class").agg(F.count("*").alias("n_fixes"), F.sum("added").alias("added"), F.sum("deleted").alias("deleted"), F.count_if(big).alias("n_large"))


def w02_weakness_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cases by weakness; every fifth case has a second one."""
    second = F.when(F.expr("vuln_id div 16") % 5 == 0, F.array("vuln_type", ((F.col("vuln_type") + 1) % 7))).otherwise(F.array("vuln_type"))
    rows = lab_of(spark, sf_dir).fix_case.select(F.explode(second).alias("vuln_type")).select(F.col("vuln_type").cast("int"))
    names = F.element_at(F.array(*map(F.lit, WEAKNESS)), F.col("vuln_type") + 1)
    return rows.groupBy("vuln_type").agg(F.count("*").alias("n_cases")).withColumn("weakness", names)


def w03_truth(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    n = lab.truth.groupBy("vuln_id").agg(F.count("*").alias("n_versions"))
    return lab.truth_origin.join(n, "vuln_id", "left").select("vuln_id", "trigger_slot", "origin_commit_id", F.coalesce("n_versions", F.lit(0)).alias("n_versions"))


def _case_truth(lab: Lab, name: str) -> DataFrame:
    """Truth of the cases a method answers: blame methods leave out fixes that only add."""
    return lab.truth.join(lab.deleted().select("vuln_id").distinct(), "vuln_id", "left_semi") if name in BLAME else lab.truth


def _score(lab: Lab, name: str) -> DataFrame:
    return m.rates(m.confusion(lab.method(name), _case_truth(lab, name), ["repo_id"])).withColumn("method", F.lit(name))


def w03_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    return rounded(m.rates(m.confusion(lab.method("claims"), lab.truth, ["repo_id"])), "precision", "recall", "f1")


def w03_basic_blame(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    return baselines.blame_basic(lab.deleted(), lab.content)


def w03_engine_first_parent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Origins found along first parents with equal weights."""
    lab = lab_of(spark, sf_dir)
    return lab.engine("first_parent", stmts=lab.statements.withColumn("weight", F.lit(1.0))).select("vuln_id", "origin_commit_id", F.round("score", 6).alias("score"))


def w03_engine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Origins found over merges with sensitive statements at double weight."""
    return rounded(lab_of(spark, sf_dir).engine(), "score")


def w03_method_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Macro scores of every method; versions are counted by runs of tags, walks that share touches are one pass."""
    lab = lab_of(spark, sf_dir)
    blamed = lab.deleted().select("vuln_id").distinct().withColumn("deletes", F.lit(True))
    truth = lab.truth_runs.join(blamed, "vuln_id", "left").withColumn("method", F.explode(F.array(*map(F.lit, METHODS))))
    truth = truth.where(~F.col("method").isin(*BLAME) | F.col("deletes")).drop("deletes")
    rows = m.rates(m.confusion_of_runs(lab.found_runs(), truth, "method"))
    return rounded(m.macro(rows, ["method"]), "precision", "recall", "f1")


def w03_gains(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relative F1 gain of the two-level method over the blame and claim methods."""
    lab = lab_of(spark, sf_dir)
    rows = store.settle(functools.reduce(DataFrame.unionByName, (_score(lab, n) for n in ("two_level", "claims", *BLAME))))
    scores = m.macro(rows, ["method"]).select("method", "f1")
    own = scores.where("method = 'two_level'").select(F.col("f1").alias("own"))
    return scores.where("method <> 'two_level'").crossJoin(F.broadcast(own)).select("method", F.round(m.relative_gain(F.col("own"), F.col("f1")), 6).alias("gain"))


def w05_path_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Statements on which the closed form and the walk over all parent paths stop at the same touch."""
    from fixtrace.operators.blame import predecessors

    lab = lab_of(spark, sf_dir)
    closed = backtrack.statement_stops(lab.statements, lab.compared).select("vuln_id", "slot", F.col("stop_commit").alias("x"), "met_merge")
    walked = backtrack.exact_stops(lab.statements, predecessors(lab.content), lab.compared).select("vuln_id", "slot", F.col("stop_commit").alias("y"))
    both = closed.join(walked, ["vuln_id", "slot"], "full_outer")
    return both.agg(F.count("*").alias("n_statements"), F.count_if(F.col("x").eqNullSafe(F.col("y"))).alias("n_same"), F.count_if("met_merge").alias("n_met_merge"))


def w04_per_project(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(_score(lab_of(spark, sf_dir), "two_level"), "precision", "recall", "f1")


def w05_merge_subset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores over the cases whose walk met a merged branch, with and without following it."""
    lab = lab_of(spark, sf_dir)
    met = backtrack.statement_stops(lab.statements, lab.compared).where("met_merge").select("vuln_id").distinct()
    out = []
    for name in ("two_level", "first_parent"):
        p, t = (x.join(met, "vuln_id", "left_semi") for x in (lab.method(name), lab.truth))
        out.append(m.macro(m.rates(m.confusion(p, t, ["repo_id"])), []).withColumn("method", F.lit(name)))
    return rounded(out[0].unionByName(out[1]), "precision", "recall", "f1")


def _functions(lab: Lab) -> tuple[DataFrame, DataFrame]:
    """Each case's file just before the fix as a numbered function, and its changed lines."""
    main = lab.content.where("lane = 'main'").select("file_id", "slot", "seq", "text")
    asked = lab.cases.select("vuln_id", "file_id", "fix_seq").join(F.broadcast(main.select("file_id", "slot").distinct()), "file_id")
    last = last_before(asked, main, F.struct("text"), ["file_id", "slot"]).select("vuln_id", "slot", squash(F.col("met.text")).alias("text"))
    key = F.col("vuln_id").cast("string").alias("func_id")
    return last.select(key, F.col("slot").alias("line_no"), "text"), lab.statements.select(key, F.col("slot").alias("line_no"))


def _records(lab: Lab) -> DataFrame:
    name = F.element_at(F.array(*map(F.lit, WEAKNESS)), F.col("vuln_type") + 1)
    return lab.cases.select("vuln_id", F.array(name).alias("weakness"), F.concat(F.lit("A "), name, F.lit(" in file "), F.col("file_id").cast("string"), F.lit(".")).alias("description"))


def _flow(rows: DataFrame) -> DataFrame:
    return extraction.render_flow(rows).select(F.col("func_id").cast("long").alias("vuln_id"), "flow")


def _judged(lab: Lab, flows: DataFrame, strategy: str = "few_shot_reason", noise: float = 0.15, runs: int = 10) -> DataFrame:
    """(vuln_id, run_no, stmt, tokens_in, tokens_out) of a rule judge."""
    prompts = store.settle(judge.build_prompts(_records(lab), flows, strategy))
    done = judge.run_judge(prompts, judge.RuleProvider(noise, lab.watched), runs)
    return judge.named_statements(prompts, done, lab.added).select("vuln_id", "run_no", F.col("line_no").alias("stmt"))


def w06_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dependence slice of each case: direction counts."""
    lab = lab_of(spark, sf_dir)
    found = extraction.slices(*_functions(lab))
    return found.groupBy(F.col("func_id").cast("long").alias("vuln_id")).agg(F.count("*").alias("n_lines"), *(F.count_if(F.col("direction") == d).alias(f"n_{d}") for d in ("seed", "back", "fwd")))


def w06_extraction_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slice only, judge only and both: statements kept per case, and the scores of the origins found from them."""
    lab = lab_of(spark, sf_dir)
    functions, seeds = _functions(lab)
    functions = store.settle(functions)
    sliced = store.settle(extraction.slices(functions, seeds))
    by_slice = sliced.select(F.col("func_id").cast("long").alias("vuln_id"), F.col("line_no").alias("slot"))
    voted = lambda flows: m.vote(_judged(lab, flows)).select("vuln_id", F.col("stmt").alias("slot"))
    sets = {"slice": by_slice, "judge": voted(_flow(functions)), "both": voted(_flow(sliced))}
    texts = functions.select(F.col("func_id").cast("long").alias("vuln_id"), F.col("line_no").alias("slot"), "text")
    out = []
    for name, kept in sets.items():
        s = kept.distinct().join(texts, ["vuln_id", "slot"]).join(lab.cases, "vuln_id").withColumn("weight", F.lit(1.0))
        counts = kept.groupBy("vuln_id").agg(F.count_distinct("slot").alias("n"))
        scores = m.macro(m.rates(m.confusion(lab.affected(lab.engine(stmts=store.settle(s))), lab.truth, ["repo_id"])), [])
        out.append(scores.crossJoin(counts.agg(F.avg("n").alias("mean_statements"))).withColumn("mode", F.lit(name)))
    return rounded(functools.reduce(DataFrame.unionByName, out), "precision", "recall", "f1", "mean_statements")


def w07_prompt_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three rule judges by three prompt styles: agreement and Jaccard of ten runs.  Shape only; no model runs here."""
    lab = lab_of(spark, sf_dir)
    functions, seeds = _functions(lab)
    flows = store.settle(_flow(extraction.slices(functions, seeds)))
    out = []
    for noise in (0.1, 0.2, 0.3):
        for strategy in judge.STRATEGIES:
            runs = store.settle(_judged(lab, flows, strategy, noise))
            row = m.agreement(runs).crossJoin(m.mean_jaccard(runs)).crossJoin(m.vote(runs).agg(F.count("*").alias("n_voted")))
            out.append(row.withColumns({"noise": F.lit(noise), "strategy": F.lit(strategy)}))
    return rounded(functools.reduce(DataFrame.unionByName, out), "agreement", "mean_jaccard")


def _event_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = natural.table(spark, sf_dir, "events")
    k = F.get_json_object("props", "$.k").cast("int")
    return e.select(F.col("user_id").alias("vuln_id"), (F.col("event_id") % 10).cast("int").alias("run_no"), F.col("event_type").alias("stmt"), k.alias("tokens_in"), (F.col("event_id") % 97).cast("int").alias("tokens_out"))


def w08_vote(spark: SparkSession, sf_dir: str) -> DataFrame:
    return m.vote(_event_runs(spark, sf_dir))


def w08_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(m.agreement(_event_runs(spark, sf_dir)), "agreement")


def w08_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(m.mean_jaccard(_event_runs(spark, sf_dir)), "mean_jaccard")


def w09_cutoff_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Claim scores before and after a cutoff month, over all cases; the cutoff month itself is before.

    The tables' dates lie elsewhere than the three cutoffs, so the same three splits are placed at the quartiles of
    the case dates.
    """
    lab = lab_of(spark, sf_dir)
    marks = lab.cases.agg(F.percentile(F.unix_date(F.to_date("published_at")), F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("q"))
    cuts = marks.select(F.posexplode("q").alias("cut", "day")).select("cut", F.last_day(F.date_from_unix_date(F.floor("day").cast("int"))).alias("until"))
    side = lab.cases.select("vuln_id", F.to_date("published_at").alias("on")).crossJoin(F.broadcast(cuts)).select("vuln_id", "cut", F.when(F.col("on") <= F.col("until"), "pre").otherwise("post").alias("side"))
    p, t = (x.join(side, "vuln_id") for x in (lab.method("claims"), lab.truth))
    return rounded(m.rates(m.confusion(p, t, ["cut", "side"])), "precision", "recall", "f1")


def _swept(lab: Lab, params: DataFrame) -> DataFrame:
    """Macro scores of the engine's walk over merges for each row of ``params`` (p, theta_a, theta_b, theta_s, ratio).

    Both levels are computed once for every pair; every pair of thresholds only re-reads them, and versions are
    counted by their first and last, as a lax threshold finds origins far back.
    """
    by = ("p", "theta_s")
    grid = sorted({(r.theta_a, r.theta_b) for r in params.collect()})
    numbers = F.broadcast(lab.spark.createDataFrame([(k, *t) for k, t in enumerate(grid)], "k int, theta_a int, theta_b int").join(params, ["theta_a", "theta_b"]).select("k", *by))
    stops = store.settle(backtrack.swept_stops(lab.statements, lab.levels, grid).join(numbers, "k").drop("k"))
    stmts = lab.statements.crossJoin(F.broadcast(params)).withColumn("weight", F.when(F.col("sensitive"), F.col("ratio")).otherwise(1.0))
    origins = backtrack.cumulative(stmts, stops, F.col("theta_s"), by).select("p", "vuln_id", "origin_commit_id")
    c = lab.commit.select(F.col("commit_id").alias("origin_commit_id"), "repo_id", reach.arrival().alias("seq"))
    came = c.join(F.broadcast(origins.select("origin_commit_id").distinct()), "origin_commit_id", "left_semi").where("seq is not null")
    starts = versions.tags_before(came, lab.tags).select("origin_commit_id", F.col("n_tags").alias("first"))
    fixed = versions.tags_before(lab.cases.select("vuln_id", "repo_id", F.col("fix_seq").alias("seq")), lab.tags).select("vuln_id", "repo_id", F.col("n_tags").alias("stop"))
    known = versions.tags_before(lab.arrivals(lab.truth_origin.where("origin_commit_id is not null")).where("arrival is not null").withColumnRenamed("arrival", "seq"), lab.tags)
    real = fixed.join(known.select("vuln_id", F.col("n_tags").alias("real")), "vuln_id", "left").crossJoin(F.broadcast(params.select("p")))
    spans = real.join(origins.join(starts, "origin_commit_id"), ["p", "vuln_id"], "left")
    return m.macro(m.rates(m.confusion_of_spans(spans, ["p", "repo_id"])), ["p"]).join(F.broadcast(params), "p")


_PARAMS = "p int, theta_a int, theta_b int, theta_s int, ratio double"


def w10_weight_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    params = spark.createDataFrame([(k, 900, 800, 700, float(k)) for k in range(1, 6)], _PARAMS)
    return rounded(_swept(lab_of(spark, sf_dir), params), "precision", "recall", "f1").select("ratio", "precision", "recall", "f1")


def _detected(lab: Lab, name: str) -> DataFrame:
    """(detector, repo_id, same, n, similarity) of every change."""
    pairs = lab.changes
    if name == "function_model":
        rows = detectors.function_model(lab.function_changes)
    else:
        scored = {"edit": detectors.edit, "md5": detectors.md5, "vector": detectors.vector}
        by_sims = {"tree": detectors.tree, "two_level": detectors.two_level}
        rows = detectors.weighed(pairs, scored[name](pairs) if name in scored else by_sims[name](pairs, lab.sims_both))
    return rows.select(F.lit(name).alias("detector"), "repo_id", "same", "n", "similarity")


def _detector_scores(lab: Lab, *names: str) -> DataFrame:
    return rounded(detectors.compared(functools.reduce(DataFrame.unionByName, (_detected(lab, n) for n in names))), "precision", "recall", "f1")


def w11_detectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every detector on the grid of thresholds against the planted kinds, all on the odd repositories."""
    lab = lab_of(spark, sf_dir)
    rows = detectors.by_text(lab.changes, lab.sims_both).unionByName(_detected(lab, "function_model"))
    return rounded(detectors.compared(rows), "precision", "recall", "f1")


def w11_statement_edit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _detector_scores(lab_of(spark, sf_dir), "edit")


def w11_statement_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _detector_scores(lab_of(spark, sf_dir), "md5")


def w11_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _detector_scores(lab_of(spark, sf_dir), "tree", "two_level")


def w11_function_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _detector_scores(lab_of(spark, sf_dir), "function_model")


def w12_refactor_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Compared touches of the patched files and those found to be refactorings."""
    lab = lab_of(spark, sf_dir)
    total = lambda c: F.coalesce(F.sum(c), F.lit(0).cast("long"))
    out = lab.sims.agg(total(F.col("n")).alias("n_compared"), total(F.when(similarity.refactoring(), F.col("n"))).alias("n_refactorings"))
    return out.withColumn("share", F.round(F.col("n_refactorings") / F.col("n_compared"), 6))


def w12_walk_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Comparisons that stepwise walks over all parents make: in all, per fix, and fixes with an empty walk."""
    from fixtrace.operators.blame import predecessors

    lab = lab_of(spark, sf_dir)
    preds = predecessors(lab.content)
    steps = backtrack.walk(lab.statements, preds, lab.compared).where("round > 0").select("vuln_id", "slot", "commit_id", "pred_commit_id").distinct()
    per = lab.statements.select("vuln_id").distinct().join(steps.groupBy("vuln_id").agg(F.count("*").alias("n")), "vuln_id", "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return per.agg(F.count("*").alias("n_fixes"), F.sum("n").alias("n_comparisons"), F.round(F.avg("n"), 6).alias("mean_comparisons"), F.count_if(F.col("n") == 0).alias("n_direct"))


GRID = tuple(k * 100 for k in range(1, 11))


def threshold_sweep(lab: Lab, start: tuple[int, int] = (800, 800)) -> DataFrame:
    """Coordinate-wise: each threshold over the grid with the others at their chosen values, the best F1 chosen from
    the data (of equal ones the greatest threshold), then the next.  Each step collects the one row chosen."""
    chosen = {"theta_a": None, "theta_b": start[0], "theta_s": start[1]}
    out = []
    for k, name in enumerate(chosen):
        rows = [(k * len(GRID) + i, *({**chosen, name: t}[c] for c in chosen), 2.0) for i, t in enumerate(GRID)]
        step = store.settle(_swept(lab, lab.spark.createDataFrame(rows, _PARAMS)).withColumn("step", F.lit(name)))
        best = step.orderBy(F.desc_nulls_last(F.round("f1", 9)), F.desc(name)).first()
        chosen[name] = best[name] if best else start[-1]
        out.append(step.withColumn("chosen", F.col(name) == chosen[name]))
    return functools.reduce(DataFrame.unionByName, out)


def threshold_grid(lab: Lab, grid: tuple[int, ...] = GRID) -> DataFrame:
    """Every combination of the three thresholds."""
    rows = [(k, *t, 2.0) for k, t in enumerate(itertools.product(grid, repeat=3))]
    return _swept(lab, lab.spark.createDataFrame(rows, _PARAMS))


def w13_threshold_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = threshold_sweep(lab_of(spark, sf_dir))
    return rounded(found, "precision", "recall", "f1").select("step", "theta_a", "theta_b", "theta_s", "precision", "recall", "f1", "chosen")


def w13_full_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The full grid in steps of .3 (64 points); ``threshold_grid`` takes any."""
    found = threshold_grid(lab_of(spark, sf_dir), (100, 400, 700, 1000))
    return rounded(found, "precision", "recall", "f1").select("theta_a", "theta_b", "theta_s", "precision", "recall", "f1")


#: Parts of the tree level left out one by one: depth of call expansion and rules of the normal form.
ABLATIONS = {"full": (1, ctree.RULES), "no_expansion": (0, ctree.RULES), "no_normal_form": (1, frozenset())} | {f"no_{r}": (1, ctree.RULES - {r}) for r in sorted(ctree.RULES)}


def w12_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tree level without call expansion, without each rule of the normal form and without all: planted
    refactorings found, rewrites taken for refactorings, and the engine's scores."""
    lab = lab_of(spark, sf_dir)
    near = F.round(F.col("sim_a") * 1000) >= similarity.THETA_LINE
    told = similarity.tree_variants(lab.content.where(~near).select("pre", F.col("text").alias("post")), lab.callees, list(ABLATIONS.values()))
    reached = F.transform("sims", lambda b: F.coalesce(F.round(b * 1000) >= similarity.THETA_TREE, F.lit(False)))
    # a bit for each ablation: those under which the touch kept its statement
    bits = lambda flags: functools.reduce(lambda x, y: x.bitwiseOR(y), (F.when(F.get(flags, F.lit(k)), 1 << k).otherwise(0) for k in range(len(ABLATIONS))))
    flags = told.select("pair", F.lit(None).cast("boolean").alias("similar"), bits(reached).alias("found"))
    rows = backtrack.compared_touches(lab.content.withColumn("similar", F.when(near, True)), flags, keep=("edit_kind",))
    every = (1 << len(ABLATIONS)) - 1
    kept = F.when(F.col("kind") == 0, 0).when((F.col("kind") == 1) | F.col("similar") | F.col("kind").isNull(), every).otherwise(F.coalesce("found", F.lit(0)))
    rows = store.settle(rows.select(*backtrack.PLACE, "kind", "edit_kind", kept.alias("kept")))
    store.drop(told)

    def of(k: int, edit: int, all_of_them: bool = False) -> Column:
        return F.count_if((F.col("edit_kind") == edit) & (F.lit(all_of_them) | (F.col("kept").bitwiseAND(F.lit(1 << k)) != 0)))

    each = F.array(*(F.struct(F.lit(k).alias("k"), F.lit(name).alias("without"), of(k, 1).alias("n_found"), of(k, 1, True).alias("n_refactorings"), of(k, 2).alias("n_mistaken")) for k, name in enumerate(ABLATIONS)))
    counts = rows.where("kind in (1, 2)").agg(each.alias("x")).select(F.inline("x"))
    lost = [F.col("kept").bitwiseAND(F.lit(1 << k)) == 0 for k in range(len(ABLATIONS))]
    stops = store.settle(backtrack.many_stops(lab.statements, rows, lost, F.col("kept") < every, ("kept",)))
    number = F.explode(F.array(*map(F.lit, range(len(ABLATIONS))))).alias("k")
    origins = backtrack.cumulative(lab.statements.select("vuln_id", "slot", "weight", number), stops, by=("k",)).select("k", "vuln_id", "origin_commit_id")
    walked = lab.first_tags(store.settle(origins)).join(lab.truth_runs.select("vuln_id", "stop"), "vuln_id")
    walked = walked.select("k", "vuln_id", (F.col("ahead") + 1).alias("first"), F.col("stop").alias("last")).where("first <= last")
    scores = m.macro(m.rates(m.confusion_of_runs(walked, lab.truth_runs.select("*", number), "k")), ["k"]).select("k", "precision", "recall", "f1")
    out = store.settle(counts.join(scores, "k", "left"))
    store.drop(rows, stops)
    return rounded(out.select("n_found", "n_refactorings", "n_mistaken", "precision", "recall", "f1", "without"), "precision", "recall", "f1")


def w14_claim_audit(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    return m.audit(lab.claims, lab.truth, lab.tags).select("vuln_id", "source_id", "pattern", "audit", "pattern_found", "n_missing", "n_extra")


def w14_severity(spark: SparkSession, sf_dir: str) -> DataFrame:
    lab = lab_of(spark, sf_dir)
    wrong = m.audit(lab.claims, lab.truth, lab.tags)
    return wrong.groupBy("audit", m.band(F.col("severity")).alias("severity_band")).agg(F.count("*").alias("n_cases"))


def w15_judge_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = m.judge_cost(_event_runs(spark, sf_dir))
    return out.select("vuln_id", *(F.col(c).cast("long").alias(c) for c in ("tokens_in", "tokens_out")), F.round("cost", 9).alias("cost"))


def w14_audit_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Audited claims by domain and class, with subtotals; ``level`` is 0 for single cells, 1 for domains, 3 for all."""
    lab = lab_of(spark, sf_dir)
    rows = m.audit(lab.claims, lab.truth, lab.tags).join(lab.project.select("repo_id", "domain"), "repo_id")
    return rows.rollup("domain", "audit").agg(F.count("*").alias("n_cases"), F.grouping_id().cast("int").alias("level"))


def w14_audit_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each claiming source, one column for each class."""
    lab = lab_of(spark, sf_dir)
    rows = m.audit(lab.claims, lab.truth, lab.tags)
    return rows.groupBy("source_id").pivot("audit", list(m.CLASSES)).agg(F.count(F.lit(1))).fillna(0)


def w15_stage_seconds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of each stage on a fresh lab, in all and per case, and how many times a dynamic check of three hours a case takes."""
    lab, timer = Lab(spark, sf_dir), StageTimer()
    with timer.stage("cases and texts"):
        lab.cases, lab.content  # noqa: B018
    with timer.stage("slices"):
        store.settle(extraction.slices(*_functions(lab)))
    with timer.stage("similarity"):
        lab.sims, lab.compared  # noqa: B018
    with timer.stage("backtracking"):
        origins = store.settle(lab.engine())
    with timer.stage("versions"):
        store.settle(lab.affected(origins))
    n = lab.cases.count()
    rows = [(k, round(s, 3), round(per, 6), round(time_ratio(max(per, 1e-9), n, 3.0), 1)) for (k, s), per in zip(timer.seconds.items(), timer.per_case(n).values(), strict=True)]
    return spark.createDataFrame(rows, "stage string, seconds double, seconds_per_case double, dynamic_ratio double")


def w16_affected_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lab_of(spark, sf_dir).truth.select("vuln_id", "repo_id", "tag_no", "tag")


def w16_ranges(spark: SparkSession, sf_dir: str) -> DataFrame:
    return versions.as_ranges(lab_of(spark, sf_dir).truth)


def w16_closure_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs on which branch labels and the edges disagree about who holds a fix or origin commit, in all repositories with cases: none."""
    lab = lab_of(spark, sf_dir)
    asked = lab.cases.select(F.col("fix_commit_id").alias("commit_id")).unionByName(lab.truth_origin.select(F.col("origin_commit_id").alias("commit_id")))
    sources = store.settle(lab.commit.join(asked.distinct(), "commit_id", "left_semi"))
    found = reach.disagreements(lab.commit_edge, lab.commit, sources)
    return found.agg(*(F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("n_pairs", "n_differ")))


def method_query(name: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = lab_of(spark, sf_dir).method(name).select("vuln_id", "repo_id", "tag_no")
        return found if name in PER_VERSION else found.distinct()

    return run


def queries() -> dict[str, Query]:
    own = (
        w01_dataset_profile, w02_patch_classes, w02_weakness_types, w03_truth, w03_claims, w03_basic_blame, w03_engine_first_parent, w03_engine,
        w03_method_scores, w03_gains, w04_per_project, w05_path_check, w05_merge_subset, w06_slices, w06_extraction_ablation, w07_prompt_grid, w08_vote, w08_agreement,
        w08_jaccard, w09_cutoff_split, w10_weight_sweep, w11_detectors, w11_statement_edit, w11_statement_md5, w11_tree, w11_function_model, w12_refactor_share, w12_walk_counts, w12_ablations, w13_threshold_sweep, w13_full_grid, w14_claim_audit, w14_severity, w14_audit_rollup, w14_audit_pivot, w15_stage_seconds,
        w15_judge_cost, w16_affected_versions, w16_ranges, w16_closure_check,
    )
    found = {f.__name__: f for f in own} | natural.queries() | reports.queries()
    return found | {f"method_{n}": method_query(n) for n in METHODS}
