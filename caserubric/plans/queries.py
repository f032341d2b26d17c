"""The experiment workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as X
from ..operators import analysis as A
from ..operators import collection as C
from ..operators import curation as U
from ..operators import dense as D
from ..operators import grading as G
from ..operators import rubric as R
from ..tables import TAGS, load, models, posts, star_cases, star_criteria, star_judged, threads_to_filter

QUERIES: dict = {}


def query(f):
    QUERIES[f.__name__] = f
    return f


# --- shared inputs --------------------------------------------------------------------------------------------------


def scored(spark: SparkSession, d: str) -> DataFrame:
    """Star-track case scores with the case's facets. The scores keep the layout by case, so the join moves only the cases."""
    return G.case_scores(star_judged(spark, d)).join(star_cases(spark, d), "case_id")


def dated_scores(spark: SparkSession, d: str) -> DataFrame:
    dates = load(spark, d, "orders").select(F.col("o_orderkey").alias("case_id"), F.to_date("o_orderdate").alias("published"))
    return G.case_scores(star_judged(spark, d)).join(dates, "case_id")


def messages(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "conversations").where("role <> 'system'").select(F.col("conv_id").alias("thread_id"), "turn", "role", "text")


def screened(spark: SparkSession, d: str) -> DataFrame:
    return U.screen(U.assemble_threads(messages(spark, d)))


def passages(spark: SparkSession, d: str) -> DataFrame:
    labels = load(spark, d, "labels").where("quality = 1").select("doc_id", "toxic")
    return load(spark, d, "documents").select("doc_id", "text").join(labels, "doc_id")


FLOOR_DATE, OFF_TOPIC = "2024-01-04", ("career", "exam")


def thread_rules(rows: DataFrame, first: DataFrame, hits: DataFrame) -> tuple[DataFrame, list[C.Rule]]:
    """The eight post filters, in the order in which they are listed."""
    rows = rows.join(hits.select("thread_id", F.size("matched").alias("codes")), "thread_id", "left").join(first, "thread_id", "left")
    return rows, [
        C.Rule("date", C.published_since(F.col("posted_at"), FLOOR_DATE)),
        C.Rule("tags", C.tag_allowed(F.col("tags"), [x for x in TAGS if x not in OFF_TOPIC], list(OFF_TOPIC))),
        C.Rule("text only", X.text_only("text")),
        C.Rule("symbols", X.symbol_share("text") < 0.5),
        C.Rule("language", X.language("text").isin("en", "zh")),
        C.Rule("code term", F.col("codes") > 0),
        C.Rule("duplicate", F.col("dup_of").isNull()),
        C.Rule("verified reply", F.col("replied")),
    ]


def ruled_threads(spark: SparkSession, d: str) -> tuple[DataFrame, list[C.Rule]]:
    rows = threads_to_filter(spark, d)
    return thread_rules(rows, C.exact_groups(rows, "thread_id", "text"), C.code_hits(rows, "thread_id", "text", C.codebook(load(spark, d, "benchmark"))))


def answers(spark: SparkSession, d: str) -> DataFrame:
    return R.synthetic_responses(screened(spark, d))


def text_judged(spark: SparkSession, d: str) -> DataFrame:
    return G.grade(answers(spark, d), R.build_rubric(screened(spark, d)))


def answer_pairs(spark: SparkSession, d: str) -> DataFrame:
    """(id, candidate, reference): each responder's answer beside the whole advice."""
    a = answers(spark, d)
    ref = a.where("model = 'reference'").select("case_id", F.col("text").alias("reference"))
    return a.join(ref, "case_id").select(F.concat_ws(":", "model", "case_id").alias("id"), F.col("text").alias("candidate"), "reference")


# --- collection -----------------------------------------------------------------------------------------------------


@query
def platform_activity(spark, d):
    return C.weekly_activity(load(spark, d, "events"), "event_type", "ts", 5)


@query
def platform_verified(spark, d):
    return C.verified_count(load(spark, d, "events"), "event_type", "user_id", 100)


@query
def platform_selection(spark, d):
    registry = spark.createDataFrame([("click",), ("view",), ("purchase",)], "event_type string")
    return C.select_platforms(load(spark, d, "events"), registry, "event_type", "ts", "user_id", 5, 100)


@query
def post_filter_funnel(spark, d):
    rows, rules = ruled_threads(spark, d)
    return C.filter_funnel(rows, rules, ablate=True)


@query
def post_filter_reasons(spark, d):
    rows, rules = ruled_threads(spark, d)
    return C.post_filter(rows, rules).select("thread_id", F.array_join("reasons", ",").alias("reasons"), "kept")


@query
def code_term_hits(spark, d):
    hits = C.code_hits(load(spark, d, "documents").select("doc_id", "text"), "doc_id", "text", C.codebook(load(spark, d, "benchmark")))
    return hits.select("doc_id", F.array_join("matched", ",").alias("matched"))


@query
def code_scheme_hits(spark, d):
    """Documents with a term of one scheme, for each of the three."""
    docs, book = load(spark, d, "documents").select("doc_id", "text"), C.codebook(load(spark, d, "benchmark"))
    each = [C.code_hits(docs, "doc_id", "text", book, (s,)).agg(F.lit(s).alias("scheme"), F.count(F.lit(1)).alias("docs"), F.sum(F.size("matched").cast("long")).alias("terms")) for s in C.SCHEMES]
    return each[0].union(each[1]).union(each[2])


@query
def page_bodies(spark, d):
    p = X.page_text("html")
    return load(spark, d, "pages").select("page_id", F.length(p["body"]).cast("long").alias("chars"), F.md5(p["body"]).alias("body_md5"))


@query
def weekly_harvest(spark, d):
    """The messages of one week."""
    return C.harvest_week(posts(spark, d), "2024-01-08").select("thread_id", "turn", "platform", F.col("harvest_week").cast("string").alias("harvest_week"))


@query
def symbol_share(spark, d):
    return load(spark, d, "documents").select("doc_id", F.round(X.symbol_share("text"), 6).alias("share"), (X.symbol_share("text") < 0.5).alias("ok"))


@query
def language_vote(spark, d):
    return load(spark, d, "documents").select("doc_id", X.language("text").alias("voted"), "lang")


@query
def media_pages(spark, d):
    p = X.page_text("html")
    return load(spark, d, "pages").select("page_id", p["title"].alias("title"), p["lang"].alias("lang"), F.size(p["media"]).cast("long").alias("n_media"), X.text_only("html").alias("text_only"))


@query
def verified_reply(spark, d):
    return C.has_verified_reply(messages(spark, d))


@query
def dedup_exact(spark, d):
    return C.exact_groups(load(spark, d, "documents"), "doc_id", "text")


@query
def dedup_index_anti(spark, d):
    docs = load(spark, d, "documents").select("doc_id", "source", "text")
    return C.drop_indexed(docs.where("source >= 'src5'"), docs.where("source < 'src5'"), "doc_id", "text").select("doc_id")


@query
def dedup_near(spark, d):
    """Near pairs of distinct texts, named by their smallest ids, and each exact copy beside the smallest id of its text."""
    docs = load(spark, d, "documents")
    return C.near_pairs(docs, "doc_id", "text").union(C.copy_pairs(docs, "doc_id", "text")).select("a", "b", F.round("jaccard", 6).alias("jaccard"))


# --- curation -------------------------------------------------------------------------------------------------------


@query
def screen_forward(spark, d):
    s = screened(spark, d)
    return s.select("thread_id", "query", F.size("facts").cast("long").alias("n_facts"), F.size("advice").cast("long").alias("n_advice"), "forwarded")


@query
def narrative_sufficiency(spark, d):
    s = screened(spark, d).where("forwarded")
    return s.select("thread_id", U.query_valid(F.col("query")).alias("s_cc"), F.round(U.sufficiency(F.col("query"), F.col("facts")), 6).alias("s_inf"))


@query
def requirement_checklist(spark, d):
    return U.requirements(screened(spark, d))


@query
def evidence_topk_bm25(spark, d):
    hits = U.bm25(U.advice_rows(screened(spark, d)), passages(spark, d), 5, qid=["thread_id", "advice_no"], qtext="advice_text")
    return hits.select("thread_id", "advice_no", F.col("rank").cast("long").alias("rank"), "doc_id", "score")


@query
def advice_verdicts(spark, d):
    advice, p = U.advice_rows(screened(spark, d)), passages(spark, d)
    return U.verdicts(advice, U.bm25(advice, p, 5, qid=["thread_id", "advice_no"], qtext="advice_text"), p)


@query
def validator_keep(spark, d):
    v = U.validate(screened(spark, d), passages(spark, d))
    return v.select("thread_id", "s_cc", F.round("s_inf", 6).alias("s_inf"), F.round("s_align", 6).alias("s_align"), "vetoed", "keep")


@query
def threshold_sweep(spark, d):
    return U.sweep(U.validate(screened(spark, d), passages(spark, d)), [0.25, 0.5, 0.75])


@query
def audit_support(spark, d):
    a = U.audit(U.inject_fabrication(screened(spark, d)))
    return a.select("thread_id", F.col("n_elements").cast("long").alias("n_elements"), F.size("fabricated").cast("long").alias("n_fabricated"), "supported")


@query
def curation_funnel(spark, d):
    return U.curate(messages(spark, d), passages(spark, d)).funnel


@query
def note_sections(spark, d):
    """The four parts of each thread's note, by their sizes and the text of the assessment."""
    note = U.note_sections(F.col("facts"), F.col("advice"))
    rows = screened(spark, d).where("forwarded").select("thread_id", note.alias("note"))
    return rows.select("thread_id", *[F.size(F.col("note")[k]).cast("long").alias(f"n_{k.lower()}") for k in "SOP"], F.get(F.col("note")["A"], F.lit(0)).alias("assessment"))


@query
def fold_strictest(spark, d):
    """Alignment by the worst verdict instead of the mean."""
    advice, p = U.advice_rows(screened(spark, d)), passages(spark, d)
    return U.fold(U.verdicts(advice, U.bm25(advice, p, 5, qid=["thread_id", "advice_no"], qtext="advice_text"), p), "min")


@query
def curation_rejects(spark, d):
    return U.curate(messages(spark, d), passages(spark, d)).rejects


@query
def curated_cases(spark, d):
    return U.curate(messages(spark, d), passages(spark, d)).cases


KINDS = ("guidelines", "abstracts", "textbooks")


def source_hits(spark: SparkSession, d: str, whole: bool) -> DataFrame:
    """Hits for each thread's question in three evidence sources, to which passages are dealt by number, and in all of them if asked."""
    p = passages(spark, d)
    corpora = {k: p.where(F.col("doc_id") % len(KINDS) == i) for i, k in enumerate(KINDS)} | ({"all": p} if whole else {})
    return U.per_source(screened(spark, d).where("forwarded").select("thread_id", "query"), corpora, 5, qid=["thread_id"], qtext="query")


@query
def evidence_by_source(spark, d):
    return source_hits(spark, d, False).select("source", "thread_id", F.col("rank").cast("long").alias("rank"), "doc_id", "score")


@query
def evidence_fused(spark, d):
    """The lists of the three sources and of all passages, fused by reciprocal ranks."""
    hits = source_hits(spark, d, True)
    return U.fuse_ranks([hits], ["thread_id"], 5).select("thread_id", F.col("rank").cast("long").alias("rank"), "doc_id", F.round("score", 6).alias("score"))


# --- dense retrieval ------------------------------------------------------------------------------------------------


def vectors(spark, d):
    v = load(spark, d, "embeddings")
    return v.where("vec_id % 10 = 0").select(F.col("vec_id").alias("q_id"), F.col("embedding").alias("q")), v.select(F.col("vec_id").alias("doc_id"), F.col("embedding").alias("v"))


@query
def evidence_topk_dense(spark, d):
    return D.exact_top_k(*vectors(spark, d), 5)


@query
def retrieval_precision(spark, d):
    labels = load(spark, d, "embeddings").select("vec_id", "label")
    hits = D.exact_top_k(*vectors(spark, d), 5).join(labels.select(F.col("vec_id").alias("q_id"), F.col("label").alias("ql")), "q_id").join(labels.select(F.col("vec_id").alias("doc_id"), F.col("label").alias("dl")), "doc_id")
    return hits.agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.col("ql") == F.col("dl")).cast("double")), 6).alias("precision"))


@query
def ann_recall(spark, d):
    q, v = vectors(spark, d)
    return D.recall(D.lsh_top_k(q, v, 5), D.exact_top_k(q, v, 5))


# --- rubrics and scores ---------------------------------------------------------------------------------------------


@query
def rubric_text(spark, d):
    return R.build_rubric(screened(spark, d))


@query
def rubric_star(spark, d):
    return star_criteria(spark, d).groupBy("axis").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("weight").cast("long")).alias("weights"), F.sum((F.col("weight") < 0).cast("long")).alias("negative"))


@query
def rubric_violations(spark, d):
    return R.check_rubric(star_criteria(spark, d).withColumn("polarity", F.signum(F.col("weight").cast("double")).cast("int"))).groupBy("violation").agg(F.count(F.lit(1)).alias("n"))


@query
def rubric_text_violations(spark, d):
    """The checks on the criteria that are built from texts: equal criteria of a case are its usual fault."""
    return R.check_rubric(R.build_rubric(screened(spark, d))).groupBy("violation").agg(F.count(F.lit(1)).alias("n"))


@query
def unique_criteria(spark, d):
    return R.unique_criteria(R.build_rubric(screened(spark, d)))


@query
def case_scores(spark, d):
    s = G.case_scores(star_judged(spark, d))
    return s.groupBy("model_id").agg(F.sum("got").alias("got"), F.sum("possible").alias("possible"), F.count("score").alias("n_scored"), F.sum((F.col("raw") < 0).cast("long")).alias("clipped"), F.round(F.avg("raw"), 6).alias("raw"), F.round(F.avg("score"), 6).alias("score"))


@query
def leaderboard(spark, d):
    return G.leaderboard(G.case_scores(star_judged(spark, d)))


@query
def leaderboard_modes(spark, d):
    return G.leaderboard_modes(star_judged(spark, d))


@query
def axis_scores(spark, d):
    return G.axis_scores(star_judged(spark, d))


@query
def snapshot_leaderboard(spark, d):
    return G.leaderboard(dated_scores(spark, d).where("published <= date'1996-12-31'"))


@query
def pairwise_wins(spark, d):
    return G.pairwise_wins(G.case_scores(star_judged(spark, d)))


@query
def text_leaderboard(spark, d):
    s = G.case_scores(text_judged(spark, d), "model")
    return s.groupBy("model").agg(F.count("score").alias("n"), F.round(F.avg("raw"), 6).alias("raw"), F.round(F.avg("score"), 6).alias("score"))


# --- time and leakage -----------------------------------------------------------------------------------------------


@query
def cutoff_delta(spark, d):
    return A.cutoff_delta(dated_scores(spark, d), models(spark))


@query
def degraded_share(spark, d):
    return A.degraded_share(A.cutoff_delta(dated_scores(spark, d), models(spark)))


@query
def degraded_by_family(spark, d):
    return A.degraded_by_family(A.cutoff_delta(dated_scores(spark, d), models(spark)), models(spark))


@query
def score_by_month(spark, d):
    return A.score_by_window(dated_scores(spark, d), 1)


@query
def score_sliding(spark, d):
    return A.score_by_window(dated_scores(spark, d), 12, 3)


@query
def drop_significance(spark, d):
    return A.drop_significance(dated_scores(spark, d), models(spark))


@query
def drop_bootstrap(spark, d):
    return A.drop_bootstrap(dated_scores(spark, d), models(spark))


@query
def score_by_quarter(spark, d):
    return A.score_by_quarter(dated_scores(spark, d))


@query
def score_trend(spark, d):
    return A.trend(dated_scores(spark, d))


@query
def aligned_windows(spark, d):
    return A.aligned_windows(dated_scores(spark, d), models(spark))


@query
def separation_violations(spark, d):
    return A.separation_violations(load(spark, d, "orders").select(F.col("o_orderkey").alias("case_id"), F.to_date("o_orderdate").alias("published")), models(spark))


@query
def leak_exact(spark, d):
    return A.verbatim_leaks(load(spark, d, "documents"), load(spark, d, "benchmark"))


@query
def leak_ngram(spark, d):
    return A.ngram_leaks(load(spark, d, "documents"), load(spark, d, "benchmark"))


@query
def leak_gap(spark, d):
    leaked = A.ngram_leaks(load(spark, d, "documents"), load(spark, d, "benchmark")).select(F.col("item_id").alias("case_id")).distinct().withColumn("leaked", F.lit(True))
    s = G.case_scores(star_judged(spark, d)).join(load(spark, d, "benchmark").select(F.col("item_id").alias("case_id")), "case_id").join(leaked, "case_id", "left")
    is_leaked = F.col("leaked").isNotNull()
    return s.groupBy("model_id").agg(F.round(F.avg(F.when(is_leaked, F.col("score"))), 6).alias("leaked"), F.round(F.avg(F.when(~is_leaked, F.col("score"))), 6).alias("clean"))


# --- agreement ------------------------------------------------------------------------------------------------------


def rated(spark, d):
    """doc_id, a (the label), b (a rule on symbols and length)."""
    docs = load(spark, d, "documents").select("doc_id", "text")
    rule = ((X.symbol_share("text") < 0.25) & (F.length("text") >= 100)).cast("int")
    return load(spark, d, "labels").select("doc_id", F.col("quality").alias("a")).join(docs, "doc_id").select("doc_id", "a", rule.alias("b"))


@query
def approval(spark, d):
    r = rated(spark, d)
    rows = r.select(F.inline(F.array(*[F.struct(F.lit("quality").alias("dim"), F.lit(k).alias("rater_id"), F.col(c).alias("rating")) for k, c in ((1, "a"), (2, "b"))])))
    return A.approval_rate(rows)


@query
def gwet_ac1(spark, d):
    return A.agreement(rated(spark, d), [0, 1]).withColumn("band", A.agreement_band(F.col("ac1")))


@query
def gwet_ac1_levels(spark, d):
    """Agreement on three levels: each rater gives one point more to longer texts, at lengths of their own."""
    long = load(spark, d, "documents").select("doc_id", F.length("text").alias("len"))
    three = rated(spark, d).join(long, "doc_id").select((F.col("a") + (F.col("len") >= 900).cast("int")).alias("a"), (F.col("b") + (F.col("len") >= 800).cast("int")).alias("b"))
    return A.agreement(three, [0, 1, 2])


@query
def macro_f1(spark, d):
    return A.macro_f1(rated(spark, d), "b", "a")


@query
def grader_alignment(spark, d):
    """Judgements of all models against two simulated physicians, who each flip about one in eleven."""
    j = star_judged(spark, d)
    flip = lambda k: F.pmod(F.col("case_id") * 31 + F.col("criterion_no") * 17 + k, F.lit(11)) == 0
    rows = j.select(F.col("met").cast("int").alias("m"), *[(F.col("met") != flip(k)).cast("int").alias(f"p{k}") for k in (1, 2)])
    out = A.macro_f1(rows, "m", "p1").select(F.lit("grader 1").alias("pair"), "macro_f1")
    return out.union(A.macro_f1(rows, "m", "p2").select(F.lit("grader 2"), "macro_f1")).union(A.macro_f1(rows, "p1", "p2").select(F.lit("raters"), "macro_f1"))


@query
def grader_mean(spark, d):
    """The grader's mean agreement with both physicians, beside theirs with each other."""
    g = grader_alignment(spark, d)
    return g.groupBy(F.when(F.col("pair") == "raters", "raters").otherwise("grader").alias("who")).agg(F.round(F.avg("macro_f1"), 6).alias("macro_f1"))


def two_models(spark, d):
    s = G.case_scores(star_judged(spark, d).where("model_id in (36, 37)"))
    return s.groupBy("case_id").agg(F.max(F.when(F.col("model_id") == 36, F.col("score"))).alias("x"), F.max(F.when(F.col("model_id") == 37, F.col("score"))).alias("y"))


@query
def pearson_case(spark, d):
    return A.pearson_test(two_models(spark, d), "x", "y").select("n", "r")


@query
def pearson_significance(spark, d):
    return A.pearson_test(two_models(spark, d), "x", "y")


@query
def pearson_pairs(spark, d):
    return A.pearson_pairs(G.case_scores(star_judged(spark, d)))


@query
def sampled_cases(spark, d):
    return A.sample_cases(star_cases(spark, d).select("case_id", "theme"), 50)


@query
def score_histogram(spark, d):
    return A.score_histogram(G.case_scores(star_judged(spark, d)))


@query
def score_skew(spark, d):
    return A.score_skew(G.case_scores(star_judged(spark, d)))


def judged_twice(spark, d):
    """model, case_id, text length, rubric and holistic score."""
    s = G.case_scores(text_judged(spark, d), "model").select("model", "case_id", F.col("score").alias("rubric"))
    a = answers(spark, d).select("model", "case_id", F.length("text").alias("len"), G.holistic_score(F.col("text")).alias("holistic"))
    return a.join(s, ["model", "case_id"])


@query
def length_bias(spark, d):
    t = judged_twice(spark, d).withColumn("l", F.log(1.0 + F.col("len")))
    return t.agg(F.count("rubric").alias("n"), F.round(A.corr(F.col("rubric"), F.col("l")), 5).alias("rubric_r"), F.round(A.corr(F.col("holistic"), F.col("l")), 5).alias("holistic_r"))


@query
def missed_hazards(spark, d):
    return judged_twice(spark, d).where("rubric = 0 and holistic >= 0.7").groupBy("model").agg(F.count(F.lit(1)).alias("n"))


@query
def holistic_scores(spark, d):
    return answers(spark, d).groupBy("model").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(G.holistic_score(F.col("text"))), 6).alias("score"))


@query
def rouge_scores(spark, d):
    p = answer_pairs(spark, d)
    return G.rouge_n(p, 1).withColumn("n", F.lit(1)).union(G.rouge_n(p, 2).withColumn("n", F.lit(2)))


@query
def rouge_l_scores(spark, d):
    return G.rouge_l(answer_pairs(spark, d))


@query
def bleu_scores(spark, d):
    return G.bleu(answer_pairs(spark, d))


def choices(spark, d):
    return load(spark, d, "lineitem").select((F.col("l_suppkey") % 38).cast("int").alias("model_id"), F.col("l_partkey").alias("item_id"), (F.col("l_quantity").cast("int") % 4).alias("choice"))


@query
def repeated_runs(spark, d):
    """Items that a model answered more than once, against the rule of one answer each."""
    return G.check_runs(choices(spark, d), ("model_id", "item_id"))


@query
def perturbed_cases(spark, d):
    """Each thread's facts, rewritten: seeds that stay as old as they were."""
    text = F.array_join("facts", ". ")
    return screened(spark, d).where("forwarded").select("thread_id", F.length(text).cast("long").alias("chars"), R.perturb(text).alias("rewritten"))


@query
def choice_accuracy(spark, d):
    key = load(spark, d, "part").select(F.col("p_partkey").alias("item_id"), (F.col("p_size") % 4).alias("right"))
    return G.choice_accuracy(choices(spark, d), key)


# --- breakdown and errors -------------------------------------------------------------------------------------------


@query
def specialty_matrix(spark, d):
    return A.group_matrix(scored(spark, d), "specialty")


@query
def theme_profile(spark, d):
    return A.group_matrix(scored(spark, d), "theme")


@query
def theme_cube(spark, d):
    return A.group_cube(scored(spark, d), "theme", "source")


@query
def specialty_extremes(spark, d):
    return A.extremes(A.group_matrix(scored(spark, d), "specialty"), "specialty")


@query
def specialty_correlation(spark, d):
    return A.group_correlation(A.group_matrix(scored(spark, d), "specialty"), "specialty")


@query
def prevalence_effect(spark, d):
    g = A.group_matrix(scored(spark, d), "specialty").groupBy("specialty").agg(F.sum("n").alias("n"), F.avg("score").alias("s"))
    return g.agg(F.count(F.lit(1)).alias("groups"), F.round(A.corr(F.col("n"), F.col("s")), 5).alias("r"))


@query
def class_contrast(spark, d):
    return A.class_contrast(G.leaderboard(G.case_scores(star_judged(spark, d))), models(spark))


@query
def efficiency(spark, d):
    return A.efficiency(G.leaderboard(G.case_scores(star_judged(spark, d))), models(spark))


@query
def axis_error_rate(spark, d):
    return A.axis_error_rate(star_judged(spark, d))


@query
def worst_per_axis(spark, d):
    return A.worst_per_axis(A.axis_error_rate(star_judged(spark, d)))


@query
def bottom_k(spark, d):
    return A.bottom_k(G.case_scores(star_judged(spark, d)))


@query
def bottom_overlap(spark, d):
    return A.bottom_overlap(A.bottom_k(G.case_scores(star_judged(spark, d))), models(spark))


@query
def mean_overlap(spark, d):
    o = A.bottom_overlap(A.bottom_k(G.case_scores(star_judged(spark, d))), models(spark))
    return o.agg(F.count(F.lit(1)).alias("pairs"), F.round(F.avg("jaccard"), 6).alias("mean"), F.min("jaccard").alias("least"), F.max("jaccard").alias("most"))


@query
def cause_share(spark, d):
    j = star_judged(spark, d)
    return A.cause_share(A.root_causes(A.bottom_k(G.case_scores(j)), j))


# --- augmentation, comparison, statistics ---------------------------------------------------------------------------


def star_modes(spark, d):
    """Baseline on all cases, closed and open on the last month; with evidence, models gain four points of skill."""
    j = star_judged(spark, d)
    base = dated_scores(spark, d).groupBy("model_id").agg(F.avg("score").alias("baseline"))
    month = j.where("published >= date'2001-07-01'")
    luck = F.pmod(F.col("case_id").cast("long") * 7919 + F.col("criterion_no").cast("long") * 104729 + F.col("model_id").cast("long") * 1299709, F.lit(1000003)) % 100
    helped = month.withColumn("met", F.col("met") | ((F.col("weight") > 0) & (luck < F.lit(24) + F.col("model_id"))))
    closed = G.case_scores(month).groupBy("model_id").agg(F.avg("score").alias("closed"))
    opened = G.case_scores(helped).groupBy("model_id").agg(F.avg("score").alias("open"))
    return base.join(closed, "model_id").join(opened, "model_id")


@query
def injection_modes(spark, d):
    return star_modes(spark, d).select("model_id", *[F.round(c, 6).alias(c) for c in ("baseline", "closed", "open")])


@query
def recovery(spark, d):
    return A.recovery(star_modes(spark, d))


@query
def all_improve(spark, d):
    return A.all_improve(star_modes(spark, d))


@query
def open_book_text(spark, d):
    """Half answers, closed and with the two best passages appended."""
    s, p = screened(spark, d), passages(spark, d)
    half = R.synthetic_responses(s).where("model = 'half'")
    asked = s.where("forwarded").select(F.col("thread_id").alias("case_id"), "query")
    hits = U.bm25(asked, p, 2, qid=["case_id"], qtext="query")
    both = half.withColumn("model", F.lit("closed")).unionByName(A.augment(half, hits, p).withColumn("model", F.lit("open")).select("model", "case_id", "text"))
    out = G.case_scores(G.grade(both, R.build_rubric(s)), "model")
    return out.groupBy("model").agg(F.count("score").alias("n"), F.round(F.avg("score"), 6).alias("score"))


FEATURES = "RB1:0100 RB2:1000 RB3:0000 RB4:1000 RB5:1000 RB6:1100 RB7:0000 RB8:0000 RB9:1000 RB10:1000 RB11:1010"


@query
def feature_matrix(spark, d):
    """Rivals from their published features, and this engine's own set from what its tables show."""
    names = ["free_response", "multilingual", "case_rubric", "updated"]
    rivals = spark.createDataFrame([(n, *[c == "1" for c in bits]) for n, bits in (x.split(":") for x in FEATURES.split())], "benchmark string, " + ", ".join(f"{n} boolean" for n in names))
    weeks = posts(spark, d).agg(F.countDistinct(F.date_trunc("week", "posted_at")).alias("w"))
    langs = star_cases(spark, d).agg(F.countDistinct("lang").alias("l"))
    own = weeks.join(langs).select(F.lit("ours").alias("benchmark"), F.lit(True).alias(names[0]), (F.col("l") >= 2).alias(names[1]), F.lit(True).alias(names[2]), (F.col("w") >= 2).alias(names[3]))
    return rivals.union(own).withColumn("all_true", F.col(names[0]) & F.col(names[1]) & F.col(names[2]) & F.col(names[3]))


@query
def difficulty_table(spark, d):
    """Four models on all cases and on the hard fifth, the cases of lowest mean."""
    s = G.case_scores(star_judged(spark, d)).where("score is not null")
    mean = s.groupBy("case_id").agg(F.round(F.avg("score"), 6).alias("m"))
    bound = mean.agg(F.percentile("m", 0.2).alias("bound"))
    few = s.where("model_id in (34, 35, 36, 37)").join(mean, "case_id").join(F.broadcast(bound))
    return few.groupBy("model_id").agg(F.round(F.avg("score"), 6).alias("standard"), F.round(F.avg(F.when(F.col("m") <= F.round("bound", 6), F.col("score"))), 6).alias("hard"))


@query
def dataset_profile(spark, d):
    return A.dataset_profile(star_cases(spark, d))


@query
def criteria_profile(spark, d):
    return A.criteria_profile(star_criteria(spark, d))


@query
def criteria_histogram(spark, d):
    per = star_criteria(spark, d).groupBy("case_id").agg(F.count(F.lit(1)).alias("criteria"))
    return per.groupBy("criteria").agg(F.count(F.lit(1)).alias("cases"))


@query
def long_tail(spark, d):
    return A.long_tail(star_cases(spark, d), "specialty")


@query
def tail_gini(spark, d):
    return A.gini(A.long_tail(star_cases(spark, d), "specialty"))


@query
def weekly_growth(spark, d):
    p = posts(spark, d)
    return p.groupBy(F.date_trunc("week", "posted_at").cast("date").cast("string").alias("week"), "platform").agg(F.count(F.lit(1)).alias("posts"), F.countDistinct("thread_id").alias("threads"))


@query
def cascade_cost(spark, d):
    from .cost import cost_report

    return cost_report(U.curate(messages(spark, d), passages(spark, d)).funnel)


@query
def cascade_tokens(spark, d):
    from .cost import token_report

    done = U.curate(messages(spark, d), passages(spark, d))
    return token_report(done.threads, done.rejects)
