"""Screening, evidence, validation and audit of threads. Rule agents stand in for the language models of the method."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import text as X
from ..shared import publish
from . import sparse as S


def assemble_threads(messages: DataFrame, max_messages: int | None = None) -> DataFrame:
    """thread_id, messages in turn order. Threads of more than max_messages, if given, are left out for a dead-letter table."""
    out = messages.groupBy("thread_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("messages"))
    return out.where(F.size("messages") <= max_messages) if max_messages else out


def said_by(messages: Column, role: str) -> Column:
    return F.filter(messages, lambda m: m["role"] == role)


def screen(threads: DataFrame, max_advice: int | None = None) -> DataFrame:
    """thread_id, facts, query, advice, thread_text, forwarded; everything is narrow.

    The query is the first question of the patient, else the first sentence of their last turn before the last reply; its
    sentence is not a fact. Advice is all sentences of the replies, or the first max_advice if that is given.
    """
    user, reply = said_by(F.col("messages"), "user"), said_by(F.col("messages"), "assistant")
    asked = F.filter(F.transform(user, lambda m: F.regexp_extract(m["text"], r"([^.!?？\n]*[?？])", 1)), lambda q: q != "")
    threads = X.fixed(threads, last_reply=F.array_max(F.transform(reply, lambda m: m["turn"])))
    before = F.filter(user, lambda m: m["turn"] < F.col("last_reply"))
    last = F.element_at(F.slice(before, F.greatest(F.size(before), F.lit(1)), F.lit(1)), 1)
    fallback = F.when(F.size(before) > 0, F.get(X.sentences(last["text"]), F.lit(0)))
    said = F.array_distinct(F.flatten(F.transform(reply, lambda m: X.sentences(m["text"]))))
    base = X.fixed(
        threads,
        query=F.coalesce(F.get(asked, F.lit(0)), fallback),
        all_facts=F.array_distinct(F.flatten(F.transform(user, lambda m: X.sentences(m["text"])))),
        advice=said if max_advice is None else F.slice(said, 1, max_advice),
        thread_text=F.array_join(F.transform("messages", lambda m: m["text"]), "\n"),
    ).drop("messages", "last_reply")
    out = base.withColumn("facts", F.filter("all_facts", lambda s: ~s.eqNullSafe(F.col("query")))).drop("all_facts")
    return out.withColumn("forwarded", forward(F.col("facts"), F.col("query"), F.col("advice")))


def forward(facts: Column, query: Column, advice: Column) -> Column:
    return (F.size(facts) > 0) & (F.length(F.trim(F.coalesce(query, F.lit("")))) > 0) & (F.size(advice) > 0)


def note_sections(facts: Column, advice: Column) -> Column:
    """Four-part note: S the facts, O those with digits, A the first advice, P the others."""
    return F.create_map(F.lit("S"), facts, F.lit("O"), F.filter(facts, lambda s: s.rlike("[0-9]")), F.lit("A"), F.slice(advice, 1, 1), F.lit("P"), F.slice(advice, 2, 1_000_000))


def query_valid(query: Column) -> Column:
    """1 if the query has three tokens, one content token and a known language."""
    return ((F.size(X.tokens(query)) >= 3) & (F.size(X.content(query)) >= 1) & X.language(query).isNotNull()).cast("int")


def heads_of(facts: Column, prefix: int) -> Column:
    """The first letters of the facts' content tokens."""
    return F.array_distinct(F.transform(F.flatten(F.transform(facts, lambda s: X.content(s))), lambda t: F.substring(t, 1, prefix)))


def requirements(screened: DataFrame, prefix: int = 3) -> DataFrame:
    """thread_id, requirement, met: what the query of a forwarded thread asks for, and whether a fact speaks of it. Their share is the sufficiency."""
    rows = X.fixed(screened.where("forwarded"), heads=heads_of(F.col("facts"), prefix))
    need = rows.select("thread_id", "heads", F.explode(X.content("query")).alias("requirement"))
    return need.select("thread_id", "requirement", F.array_contains("heads", F.substring("requirement", 1, prefix)).alias("met"))


def sufficiency(query: Column, facts: Column, prefix: int = 3) -> Column:
    """Share of the query's content tokens that agree in their first letters with a token of a fact; 0 without any."""
    head = lambda t: F.substring(t, 1, prefix)
    heads = heads_of(facts, prefix)
    need = X.content(query)
    asked = F.transform(need, head)
    missing = F.array_except(asked, heads)
    met = F.size(need) - F.size(F.filter(asked, lambda h: F.array_contains(missing, h)))
    return F.when(F.size(need) > 0, met / F.size(need)).otherwise(F.lit(0.0))


def advice_rows(screened: DataFrame) -> DataFrame:
    return screened.where("forwarded").select("thread_id", F.posexplode("advice").alias("advice_no", "advice_text"))


def bm25(queries: DataFrame, corpus: DataFrame, k: int = 5, k1: float = 1.2, b: float = 0.75, common: float = 0.05, qid: list[str] = ("q_id",), qtext: str = "q_text", did: str = "doc_id", dtext: str = "text") -> DataFrame:
    """qid, doc_id, rank, score (in thousandths), shared by posting lists in shards.

    Contributions are rounded to integers before they are added, so the order of addition doesn't matter. shared is the
    number of the query's content tokens that the document holds. `common` is the share of a shard's documents from which
    a list is held as a row over all of them; the result is the same for any.
    """
    rows = X.fixed(queries.select(*qid, F.col(qtext).alias("_text")), _tokens=F.array_distinct(X.tokens("_text")))
    weighty = lambda x: F.length(x) >= 4
    own = F.filter("_tokens", weighty)
    asked = rows.select(*qid, F.size(own).alias("own"), F.concat(own, F.filter("_tokens", lambda x: ~weighty(x))).alias("t"))
    return S.top_k(asked, corpus.select(F.col(did).cast("long").alias("doc_id"), X.tokens(dtext).alias("t")), list(qid), k, k1, b, common)


def fuse_ranks(lists: list[DataFrame], qid: list[str], k: int, c: int = 60) -> DataFrame:
    """Reciprocal rank fusion of hit lists."""
    union = lists[0].select(*qid, "doc_id", "rank")
    for x in lists[1:]:
        union = union.unionByName(x.select(*qid, "doc_id", "rank"))
    scored = union.groupBy(*qid, "doc_id").agg(F.round(F.sum(F.lit(1.0) / (F.lit(c) + F.col("rank"))), 9).alias("score"))
    rank = F.row_number().over(Window.partitionBy(*qid).orderBy(F.col("score").desc(), "doc_id"))
    return scored.withColumn("rank", rank).where(F.col("rank") <= k)


def per_source(queries: DataFrame, corpora: dict[str, DataFrame], k: int, **names) -> DataFrame:
    """source and the hits of bm25 in each of several corpora, which keep their own statistics."""
    out = None
    for source, corpus in corpora.items():
        hits = bm25(queries, corpus, k, **names).withColumn("source", F.lit(source))
        out = hits if out is None else out.unionByName(hits)
    return out


def verdicts(advice: DataFrame, hits: DataFrame, passages: DataFrame, tau_s: float = 0.4, tau_c: float = 0.6) -> DataFrame:
    """thread_id, advice_no, verdict in {0, 0.5, 1}: contradicted by a covering toxic passage, else supported by a clean one, else neutral."""
    if "shared" in hits.columns:  # the search has counted already what the passage covers
        named = hits.select("thread_id", "advice_no", "doc_id", "shared").join(passages.select("doc_id", "toxic"), "doc_id")
        rows = advice.select("thread_id", "advice_no", F.size(X.content("advice_text")).alias("n")).join(named, ["thread_id", "advice_no"], "left")
        cover = F.when(F.col("n") > 0, F.col("shared") / F.col("n")).otherwise(F.lit(0.0))
    else:
        named = hits.select("thread_id", "advice_no", "doc_id").join(passages.select("doc_id", X.content("text").alias("pc"), "toxic"), "doc_id")
        rows = advice.withColumn("ac", X.content("advice_text")).join(named, ["thread_id", "advice_no"], "left")
        cover = X.coverage_of(F.col("ac"), F.col("pc"))
    bad = F.max(F.when((F.col("toxic") == 1) & (cover >= tau_c), 1).otherwise(0))
    good = F.max(F.when((F.col("toxic") == 0) & (cover >= tau_s), 1).otherwise(0))
    out = rows.groupBy("thread_id", "advice_no").agg(bad.alias("bad"), good.alias("good"))
    return out.select("thread_id", "advice_no", F.when(F.col("bad") == 1, F.lit(0.0)).when(F.col("good") == 1, F.lit(1.0)).otherwise(F.lit(0.5)).alias("verdict"))


def fold(v: DataFrame, how: str = "mean") -> DataFrame:
    """thread_id, s_align, vetoed."""
    f = F.avg if how == "mean" else F.min
    return v.groupBy("thread_id").agg(f("verdict").alias("s_align"), F.bool_or(F.col("verdict") == 0).alias("vetoed"))


def keep_rule(tau_inf: float = 0.5, tau_align: float = 0.5) -> Column:
    return (F.col("s_cc") == 1) & (F.col("s_inf") > tau_inf) & (F.coalesce("s_align", F.lit(0.0)) > tau_align) & ~F.coalesce("vetoed", F.lit(True))


def narrated(screened: DataFrame) -> DataFrame:
    """thread_id, s_cc, s_inf of each forwarded thread: what needs no evidence."""
    return screened.where("forwarded").select("thread_id", query_valid(F.col("query")).alias("s_cc"), sufficiency(F.col("query"), F.col("facts")).alias("s_inf"))


def validate(screened: DataFrame, passages: DataFrame, k: int = 5, tau_inf: float = 0.5, tau_align: float = 0.5, gated: bool = False) -> DataFrame:
    """thread_id, s_cc, s_inf, s_align, vetoed, keep for each forwarded thread.

    Gated, evidence is sought only for threads whose complaint is valid and whose narrative suffices; the others have
    no s_align and no veto. keep is the same either way.
    """
    base = narrated(screened)
    live = screened
    if gated:
        base = publish(base, "narrated")
        live = screened.join(base.where((F.col("s_cc") == 1) & (F.col("s_inf") > tau_inf)).select("thread_id"), "thread_id", "left_semi")
    advice = advice_rows(live)
    hits = bm25(advice, passages, k, qid=["thread_id", "advice_no"], qtext="advice_text")
    align = fold(verdicts(advice, hits, passages))
    return base.join(align, "thread_id", "left").withColumn("keep", keep_rule(tau_inf, tau_align))


def sweep(validated: DataFrame, grid: list[float]) -> DataFrame:
    """tau_inf, tau_align, kept over a grid in one pass."""
    sums = [F.sum(keep_rule(a, b).cast("long")).alias(f"k{i}_{j}") for i, a in enumerate(grid) for j, b in enumerate(grid)]
    rows = [F.struct(F.lit(float(a)).alias("tau_inf"), F.lit(float(b)).alias("tau_align"), F.coalesce(f"k{i}_{j}", F.lit(0)).alias("kept")) for i, a in enumerate(grid) for j, b in enumerate(grid)]
    return validated.agg(*sums).select(F.inline(F.array(*rows)))


def audit(screened: DataFrame) -> DataFrame:
    """thread_id, n_elements, fabricated (the elements the thread doesn't cover), supported."""
    rows = X.fixed(screened.where("forwarded"), own=X.content("thread_text"), elements=F.array_union("facts", "advice"))
    out = rows.select("thread_id", F.size("elements").alias("n_elements"), F.filter("elements", lambda x: (F.size(X.content(x)) > 0) & (X.coverage_of(X.content(x), F.col("own")) < 1)).alias("fabricated"))
    return out.withColumn("supported", F.size("fabricated") == 0)


def inject_fabrication(screened: DataFrame, every: int = 2) -> DataFrame:
    """Put the next thread's first advice into every n-th thread, to test the audit."""
    other = screened.select((F.col("thread_id") - 1).alias("thread_id"), F.get("advice", F.lit(0)).alias("foreign"))
    out = screened.join(other, "thread_id", "left")
    hit = (F.col("thread_id") % every == 0) & F.col("foreign").isNotNull()
    return out.withColumn("advice", F.when(hit, F.array_append("advice", F.col("foreign"))).otherwise(F.col("advice"))).drop("foreign")


def synthesise(screened: DataFrame) -> DataFrame:
    return screened.select(F.col("thread_id").alias("case_id"), F.array_join("facts", ". ").alias("narrative"), "query", F.array_join("advice", ". ").alias("advice"))


@dataclass
class Curated:
    cases: DataFrame
    rejects: DataFrame
    funnel: DataFrame
    threads: DataFrame


def curate(messages: DataFrame, passages: DataFrame, k: int = 5, tau_inf: float = 0.5, tau_align: float = 0.5) -> Curated:
    """The cascade: each tier sees what the former passed. rejects has one row per lost thread with its first reason; threads
    are the screened ones.

    Evidence is retrieved for threads with a valid complaint and a sufficient narrative, and only what is kept is audited.
    Threads and verdicts are published, as several tiers read them and each would work them out again.
    """
    screened = publish(screen(assemble_threads(messages)), "screened")
    checked = publish(validate(screened, passages, k, tau_inf, tau_align, gated=True), "checked")
    audited = audit(screened.join(checked.where("keep").select("thread_id"), "thread_id", "left_semi")).select("thread_id", "supported")
    all_ = screened.join(checked, "thread_id", "left").join(audited, "thread_id", "left")
    reason = F.when(~F.col("forwarded"), "screen").when(F.col("s_cc") != 1, "complaint").when(F.col("s_inf") <= tau_inf, "sufficiency").when(F.col("vetoed"), "veto").when(~F.col("keep"), "alignment").when(~F.col("supported"), "audit")
    marked = all_.withColumn("reason", reason)
    order = ["screen", "complaint", "sufficiency", "veto", "alignment", "audit"]
    place = F.coalesce(F.array_position(F.array(*map(F.lit, order)), F.col("reason")), F.lit(len(order) + 1))
    sums = [F.sum((place > i).cast("long")).alias(f"n{i}") for i in range(len(order) + 1)]
    rows = [F.struct(F.lit(i).alias("step"), F.lit(["threads", *order][i]).alias("stage"), F.coalesce(f"n{i}", F.lit(0)).alias("remaining")) for i in range(len(order) + 1)]
    return Curated(synthesise(marked.where("reason is null")), marked.where("reason is not null").select("thread_id", "reason"), marked.agg(*sums).select(F.inline(F.array(*rows))), screened)
