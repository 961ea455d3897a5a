"""Workloads of the question benchmark."""
from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from provgraph.functions.durable import cut_table
from provgraph.plans.registry import workload
from provgraph.questions import suite
from provgraph.questions.templates import ALL
from provgraph.sources.overlay import Layers, sql

KINDS = "question_id string, template int, category string, kind string, city int, lang string, text string, feasible boolean, verdict string, split string, outcome string, code string, system string"


def _frame(spark, rows: list[dict], names: list[str], kinds: str) -> DataFrame:
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in rows], kinds)


def _questions(spark, d):
    s = suite.Suite(spark, d)
    return s, s.questions()


#: Slot values a template: over a thousand questions, those in three languages included.
SLOTS = 12


@workload("question_inventory")
def question_inventory(spark, d):
    """Questions by category, city, language, split and verdict, and in all (nulls)."""
    q = suite.Suite(spark, d).questions(SLOTS)
    names = ["category", "city", "lang", "split", "verdict"]
    rows = _frame(spark, q, names, "category string, city int, lang string, split string, verdict string")
    return rows.groupingSets([names, ["category"], ["split"], []], *names).agg(F.count(F.lit(1)).alias("questions"))


_TOKENS = ["auth_height", "roof", "floor_area", "volume", "year_built", "vintage", "用途", "構造", "storeys", "function"]
_CATALOG = " union all ".join([f"""select city::bigint city, '{t}' as token, count("{t}")::bigint non_null, count(*)::bigint total from entity group by city""" for t in _TOKENS] + [f"select e.city::bigint, '{n}', count(distinct x.entity_id)::bigint, count(distinct e.entity_id)::bigint from entity e left join {t} x on x.entity_id = e.entity_id group by e.city" for n, t in (("predicted", "predicted"), ("recon", "recon"), ("fusion_edge", "edge"))])
_NEEDS = ", ".join(f"({t.number}, '{n}')" for t in ALL for n in t.needs or ("",))


_VERDICTS = [f"have as ({_CATALOG})", f"""verdicts as (select template, c.city, case when bool_or(k <> '' and coalesce(non_null, 0) = 0) then 'infeasible' when bool_or(k <> '' and non_null < total) then 'partial' else 'full' end verdict
 from (values {_NEEDS}) n(template, k) cross join (select unnest(range(5)) city) c left join have h on h.token = k and h.city = c.city group by all)"""]


@workload("feasibility_matrix", sql(f"""select template, {", ".join(f'max(case when city = {c} then verdict end) "{c}"' for c in suite.CITIES)} from verdicts group by template""", *_VERDICTS))
def feasibility_matrix(spark, d):
    fits = suite.Suite(spark, d).feasibility()
    return spark.createDataFrame([(t, c, v) for (t, c), v in fits.items()], "template int, city int, verdict string").groupBy("template").pivot("city", list(suite.CITIES)).agg(F.first("verdict"))


@workload("token_catalog", sql(_CATALOG))
def token_catalog(spark, d):
    return suite.Suite(spark, d).catalog().select(*[F.col(c).cast("long").alias(c) if c != "token" else c for c in ("city", "token", "non_null", "total")])


@workload("infeasible_guards", sql("select template || '-' || city || '-0-en' question_id, 0::bigint found from verdicts where verdict = 'infeasible'", *_VERDICTS))
def infeasible_guards(spark, d):
    """Every infeasible question's guard; all counts must be 0."""
    s, q = _questions(spark, d)
    return spark.createDataFrame([(x["question_id"], s.guard_count(x["guard"])) for x in q if not x["feasible"] and x["lang"] == "en"], "question_id string, found long")


@workload("split_leakage", "select case when t * 7919 % 101 < 27 then 'test' else 'dev' end split, count(*)::bigint templates, 0::bigint shared_templates, case when t * 7919 % 101 < 27 then 0 else 1 end::bigint gold_published from range(1, 85) r(t) group by all")
def split_leakage(spark, d):
    """Templates by split, those found in both, and whether what is published of a split has gold queries."""
    q = suite.public(_questions(spark, d)[1])
    rows = _frame(spark, [x for x in q if x["feasible"]] + [{**x, "gold": None} for x in q if not x["feasible"]], ["template", "split", "gold"], "template int, split string, gold string")
    both = rows.groupBy("template").agg(F.countDistinct("split").alias("n"), F.first("split").alias("split"), F.max(F.col("gold").isNotNull().cast("long")).alias("gold"))
    return both.groupBy("split").agg(F.count(F.lit(1)).alias("templates"), F.sum((F.col("n") > 1).cast("long")).alias("shared_templates"), F.max("gold").alias("gold_published"))


@workload("gate_report")
def gate_report(spark, d):
    """How many questions pass each stage, by category."""
    s, q = _questions(spark, d)
    rows = s.gate([x for x in q if x["lang"] == "en"])
    stages = ["runs", "deterministic", "non_empty", "guarded", "materialised"]
    out = _frame(spark, rows, ["category", *stages], "category string, " + ", ".join(f"{x} boolean" for x in stages))
    return out.groupBy("category").agg(F.count(F.lit(1)).alias("questions"), *[F.sum(F.col(x).cast("long")).alias(x) for x in stages])


@workload("multilingual_same_gold")
def multilingual_same_gold(spark, d):
    """Ten templates in three languages: one answer each."""
    s, q = _questions(spark, d)
    many = {t.number for t in ALL if t.others}
    rows = s.gate([x for x in q if x["template"] in many and x["feasible"]])
    out = _frame(spark, rows, ["template", "city", "lang", "digest"], "template int, city int, lang string, digest string")
    return out.groupBy("template", "city").agg(F.countDistinct("lang").alias("languages"), F.countDistinct("digest").alias("answers"))


def _outcomes(spark, d, systems=("careful", "hallucinating", "never_decline", "keyword_rules", "gold_system", "always_decline")) -> DataFrame:
    """Outcomes of the simulated systems on the stratified part of the suite; outputs are read back from a table."""
    s, q = _questions(spark, d)
    part = suite.subsample(q)
    gold = {r["question_id"]: r["digest"] for r in s.materialise(part).collect()}
    part = [{**x, "digest": gold.get(x["question_id"])} for x in part]
    said = cut_table(spark.createDataFrame([(n, x["question_id"], suite.SYSTEMS[n](x)) for n in systems for x in part], "system string, question_id string, output string"))
    answers: dict = {}
    for r in said.collect():  # a row a system and question
        answers.setdefault(r["system"], {})[r["question_id"]] = r["output"]
    rows = [{**r, "system": n} for n in systems for r in s.score(part, answers[n])]
    return _frame(spark, rows, [k.split()[0] for k in KINDS.split(", ")], KINDS)


@workload("qa_outcomes")
def qa_outcomes(spark, d):
    return suite.rates(_outcomes(spark, d), ["system", "city", "split"])


@workload("qa_abstention")
def qa_abstention(spark, d):
    return suite.abstention(_outcomes(spark, d), ["system"])


@workload("qa_by_category")
def qa_by_category(spark, d):
    return suite.rates(_outcomes(spark, d), ["system", "category"])


@workload("qa_error_codes")
def qa_error_codes(spark, d):
    return _outcomes(spark, d, ("hallucinating",)).where("outcome = 'error'").groupBy("code").agg(F.count(F.lit(1)).alias("n"))


@workload("qa_traps")
def qa_traps(spark, d):
    """Systems that ignore provenance or coverage, on the questions that are traps for them."""
    return suite.rates(_outcomes(spark, d, ("provenance_blind", "coverage_blind")), ["system", "category"])


@workload("question_review_sample")
def question_review_sample(spark, d):
    """About a fifth of each category, drawn by hash, for reading by people."""
    q = _frame(spark, _questions(spark, d)[1], ["question_id", "category", "city", "text", "gold"], "question_id string, category string, city int, text string, gold string")
    return q.where(F.pmod(F.xxhash64("question_id"), F.lit(1000)) < 202)


_ANSWERS = """c as (select 'part-' || (user_id % 4) part, count(*) filter (where event_type = 'click') correct, count(*) filter (where event_type = 'view') wrong, count(*) filter (where event_type = 'error') err,
 count(*) filter (where event_type = 'signup') refused, count(*) filter (where event_type = 'purchase' and event_id % 10 <> 0) tp, count(*) filter (where event_type = 'purchase' and event_id % 10 = 0) fn from events where user_id is not null group by 1)"""


@workload("qa_published_rates", f"""with {_ANSWERS}, f as (select *, correct + wrong + err + refused n from c)
 select part, n::bigint feasible_n, round(100.0::double * correct / n, 1) ex, round(100.0::double * wrong / n, 1) exec_wrong, round(100.0::double * err / n, 1) error, round(100.0::double * refused / n, 1) over_refusal,
 case when tp + refused > 0 then round(200.0::double * tp / (2 * tp + refused + fn), 1) end f1 from f where n > 0""")
def qa_published_rates(spark, d):
    """The scorer's published rates on a table of outcomes: every event is an answer in one of four parts, its type the outcome."""
    kind, asked = F.col("event_type"), F.col("event_id") % 10 == 0
    names = {"click": "correct", "view": "executed_wrong", "error": "error", "signup": "over_refusal"}
    outcome = F.coalesce(*[F.when(kind == k, F.lit(o)) for k, o in names.items()], F.when(kind == "purchase", F.when(asked, "answered_infeasible").otherwise("declined")))
    rows = Layers(spark, d).table("events").select(F.concat(F.lit("part-"), (F.col("user_id") % 4).cast("string")).alias("part"), outcome.alias("outcome"))
    rows = rows.where("part is not null").withColumn("feasible", ~F.col("outcome").isin("declined", "answered_infeasible"))
    f1 = suite.abstention(rows, ["part"]).select(F.col("part").alias("_p"), "f1")
    return suite.rates(rows, ["part"]).join(f1, F.col("part") == F.col("_p")).drop("_p")
