"""The question suite: catalogue, feasibility, binding, verification gate, split, execution and scores."""
from __future__ import annotations

import re
import unicodedata
import uuid
from concurrent.futures import ThreadPoolExecutor

import pandas as pd
from pyspark.errors import AnalysisException, ParseException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from provgraph.functions.durable import cut, cut_table
from provgraph.operators import fusion, provenance
from provgraph.questions import neighbours
from provgraph.questions.templates import ALL, Template
from provgraph.sources.overlay import Layers

CITIES = range(5)
VIEWS = ("entity", "crowd", "fusion_edge", "predicted", "recon", "poi", "fact", "activity")


class Suite:
    """Views of one scale directory under a prefix of their own, and the questions over them."""

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder
        w = Layers(spark, folder)
        edge = cut(fusion.edges(fusion.candidates(w.entity, w.crowd)).select("city", "entity_id", "feature_id", "shared", "overlap", "jaccard"))
        city = w.entity.select("entity_id", "city")
        frames = {
            "entity": w.entity,
            "crowd": w.crowd.drop("tags"),
            "fusion_edge": edge,
            "predicted": w.predicted.join(city, "entity_id"),
            "recon": w.recon.join(city, "entity_id"),
            "poi": w.poi,
            "fact": provenance.height_facts(w.entity, edge, w.crowd),
            "activity": w.table("events").select("user_id", "event_type", "value"),
        }
        # Written by column: a question reads the few that it names.
        self.frames = {k: cut_table(v) for k, v in frames.items()}
        bare = lambda layer, *c: self.frames[layer].where(" or ".join(f"{x} is null" for x in c)).isEmpty()
        self.boxes = bare("entity", "x0", "y0", "x1", "y1") and bare("crowd", "x0", "y0", "x1", "y1") and bare("poi", "x", "y")
        self.prefix = f"q{uuid.uuid4().hex[:12]}_"
        for k, v in self.frames.items():
            v.createOrReplaceTempView(self.prefix + k)

    def sql(self, text: str) -> str:
        """The query over this suite's views, with joins on nearness keyed by grid cells."""
        text = neighbours.indexed(text, self.boxes)
        return re.sub(rf"\b(from|join)\s+({'|'.join(VIEWS)})\b", lambda m: f"{m[1]} {self.prefix}{m[2]} as {m[2]}" if not re.match(r"\s+(?:as\s+)?(?!on\b|where\b|using\b|group\b|join\b|left\b|order\b|limit\b|union\b)[a-z]\w*", text[m.end() :]) else f"{m[1]} {self.prefix}{m[2]}", text)

    def catalog(self) -> DataFrame:
        """(city, token, non_null, total): what the graph holds, in one aggregate a layer."""
        tokens = ["auth_height", "roof", "floor_area", "volume", "year_built", "vintage", "用途", "構造", "storeys", "function"]
        e = self.frames["entity"].groupBy("city").agg(F.count(F.lit(1)).alias("total"), *[F.count(F.col(f"`{t}`")).alias(t) for t in tokens])
        rows = e.select("city", "total", F.explode(F.array(*[F.struct(F.lit(t).alias("token"), F.col(f"`{t}`").alias("non_null")) for t in tokens])).alias("k")).select("city", "k.token", "k.non_null", "total")
        total = e.select(F.col("city").alias("_c"), "total")
        for layer in ("predicted", "recon", "fusion_edge"):
            n = self.frames[layer].groupBy(F.col("city").alias("_l")).agg(F.countDistinct("entity_id").alias("non_null"))
            rows = rows.union(total.join(n, F.col("_c") == F.col("_l"), "left").select("_c", F.lit(layer), F.coalesce("non_null", F.lit(0)), "total"))
        return rows

    def feasibility(self) -> dict[tuple[int, int], str]:
        """full, partial or infeasible per (template, city); from a catalogue of a few dozen rows."""
        have = {(r["token"], r["city"]): (r["non_null"], r["total"]) for r in self.catalog().collect()}
        out = {}
        for t in ALL:
            for c in CITIES:
                got = [have.get((n, c), (0, 1)) for n in t.needs]
                out[t.number, c] = "infeasible" if any(n == 0 for n, _ in got) else "partial" if any(n < m for n, m in got) else "full"
        return out

    def questions(self, slots: int = 1, seed: int = 1) -> list[dict]:
        """All templates in all cities, slot values drawn from the graph by hash; languages double where texts exist."""
        fits = self.feasibility()
        ids = {c: [r[0] for r in self.frames["entity"].where(F.col("city") == c).orderBy(F.xxhash64("entity_id", F.lit(seed)), "entity_id").limit(slots).select("entity_id").collect()] for c in CITIES}
        out = []
        for t in ALL:
            for c in CITIES:
                for k, value in enumerate(ids[c] if t.slot else [""]):
                    fill = lambda q: re.sub(r"\bS\b", str(value), re.sub(r"\bC\b", str(c), q))  # noqa: E731,B023
                    verdict = fits[t.number, c]
                    for lang, text in {"en": t.text, **t.others}.items():
                        out.append({"question_id": f"{t.number}-{c}-{k}-{lang}", "template": t.number, "category": t.category, "kind": t.kind, "city": c, "lang": lang, "text": re.sub(r"\bS\b", str(value), text), "feasible": verdict != "infeasible", "verdict": verdict, "gold": fill(t.gold) if verdict != "infeasible" else None, "guard": guard(t, c, self.frames) if verdict == "infeasible" else None, "ordered": t.ordered, "split": split(t.number)})
        return out

    def context(self) -> str:
        """What a system may see: view and column names, no data; the same bytes every time."""
        return "\n".join(f"{k}({', '.join(sorted(v.columns))})" for k, v in sorted(self.frames.items()))

    def run(self, text: str, ordered: bool = False, partitions: int | None = None) -> dict:
        """n_rows and digest, or the error's code; one read-only query."""
        if code := self.admit(text):
            return {"error": code}
        try:
            df = self.spark.sql(self.sql(text))
            if partitions:
                df = df.repartition(partitions) if not ordered else df
            return canonical(df, ordered).first().asDict() | {"error": None}
        except ParseException:
            return {"error": "parse"}
        except AnalysisException as e:
            routine = re.search(r"UNRESOLVED_ROUTINE[^`]*`([^`]+)`", str(e))
            return {"error": "analysis" + (f":{routine[1]}" if routine else "")}
        except Exception as e:  # noqa: BLE001  whatever a task threw is the system's error
            return {"error": "timeout" if "cancelled" in str(e).lower() else "runtime"}

    def admit(self, text: str) -> str | None:
        """``forbidden`` unless the text is one read query over the suite's views: its parsed plan names no other relation, file or command."""
        if code := admit(text):
            return code
        try:
            plan = self.spark._jsparkSession.sessionState().sqlParser().parsePlan(text).toString()
        except Exception:  # noqa: BLE001  running it will tell what is wrong with it
            return None
        known = {*VIEWS, *(n for names in re.findall(r"\bCTE \[([^\]]*)\]", plan) for n in names.split(", "))}
        if re.search(r"InsertInto|Command\b|CreateTable|CreateView|ReplaceTable|DeleteFrom|UpdateTable|MergeInto", plan):
            return "forbidden"
        if set(re.findall(r"UnresolvedRelation \[([^\]]*)\]", plan)) - known:
            return "forbidden"
        if set(re.findall(r"UnresolvedTableValuedFunction \[([^\]]*)\]", plan)) - {"range", "explode", "posexplode", "inline", "stack"}:
            return "forbidden"
        return None

    def execute(self, text: str, ordered: bool, timeout_s: float) -> dict:
        """``run`` under a tag that is interrupted at the time limit."""
        import threading

        tag = f"question-{threading.get_ident()}"
        self.spark.addTag(tag)
        timer = threading.Timer(timeout_s, lambda: self.spark.interruptTag(tag))
        timer.start()
        try:
            return self.run(text, ordered)
        finally:
            timer.cancel()
            self.spark.removeTag(tag)

    def materialise(self, questions: list[dict], threads: int = 8) -> DataFrame:
        """(question_id, n_rows, digest, error) of all gold answers, written as a table."""
        asked = [q for q in questions if q["feasible"]]
        with ThreadPoolExecutor(threads) as pool:
            got = list(pool.map(lambda q: self.run(q["gold"], q["ordered"]), asked))
        rows = [(q["question_id"], a.get("n_rows"), a.get("digest"), a["error"]) for q, a in zip(asked, got)]
        return cut_table(self.spark.createDataFrame(rows, "question_id string, n_rows long, digest string, error string"))

    def gate(self, questions: list[dict], threads: int = 8) -> list[dict]:
        """The five stages per question: runs, deterministic, not empty unless allowed, guard present and zero, answer materialised.

        The guard of a feasible question must find what its template needs.  An infeasible one has no answer that
        could be empty or written: null there.

        Answers are written; then the graph's views are built anew, every query is asked of them under another
        partitioning, and what comes must equal what was written.
        """
        known = {t.number: t for t in ALL}
        stored = {r["question_id"]: r for r in self.materialise(questions, threads).collect()}  # a row a question
        rebuilt = Suite(self.spark, self.folder)

        def one(q):
            t = known[q["template"]]
            if q["feasible"]:
                a, b = stored[q["question_id"]], rebuilt.run(q["gold"], q["ordered"], 3)
                ok = a["error"] is None
                same = ok and b["error"] is None and (a["n_rows"], a["digest"]) == (b["n_rows"], b["digest"])
                return {**q, "runs": ok, "deterministic": same, "non_empty": ok and (a["n_rows"] > 0 or t.may_be_empty), "guarded": not t.needs or bool(self.guard_count(guard(t, q["city"], self.frames))), "materialised": same and a["digest"] is not None, "digest": a["digest"], "n_rows": a["n_rows"]}
            found, again = self.guard_count(q["guard"]), rebuilt.guard_count(q["guard"])
            return {**q, "runs": found is not None, "deterministic": found is not None and found == again, "non_empty": None, "guarded": found == 0, "materialised": None, "digest": None, "n_rows": None}

        with ThreadPoolExecutor(threads) as pool:
            return list(pool.map(one, questions))

    def guard_count(self, guard: str | None) -> int | None:
        """How much of what a guard query looks for there is; null without a guard, and for one that fails: an error proves nothing."""
        if not guard:
            return None
        try:
            return self.spark.sql(self.sql(guard)).first()[0]
        except (AnalysisException, ParseException):
            return None

    def score(self, questions: list[dict], outputs: dict[str, str | None], timeout_s: float = 60, threads: int = 8) -> list[dict]:
        """Outcome per question; ``outputs``: the query text, or None for a decline."""

        def one(q):
            text = outputs.get(q["question_id"])
            if not q["feasible"]:
                return {**q, "outcome": "declined" if text is None else "answered_infeasible", "code": None}
            if text is None:
                return {**q, "outcome": "over_refusal", "code": None}
            got = self.execute(text, q["ordered"], timeout_s)
            if got["error"]:
                return {**q, "outcome": "error", "code": got["error"]}
            gold = q.get("digest") or self.run(q["gold"], q["ordered"]).get("digest")
            return {**q, "outcome": "correct" if got["digest"] == gold else "executed_wrong", "code": None}

        with ThreadPoolExecutor(threads) as pool:
            return list(pool.map(one, questions))


def split(template: int) -> str:
    """By template: about a quarter are held out, whatever the city or slot."""
    return "test" if template * 7919 % 101 < 27 else "dev"


def guard(t: Template, city: int, frames: dict[str, DataFrame]) -> str:
    """Counts what the template needs in the city; zero proves that it is absent.

    An attribute that the catalogue's schema doesn't have at all counts as 0 by the schema, not by an error.
    """
    layers = ("predicted", "recon")

    def one(n: str) -> str:
        if n in layers:
            return f"(select count(*) from {n} where city = {city})"
        return f"(select count(`{n}`) from entity where city = {city})" if n in frames["entity"].columns else "0"

    return f"select least({', '.join(map(one, t.needs))}, 1000000000)"


def public(questions: list[dict]) -> list[dict]:
    """What is published: the held-out questions without gold query, guard or answer."""
    hidden = ("gold", "guard", "digest", "n_rows")
    return [{k: None if q["split"] == "test" and k in hidden else v for k, v in q.items()} for q in questions]


def subsample(questions: list[dict], every: int = 4) -> list[dict]:
    """Of each category and city the first question by number and every ``every``-th after it, in English."""
    seen: dict = {}
    out = []
    for q in questions:
        if q["lang"] == "en":
            n = seen[q["category"], q["city"]] = seen.get((q["category"], q["city"]), -1) + 1
            if n % every == 0:
                out.append(q)
    return out


def load_outputs(spark: SparkSession, path: str, system: str | None = None) -> dict[str, str | None]:
    """Cached outputs of a system by question: Parquet, or JSON lines, of (question_id, output[, system]); a null output is a decline."""
    rows = spark.read.json(path) if path.endswith((".json", ".jsonl")) else spark.read.parquet(path)
    if system is not None:
        rows = rows.where(F.col("system") == system)
    return {r["question_id"]: r["output"] for r in rows.select("question_id", "output").collect()}  # a row a question


def admit(text: str) -> str | None:
    """``forbidden`` unless the text is one read query."""
    bare = re.sub(r"'[^']*'|`[^`]*`", "", text or "")
    if ";" in bare or not re.match(r"\s*(select|with)\b", bare, re.I) or re.search(r"\b(insert|update|delete|drop|create|alter|merge|truncate|set|add|load|reflect|java_method)\b\s", bare, re.I):
        return "forbidden"
    return None


@F.pandas_udf(StringType())
def _nfc(text: pd.Series) -> pd.Series:
    return text.map(lambda x: x if x is None or x.isascii() else unicodedata.normalize("NFC", x))


def canonical(df: DataFrame, ordered: bool = False) -> DataFrame:
    """(n_rows, digest): names don't count, 1 is 1.0, -0 is 0, NaN is NaN, six decimals, composed characters.

    A bag of rows: the digest is a sum of row hashes, so it needs no sort and keeps duplicates apart from
    single rows.  With an order contract it is a list: a row's hash holds its number, and arrays keep their
    order.  Such a query has a limit, so its rows can be numbered in one task.
    """

    def cell(name: str, kind: str):
        c = F.col(f"`{name}`")
        if kind in ("double", "float") or kind.startswith("decimal") or kind in ("int", "bigint", "smallint", "tinyint"):
            d = c.cast("double")
            return F.when(F.isnan(d), "NaN").otherwise(F.format_string("%.6f", F.round(d, 6) + F.lit(0.0)))
        if kind.startswith("array"):
            return F.to_json(c if ordered else F.array_sort(c))
        return _nfc(c) if kind == "string" else c.cast("string")

    df = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    cells = [F.coalesce(F.concat(F.lit("v"), cell(n, k)), F.lit("n")) for n, k in df.dtypes]
    if ordered:
        df = df.withColumn("_at", F.row_number().over(Window.orderBy(F.monotonically_increasing_id())))
        cells.append(F.col("_at").cast("string"))
    h = F.sha2(F.to_json(F.array(*cells)), 256)
    half = lambda i: F.conv(F.substring("h", i, 16), 16, 10).cast("decimal(20,0)")
    rows = df.select(h.alias("h"))
    total = rows.agg(F.count(F.lit(1)).alias("n_rows"), F.sum(half(1)).alias("a"), F.sum(half(17)).alias("b"))
    return total.select("n_rows", F.sha2(F.concat_ws(":", "n_rows", F.coalesce("a", F.lit(0)).cast("string"), F.coalesce("b", F.lit(0)).cast("string")), 256).alias("digest"))


# --- simulated systems: mutations of the gold queries with known effects --------------------------


def careful(q: dict) -> str | None:
    """Declines what is infeasible; slips on meaning in every third question: reads a box edge, source or limit wrongly."""
    if not q["feasible"]:
        return None
    n = sum(map(ord, q["question_id"]))
    if n % 17 == 0:
        return None
    return q["gold"] if n % 3 else f"select * from ({q['gold']}) where 1 = 0"


def hallucinating(q: dict) -> str | None:
    """Never declines; in spatial questions it calls functions that don't exist, elsewhere it is often wrong."""
    n = sum(map(ord, q["question_id"]))
    if q["category"] == "spatial" or not q["gold"]:
        return f"select count(*) from entity where ST_DWithin(x0, y0, {n % 100})"
    return q["gold"] if n % 7 == 0 else "select cout(*) fron entity" if n % 2 else "select count(*) from entity"


def provenance_blind(q: dict) -> str | None:
    """Reads any source's value where the authoritative one is asked for."""
    return q["gold"].replace("and source = 'auth'", "") if q["gold"] else "select count(*) from fact"


def coverage_blind(q: dict) -> str | None:
    """Leaves the covered and total counts out."""
    return re.sub(r", count\(auth_height\), count\(\*\)|, \(select count\(distinct entity_id\).*?C?\), \(select count\(\*\) from entity where city = \d+\)", "", q["gold"]) if q["gold"] else "select 0"


def always_decline(q: dict) -> str | None:
    return None


def gold_system(q: dict) -> str | None:
    return q["gold"]


def never_decline(q: dict) -> str | None:
    """Right wherever there is an answer, and answers where there is none."""
    return q["gold"] if q["feasible"] else "select 0"


#: What the keyword translator knows: the first word that the question holds decides.
KEYWORDS = [("how many", "select count(*) from entity where city = {city}"), ("average", "select avg(auth_height) from entity where city = {city}"), ("height", "select max(auth_height) from entity where city = {city}"), ("which", "select entity_id from entity where city = {city}")]


def keyword_rules(q: dict) -> str | None:
    """One fixed query a keyword; declines where it knows none."""
    return next((sql.format(city=q["city"]) for word, sql in KEYWORDS if word in q["text"].lower()), None)


SYSTEMS = {f.__name__: f for f in (careful, hallucinating, provenance_blind, coverage_blind, always_decline, never_decline, keyword_rules, gold_system)}


def rates(outcomes: DataFrame, by: list[str]) -> DataFrame:
    """Percentages of the four feasible outcomes, which add up to 100, with counts."""
    f = outcomes.where("feasible")
    share = lambda o: F.round(100 * F.sum((F.col("outcome") == o).cast("long")) / F.count(F.lit(1)), 1)
    return f.groupBy(*by).agg(F.count(F.lit(1)).alias("feasible_n"), share("correct").alias("ex"), share("executed_wrong").alias("exec_wrong"), share("error").alias("error"), share("over_refusal").alias("over_refusal"))


def abstention(outcomes: DataFrame, by: list[str]) -> DataFrame:
    """Precision, recall and F1 of declining; an over-refusal is a false positive; without any decline F1 is null."""
    n = lambda o: F.sum((F.col("outcome") == o).cast("long"))
    out = outcomes.groupBy(*by).agg(n("declined").alias("tp"), n("over_refusal").alias("fp"), n("answered_infeasible").alias("fn"))
    pct = lambda a, b: F.when(b > 0, F.round(100 * a / b, 1))
    return out.withColumns({"precision": pct(F.col("tp"), F.col("tp") + F.col("fp")), "recall": pct(F.col("tp"), F.col("tp") + F.col("fn")), "f1": F.when(F.col("tp") + F.col("fp") > 0, F.round(200 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")), 1))})
