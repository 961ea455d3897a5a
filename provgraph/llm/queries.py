"""Queries of the training-data operators, and their SQL."""
from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from provgraph.llm import decontamination, forest, hilbert, language_model, licenses, line_dedup, near_duplicates, pfair, substring_dedup, toxicity


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_hilbert_shards(spark, d):
    return hilbert.digest(table(spark, d, "documents"))


def op2_decontaminate(spark, d):
    return decontamination.digest(table(spark, d, "documents"), table(spark, d, "benchmark"))


def op3_near_duplicates(spark, d):
    return near_duplicates.near_duplicates(table(spark, d, "documents"), shingle=2)


def op4_license_scan(spark, d):
    return licenses.digest(table(spark, d, "documents"))


def op5_rp_forest(spark, d):
    return forest.neighbours(table(spark, d, "embeddings"))


def op6_gated_lm(spark, d):
    return language_model.digest(table(spark, d, "documents"))


def op7_line_dedup(spark, d):
    return line_dedup.digest(table(spark, d, "documents"))


def op8_substring_dedup(spark, d):
    return substring_dedup.digest(table(spark, d, "documents"))


#: Target weights of the mix by source; every other source has OTHER.
TARGETS = {"src0": "0.2", "src1": "0.12", "src2": "0.08"}
OTHER = "0.02"


def op9_pfair_mix(spark, d):
    docs = table(spark, d, "documents").select("doc_id", "source", F.md5(F.coalesce("text", F.lit(""))).alias("text_md5"))
    return pfair.mix(docs, TARGETS, other=OTHER, spread=["doc_id"])


def op10_nnpu_toxicity(spark, d):
    return toxicity.digest(table(spark, d, "documents"), table(spark, d, "labels"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: v for k, v in globals().items() if k.startswith("op") and k[2].isdigit()}


_WORDS = "regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"
_BLANK_LOWER = "regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+')"
_BLANK = "regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')"

_OP2 = f"""
with d as (select doc_id, coalesce({_WORDS}, []) w from documents),
b as (select item_id, {_WORDS} w from benchmark),
g as (select item_id, case when len(w) < 10 then w else w[i:i + 9] end g
      from (select item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) i from b where len(w) > 0)),
sizes as (select distinct len(g) k from g),
wins as (select doc_id, i, k, w[i:i + k - 1] g from (select doc_id, w, k, unnest(range(1, len(w) - k + 2)) i from d, sizes where len(w) >= k)),
hits as (select doc_id, i, k, item_id from wins join g using (g)),
words as (select doc_id, count(distinct p) n from (select doc_id, unnest(range(i, i + k)) p from hits) group by doc_id),
items as (select doc_id, count(*) n, string_agg(item_id::varchar, ',' order by item_id::varchar) l from (select distinct doc_id, item_id from hits) group by doc_id)
select d.doc_id, len(w)::bigint n_words, coalesce(words.n, 0)::bigint n_hit, coalesce(items.n, 0)::bigint n_items,
       sha256(coalesce(l, '')) items_sha256, coalesce(words.n, 0) > 0 contaminated
from d left join words using (doc_id) left join items using (doc_id)
"""

_OP3 = f"""
with recursive d as (select doc_id, coalesce({_BLANK_LOWER}, []) w from documents),
s as (select doc_id, list_distinct(case when len(w) = 0 then [] when len(w) = 1 then w
      else list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) end) s from d),
x as (select doc_id, unnest(s) t from s),
n as (select doc_id, len(s) n from s),
i as (select a.doc_id a, b.doc_id b, count(*) k from x a join x b on a.t = b.t and a.doc_id <> b.doc_id group by 1, 2),
e as (select a, b from i join n na on a = na.doc_id join n nb on b = nb.doc_id where 100 * k >= 80 * (na.n + nb.n - k)),
r(doc_id, c) as (select doc_id, doc_id from n union select r.doc_id, e.b from r join e on r.c = e.a)
select n.doc_id, n.n::bigint n_shingles, min(c) component_id, n.doc_id = min(c) kept from n join r using (doc_id) group by n.doc_id, n.n
"""

_OP7 = """
with l as (select doc_id, i, line, trim(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), E' \\t\\n\\x0B\\x0C\\r') k
           from (select doc_id, unnest(string_split(coalesce(text, ''), E'\\n')) line, generate_subscripts(string_split(coalesce(text, ''), E'\\n'), 1) i from documents)),
m as (select k, min(doc_id) f from l where length(k) >= 10 group by k having count(distinct doc_id) > 1),
j as (select l.*, m.k is not null and doc_id <> f lost from l left join m on l.k = m.k)
select doc_id, count(*)::bigint n_lines, count(*) filter (where lost)::bigint n_dropped,
       sha256(coalesce(string_agg(line, E'\\n' order by i) filter (where not lost), '')) kept_sha256 from j group by doc_id
"""

_OP8 = f"""
with d as (select doc_id, coalesce({_BLANK}, []) w from documents),
g as (select doc_id, i, md5(array_to_string(w[i:i + 49], ' ')) g from (select doc_id, w, unnest(range(1, len(w) - 48)) i from d where len(w) >= 50)),
m as (select g, min(doc_id) f from g group by g),
lost as (select distinct doc_id, unnest(range(i, i + 50)) p from g join m using (g) where f < doc_id),
w as (select doc_id, unnest(w) t, generate_subscripts(w, 1) p from d),
k as (select w.doc_id, count(*) n, string_agg(t, ' ' order by w.p) s from w left join lost on w.doc_id = lost.doc_id and w.p = lost.p where lost.p is null group by w.doc_id)
select d.doc_id, len(w)::bigint n_words, (len(w) - coalesce(k.n, 0))::bigint n_removed, sha256(coalesce(k.s, '')) kept_sha256 from d left join k using (doc_id)
"""


#: The earliest-deadline schedule slot by slot; ``a`` counts each source's blocks so far.
_OP9 = """
with recursive lots as (select coalesce('s:' || source, 'null') lot, any_value(case source when 'src0' then 10 when 'src1' then 6 when 'src2' then 4 else 1 end)::bigint w from documents group by 1),
g as (select list(lot order by lot) ls, list(w order by lot) ws, list_sum(list(w))::bigint d from lots),
r(t, a, pick) as (select 0::bigint, list_transform(ws, lambda x: 0::bigint), 0::bigint from g
 union all select t + 1, list_transform(range(1, len(ws) + 1), lambda k: a[k] + (case when k = p then 1 else 0 end)::bigint), p
 from (select t, a, ws, d, list_min(list_transform(list_filter(range(1, len(ws) + 1), lambda k: a[k] * d // ws[k] <= t), lambda k: struct_pack(due := ((a[k] + 1) * d + ws[k] - 1) // ws[k], k := k))).k p from r, g where t < d)),
s as (select ls[pick] lot, t - 1 spot, row_number() over (partition by pick order by t) - 1 j from r, g where t > 0),
n as (select doc_id, source, coalesce('s:' || source, 'null') lot, row_number() over (partition by source order by md5(coalesce(doc_id::varchar, ''))) - 1 p, md5(coalesce(text, '')) text_md5 from documents)
select n.doc_id, n.source, text_md5, p // 16 block, (p % 16)::int pos, p // 16 * d // w as release, ((p // 16 + 1) * d + w - 1) // w deadline, p // 16 // w * d + s.spot slot
from n join lots using (lot) cross join g join s on s.lot = n.lot and s.j = p // 16 % w
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_decontaminate": _OP2, "op3_near_duplicates": _OP3, "op7_line_dedup": _OP7, "op8_substring_dedup": _OP8, "op9_pfair_mix": _OP9}
