"""The queries opN_<name> over whole tables, and their SQL where there is any."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from biclique_spark.llm import ann, bpe, chat, exact_dedup, mixing, ngram_join, quality, substring, token_counts, toxicity

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def query(name: str):
    def put(f):
        QUERIES[name] = f
        return f

    return put


@query("op7_exact_dedup")
def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.dedup(_table(spark, sf_dir, "documents"))


ORACLES["op7_exact_dedup"] = r"""
with t as (select doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') as clean from documents),
g as (select clean, min(doc_id) as keep_id, count(*) as group_size from t group by clean)
select doc_id, coalesce(keep_id, doc_id) as keep_id, group_size, coalesce(doc_id = keep_id, false) as kept,
       sha256(clean) as text_sha256
from t join g using (clean)
"""


@query("op8_token_counts")
def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return token_counts.token_counts(_table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"), 512)


@query("op6_byte_bpe")
def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return bpe.round_trip(_table(spark, sf_dir, "documents"), path, public_tokenizers.PATTERN)


@query("op2_chat_format")
def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "\\### Assistant: </turn> ok"
    more = spark.range(2).selectExpr("-7L as conv_id", "id as turn", "if(id = 0, 'user', 'assistant') as role").withColumn("text", F.lit(said))
    return chat.digests(chat.format_chats(turns.unionByName(more)))


# The formatted length of a turn: its text escaped, and for each run of a role the marks around it.
ORACLES["op2_chat_format"] = r"""
with t as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
           union all select -7, 0, 'user', '\### Assistant: </turn> ok'
           union all select -7, 1, 'assistant', '\### Assistant: </turn> ok'),
o as (select *, lag(role) over w as before, row_number() over w as n,
        regexp_replace(replace(text, '\', '\\'), '<(/?turn>|body>|part>)', '<\\\1', 'g') as esc,
        regexp_replace(replace(role, '\', '\\'), '<(/?turn>|body>|part>)', '<\\\1', 'g') as esc_role
      from t window w as (partition by conv_id order by turn, role, text))
select conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by n)) as turns_sha256,
  coalesce(sum(length(text)) filter (where role = 'assistant'), 0)::bigint as loss_chars,
  sha256(coalesce(string_agg(text, '' order by n) filter (where role = 'assistant'), '')) as loss_sha256,
  sum(length(esc) + case when n > 1 and before = role then 6 else 6 + length(esc_role) + 6 + 8 end)::bigint as formatted_chars
from o group by conv_id
"""


@query("op3_source_mix")
def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.taken(_table(spark, sf_dir, "documents"))


@query("op9_quality")
def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


@query("op10_toxicity")
def op10(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.toxicity(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "labels"))


@query("op1_ann")
def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


@query("op5_substring_dedup")
def op5(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring.remove_repeats(_table(spark, sf_dir, "documents"))


ORACLES["op5_substring_dedup"] = r"""
with d as (select row_number() over () as r, doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
s as (select r, doc_id, w, unnest(range(1, len(w) - 11)) as i from d where len(w) >= 13),
x as (select r, doc_id, i, array_to_string(w[i:i+12], ' ') as t from s),
f as (select t, min(doc_id) as m from x group by t having min(doc_id) < max(doc_id)),
g as (select distinct r, unnest(range(i, i + 13)) as j from x join f using (t) where doc_id > m),
p as (select r, unnest(w) as word, unnest(range(1, len(w) + 1)) as j from d),
k as (select r, string_agg(word, ' ' order by j) as kept, count(*) as n from p anti join g using (r, j) group by r)
select doc_id, len(w)::bigint as n_words, (len(w) - coalesce(n, 0))::bigint as n_removed, sha256(coalesce(kept, '')) as kept_sha256
from d left join k using (r)
"""


@query("op4_ngram_jaccard")
def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.join_components(_table(spark, sf_dir, "documents"), 4, 85)


ORACLES["op4_ngram_jaccard"] = r"""
with recursive d as materialized (select doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents),
s as materialized (select distinct doc_id, case when len(w) < 4 then array_to_string(w, ' ') else array_to_string(w[i:i+3], ' ') end as t
      from (select doc_id, w, unnest(range(1, greatest(len(w) - 3, 1) + 1)) as i from d where len(w) > 0)),
n as materialized (select doc_id, count(*) as n from s group by doc_id),
p as materialized (select a.doc_id as a, b.doc_id as b, count(*) as o from s a join s b on a.t = b.t and a.doc_id < b.doc_id group by 1, 2),
l as materialized (select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * o >= 85 * (x.n + y.n - o)),
e as materialized (select a, b from l union select b, a from l),
r as (select doc_id as a, doc_id as c from n union select e.b, r.c from r join e on e.a = r.a)
select d.doc_id, coalesce(n.n, 0) as n_shingles, coalesce(min(r.c), d.doc_id) as component_id
from d left join n using (doc_id) left join r on r.a = d.doc_id group by d.doc_id, n.n
"""
