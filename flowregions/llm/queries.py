"""Queries of the training-data operators, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from flowregions.llm import ball_tree, bpe, line_dedup, mixture, permutation_index, pseudonyms, quality, quotations, set_join, unit_dedup
from flowregions.llm.common import read


#: The key of the registered query; a user passes an own one.
PSEUDONYM_KEY = "example key of the registered query"


def tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op1_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(read(spark, sf_dir, "documents"), tokenizer())


def op2_permutation_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return permutation_index.nearest(read(spark, sf_dir, "embeddings"), every=20, k=20)


def op3_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture.plan(read(spark, sf_dir, "documents"))


def op4_pseudonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonyms.protect(read(spark, sf_dir, "documents"), key=PSEUDONYM_KEY)


def op5_ball_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ball_tree.top_products(read(spark, sf_dir, "embeddings"), every=50, k=5)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.deduplicate(read(spark, sf_dir, "documents")).select("doc_id", "text", "n_lines", "n_removed")


def op7_unit_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unit_dedup.deduplicate(read(spark, sf_dir, "documents"))


def op8_set_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return set_join.near_duplicates(read(spark, sf_dir, "documents"))


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op10_quotations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotations.conversations(read(spark, sf_dir, "conversations"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_bpe_round_trip, op2_permutation_index, op3_mixture, op4_pseudonyms, op5_ball_tree, op6_line_dedup, op7_unit_dedup, op8_set_join, op9_quality, op10_quotations)}

#: The mixture of ``documents`` as one statement; also the source of the pipeline's SQL.
MIXTURE_SQL = r"""
with sized as (
  select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size from documents
), total as (
  select source, sum(size)::bigint as source_size from sized group by source
), numbered as (
  select *, (array[5, 2, 1])[((row_number() over (order by source is null, source) - 1) % 3 + 1)::int]::bigint as w, 3 * source_size as cap from total
), level as (
  select source, source_size, w, cap,
    sum(source_size) over () - coalesce(sum(cap) over (order by cap::double / w, source is null, source rows between unbounded preceding and 1 preceding), 0) as room,
    sum(w) over (order by cap::double / w, source is null, source rows between current row and unbounded following) as behind
  from numbered
), mark as (
  select *, room::hugeint * w > cap::hugeint * behind as is_full from level
), open as (
  select room, behind from mark where not is_full order by cap::double / w, source is null, source limit 1
), target as (
  select m.source, m.source_size,
    case when m.cap::double / m.w < (select min(cap::double / w) from mark where not is_full) or m.is_full then m.cap::double
         else (m.w * o.room::double) / o.behind::double end as target
  from mark m cross join open o
), rate as (
  select s.doc_id, s.size, t.source_size, t.target, case when t.source_size > 0 then least(t.target / t.source_size, 3.0) else 0.0 end as rate
  from sized s join target t on s.source is not distinct from t.source
)
select doc_id, size, source_size, target,
  (size * (floor(rate) + case when ('0x' || substr(md5('mixture-1:' || coalesce(doc_id::varchar, 'null')), 1, 13))::bigint::double / 4503599627370496.0 < rate - floor(rate) then 1 else 0 end))::bigint as taken
from rate
"""

ORACLES: dict[str, str] = {
    "op6_line_dedup": r"""
with raw as (
  select doc_id, unnest(string_split(text, chr(10))) as line, unnest(range(len(string_split(text, chr(10))))) as n from documents where text is not null and doc_id is not null
), seq as (
  select doc_id, n, x, row_number() over (partition by doc_id order by n) - 1 as k
  from (select doc_id, n, trim(regexp_replace(lower(line), '[\x00-\x20]+', ' ', 'g')) as x from raw) z where x <> ''
), win as (
  select doc_id, k, x || chr(10) || lead(x, 1) over (partition by doc_id order by k) || chr(10) || lead(x, 2) over (partition by doc_id order by k) as w from seq
), ranked as (
  select doc_id, k, first_value(doc_id) over (partition by w order by doc_id, k) as d0, first_value(k) over (partition by w order by doc_id, k) as k0 from win where w is not null
), gone as (
  select distinct r.doc_id, r.k + t.i as k from ranked r cross join range(3) t(i)
  where (r.doc_id <> r.d0 or r.k <> r.k0) and (r.doc_id <> r.d0 or r.k + t.i >= r.k0 + 3)
), lost as (
  select s.doc_id, s.n from seq s join gone g on g.doc_id = s.doc_id and g.k = s.k
), kept as (
  select r.doc_id, string_agg(r.line, chr(10) order by r.n) as text from raw r left join lost l on l.doc_id = r.doc_id and l.n = r.n where l.n is null group by r.doc_id
), counted as (
  select doc_id, count(*)::int as removed from lost group by doc_id
)
select d.doc_id, case when c.removed is null then d.text else coalesce(k.text, '') end as text,
  case when coalesce(d.text, '') = '' then 0 else len(string_split(d.text, chr(10))) end::int as n_lines, coalesce(c.removed, 0)::int as n_removed
from documents d left join counted c on c.doc_id = d.doc_id left join kept k on k.doc_id = d.doc_id
""",
    "op8_set_join": r"""
with recursive word as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents
), shingle as (
  select distinct doc_id, unnest(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(list_slice(w, i, i + 4), ' ')) end) as s from word
), size as (
  select doc_id, count(*)::bigint as n from shingle group by doc_id
), pair as (
  select a.doc_id as x, b.doc_id as y, count(*)::bigint as c from shingle a join shingle b on a.s = b.s and a.doc_id < b.doc_id group by 1, 2
), link as (
  select x, y from pair join size p on p.doc_id = x join size q on q.doc_id = y where 100 * c >= 75 * (p.n + q.n - c)
), edge as (
  select x, y from link union all select y, x from link
), reach as (
  select doc_id as u, doc_id as v from documents union select r.u, e.y from reach r join edge e on e.x = r.v
), least_ as (
  select u, min(v) as component_id from reach group by u
)
select d.doc_id, coalesce(s.n, 0)::bigint as n_shingles, l.component_id from documents d left join size s on s.doc_id = d.doc_id join least_ l on l.u = d.doc_id
""",
    "op3_mixture": MIXTURE_SQL,
    "op5_ball_tree": """
with v as (
  select vec_id, list_transform(min(embedding), lambda x: floor(256 * x::double)) as e from embeddings
  where vec_id is not null and embedding is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0 group by vec_id
), scored as (
  select q.vec_id as query_id, c.vec_id, list_inner_product(q.e, c.e)::bigint as score
  from v q join v c on q.vec_id % 50 = 0 and q.vec_id <> c.vec_id and len(q.e) = len(c.e)
), ranked as (
  select query_id, (row_number() over (partition by query_id order by score desc, vec_id))::int as rank, vec_id, score from scored
)
select * from ranked where rank <= 5
""",
}
