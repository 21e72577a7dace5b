"""The registered queries of the training-data operators, with production parameters, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import portable
from factorclust.llm import chosen_path, cross_parsing, dominance_packing, edit_join, license_diagonals, onebit_ann, rendezvous, suffix_decontam, token_arrow, warc_derivatives
from factorclust.llm.shared import bounded_batches

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
#: Vocabulary of the token operators.
VOCABULARY = "byte_bpe_50k.json"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    bounded_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path(VOCABULARY)


def query(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[f.__name__] = f
    return f


@query
def op1_onebit_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return onebit_ann.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


ORACLES["op1_onebit_neighbours"] = """
with e as materialized (select row_number() over () as rn, vec_id, embedding::DOUBLE[] as v from embeddings
     where vec_id is not null and len(embedding) > 0 and len(list_filter(embedding, lambda x: x is not null and isfinite(x))) = len(embedding) and len(list_filter(embedding, lambda x: x <> 0)) > 0),
p as (select q.rn, q.vec_id as query_id, c.vec_id, sqrt(list_sum(list_transform(list_zip(q.v, c.v), lambda x: (x[1] - x[2]) * (x[1] - x[2])))) as score from e q join e c on len(q.v) = len(c.v) and q.rn <> c.rn where q.vec_id % 100 = 0),
r as (select *, row_number() over (partition by rn order by score, vec_id) as rank from p)
select query_id, rank::INTEGER as rank, vec_id, score from r where rank <= 10
"""


@query
def op2_arrow_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_arrow.round_trip(table(spark, sf_dir, "documents"), tokenizer())


@query
def op3_chosen_path_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chosen_path.join(table(spark, sf_dir, "documents"))


@query
def op4_license_diagonals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_diagonals.scan(table(spark, sf_dir, "documents"))


def _license_sql() -> str:
    """Places of the base phrases as the contract has them."""
    phrases = ", ".join(f"({i}, '{t.label}', {t.text.split()})" for i, t in enumerate(license_diagonals.TEMPLATES) if t.base)
    return f"""
with d as (select row_number() over () as rn, doc_id, coalesce({SQL_WORDS.format(text="text")}, []) as w from documents),
p as (select * from (values {phrases}) t(id, label, want)),
hit as (select rn, label, i - 1 as i from (select rn, w, unnest(range(1, len(w) + 1)) as i from d), p where w[i:i + len(want) - 1] = want),
b as (select rn, count(*) as n_base, min(i) as first_word, max(i) as last_word, string_agg(distinct label, ',' order by label) as base_labels from hit group by rn)
select doc_id, len(w)::BIGINT as n_words, coalesce(n_base, 0)::BIGINT as n_base, first_word::BIGINT as first_word, last_word::BIGINT as last_word, coalesce(base_labels, '') as base_labels
from d left join b using (rn)
"""


@query
def license_base_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op4_license_diagonals that SQL can express."""
    return op4_license_diagonals(spark, sf_dir).select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels")


@query
def op5_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc_derivatives.build(table(spark, sf_dir, "pages"))


@query
def op6_suffix_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_decontam.report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("longest_match", "longest")


#: Words of a text column in DuckDB, as the contract defines them.
SQL_WORDS = r"regexp_extract_all(translate({text}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

ORACLES["license_base_phrases"] = _license_sql()

ORACLES["op6_suffix_decontamination"] = f"""
with d as (select doc_id, coalesce({SQL_WORDS.format(text="text")}, []) as w from documents),
b as (select item_id, w, case when len(w) < 13 then len(w) else 13 end as k
      from (select item_id, {SQL_WORDS.format(text="text")} as w from benchmark where text is not null) where len(w) > 0),
win as (select distinct item_id, k, array_to_string(w[i:i + k - 1], ' ') as g from (select item_id, k, w, unnest(range(1, len(w) - k + 2)) as i from b)),
lens as (select distinct k from win),
pos as (select doc_id, k, i, array_to_string(w[i:i + k - 1], ' ') as g
        from (select doc_id, k, w, unnest(range(1, len(w) - k + 2)) as i from d, lens where len(w) >= k)),
hits as (select distinct p.doc_id, p.i, p.k, win.item_id from pos p join win on win.k = p.k and win.g = p.g),
covered as (select doc_id, count(distinct x) as n_hit from (select doc_id, unnest(range(i, i + k)) as x from hits) group by doc_id),
named as (select doc_id, count(*) as n_items, string_agg(item_id, ',' order by item_id) as names
          from (select distinct doc_id, cast(item_id as varchar) as item_id from hits) group by doc_id)
select d.doc_id, cast(len(d.w) as bigint) as n_words, cast(coalesce(c.n_hit, 0) as bigint) as n_hit, cast(coalesce(n.n_items, 0) as bigint) as n_items,
       sha256(coalesce(n.names, '')) as items_sha256, coalesce(c.n_hit, 0) > 0 and 20 * coalesce(c.n_hit, 0) >= len(d.w) as contaminated
from d left join covered c using (doc_id) left join named n using (doc_id)
"""


@query
def benchmark_longest_matches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The longest verbatim match of each document with each benchmark item, and where it stands in both."""
    found = suffix_decontam.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", F.explode("longest").alias("m")).select("doc_id", "m.item_id", "m.words", "m.doc_word", "m.item_word")


ORACLES["benchmark_longest_matches"] = f"""
with d as (select doc_id, coalesce({SQL_WORDS.format(text="text")}, []) as w from documents),
b as (select item_id, w, case when len(w) < 13 then len(w) else 13 end as k
      from (select item_id, {SQL_WORDS.format(text="text")} as w from benchmark where text is not null) where len(w) > 0),
win as (select item_id, k, i as y, array_to_string(w[i:i + k - 1], ' ') as g, len(w) as m from (select item_id, k, w, unnest(range(1, len(w) - k + 2)) as i from b)),
lens as (select distinct k from win),
pos as (select doc_id, k, i as x, array_to_string(w[i:i + k - 1], ' ') as g from (select doc_id, k, w, unnest(range(1, len(w) - k + 2)) as i from d, lens where len(w) >= k)),
hits as (select doc_id, item_id, win.k, x, y from pos join win using (k, g)),
runs as (select *, x - row_number() over (partition by doc_id, item_id, x - y order by x) as island from hits),
long as (select doc_id, item_id, min(x) as x, min(y) as y, count(*) + max(k) - 1 as words from runs group by doc_id, item_id, x - y, island)
select doc_id, item_id::VARCHAR as item_id, words::BIGINT as words, (x - 1)::BIGINT as doc_word, (y - 1)::BIGINT as item_word
from (select *, row_number() over (partition by doc_id, item_id order by words desc, x, y) as rn from long) where rn = 1
"""


@query
def op7_edit_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edit_join.dedup(table(spark, sf_dir, "documents")).select("doc_id", "text", "n_lines", "n_removed")


@query
def op8_cross_parsing_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cross_parsing.identify(table(spark, sf_dir, "documents")).drop("bits")


@query
def op9_rendezvous_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rendezvous.place(table(spark, sf_dir, "documents"))


@query
def op10_dominance_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dominance_packing.pack(table(spark, sf_dir, "documents"), tokenizer())


ORACLES["op3_chosen_path_join"] = f"""
with recursive d as (select doc_id, {SQL_WORDS.format(text="text")} as w from documents where text is not null),
s as (select distinct doc_id, array_to_string(w[i:i + 4], ' ') as g from (select doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) as i from d where len(w) > 0)),
n as (select doc_id, count(*) as n from s group by doc_id),
p as (select a.doc_id as a, b.doc_id as b, count(*) as c from s a join s b on a.g = b.g and a.doc_id <> b.doc_id group by 1, 2),
l as materialized (select p.a, p.b from p join n x on x.doc_id = p.a join n y on y.doc_id = p.b where p.c >= 0.8 * (x.n + y.n - p.c) - 1e-9),
r as (select a, b from l union select r.a, l.b from r join l on l.a = r.b),
m as (select a, min(b) as least from r group by a), k as (select a, count(*) as links from l group by a)
select t.doc_id, least(t.doc_id, coalesce(m.least, t.doc_id)) as class_id, coalesce(k.links, 0)::BIGINT as n_links, coalesce(n.n, 0)::BIGINT as n_shingles
from documents t left join n on n.doc_id = t.doc_id left join m on m.a = t.doc_id left join k on k.a = t.doc_id
"""

ORACLES["op7_edit_line_dedup"] = """
with recursive ea as (select doc_id, unnest(range(1, len(string_split(text, chr(10))) + 1)) as pos, string_split(text, chr(10)) as ls from documents),
lines as materialized (select doc_id, pos, ls[pos] as raw, trim(ls[pos], ' ') as line from ea),
u as materialized (select distinct line, length(line) as n from lines where length(line) >= 16),
c as (select a.line as a, b.line as b from u a join u b on b.n = a.n and left(b.line, a.n // 2) = left(a.line, a.n // 2) and a.line < b.line
      union select a.line, b.line from u a join u b on b.n = a.n and right(b.line, a.n - a.n // 2) = right(a.line, a.n - a.n // 2) and a.line < b.line
      union select a.line, b.line from u a join u b on b.n = a.n + 1 and left(b.line, a.n // 2) = left(a.line, a.n // 2)
      union select a.line, b.line from u a join u b on b.n = a.n + 1 and right(b.line, a.n - a.n // 2) = right(a.line, a.n - a.n // 2)),
e as materialized (select a, b from c where case when length(a) = length(b)
      then len(list_filter(list_zip(string_split(a, ''), string_split(b, '')), lambda x: x[1] <> x[2])) <= 1
      else len(list_filter(range(0, length(a) + 1), lambda i: left(a, i) = left(b, i) and right(a, length(a) - i) = right(b, length(a) - i))) > 0 end),
bo as materialized (select a, b from e union select b, a from e),
r as (select a, b from bo union select r.a, bo.b from r join bo on bo.a = r.b),
kl as (select a as line, least(a, min(b)) as name from r group by a),
named as (select l.*, coalesce(k.name, l.line) as name from lines l left join kl k on k.line = l.line),
ranked as (select *, line = '' or row_number() over (partition by name order by doc_id, pos) = 1 as stays from named)
select d.doc_id, case when d.text is null then null else coalesce(string_agg(k.raw, chr(10) order by k.pos) filter (where k.stays), '') end as text,
       count(k.pos) as n_lines, count(*) filter (where not k.stays) as n_removed
from documents d left join ranked k on k.doc_id = d.doc_id group by d.doc_id, d.text
"""


def _shard_sql(shards: int) -> str:
    """The shard with the largest draw (all weights are equal); the smaller one of equals."""
    draws = ", ".join(f"('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null') || '/{i}'), 1, 13))::BIGINT" for i in range(shards))
    return f"(list_position([{draws}], list_max([{draws}])) - 1)::INTEGER"


ORACLES["op9_rendezvous_sharding"] = f"""
with t as (select list(v order by k) as tbl from (select k, list_reduce(list_prepend(k, range(8)), lambda c, i: case when c & 1 = 1 then xor(c >> 1, 3988292384) else c >> 1 end) as v from (select unnest(range(256)) as k))),
b as (select doc_id, hex(encode(coalesce(text, ''))) as h, octet_length(encode(coalesce(text, ''))) as n from documents),
l as (select doc_id, n, list_transform(range(n), lambda i: ('0x' || h[2 * i + 1 : 2 * i + 2])::BIGINT) as bytes from b),
p as (select doc_id, (n + 1)::BIGINT as size, xor(list_reduce(list_prepend(4294967295::BIGINT, bytes), lambda c, x: xor(c >> 8, tbl[xor(c & 255, x) + 1])), 4294967295::BIGINT) as text_crc32,
      {_shard_sql(8)} as shard, {_shard_sql(9)} as grown_shard, {portable.mix_sql("coalesce(doc_id, 0)", 0, 0)} % 256 as part from l, t)
select doc_id, size, text_crc32, 'key' as law, shard, row_number() over (partition by shard order by part, doc_id) - 1 as slot, grown_shard from p
"""
