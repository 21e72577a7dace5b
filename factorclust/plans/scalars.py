"""Scalar functions around the method, each beside its SQL: vectors, text, dates, JSON, maps, conditionals, draws."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from factorclust.functions import portable, vectors
from factorclust.functions.udfs import gram_by
from factorclust.plans.pieces import r6
from factorclust.registry import register, register_sql
from factorclust.sources.points import from_embeddings
from factorclust.sources.tables import read_table

_PAIR = "p as (select a.vec_id as id, j, a.embedding[j + 1]::DOUBLE as x, b.embedding[j + 1]::DOUBLE as y from embeddings a join embeddings b on b.vec_id = a.vec_id + 1, (select unnest(range(64)) as j))"


def pair(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each vector x beside the next one, y."""
    e = from_embeddings(spark, sf_dir)
    return e.select("id", "x").join(e.select((F.col("id") - 1).alias("id"), F.col("x").alias("y")), "id")


@register(f"with {_PAIR} select id, round(sum(x * y), 6) + 0.0 as dot, round(sum(x * x), 6) as norm2, round(sum((x - y) * (x - y)), 6) as sqdist, round(sum(x * y) / sqrt(sum(x * x) * sum(y * y)), 6) + 0.0 as cosine from p group by id")
def vec_products(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = F.col("x"), F.col("y")
    return pair(spark, sf_dir).select("id", r6(vectors.dot(x, y)).alias("dot"), r6(vectors.norm2(x)).alias("norm2"), r6(vectors.sqdist(x, y)).alias("sqdist"), r6(vectors.cosine(x, y)).alias("cosine"))


@register(f"with {_PAIR} select id, round(sum(2.5 * x + y), 6) + 0.0 as axpy, round(sum(x * y), 6) + 0.0 as mul, round(sum(greatest(x, 0)), 6) as clamp, round(sum(3 * x), 6) + 0.0 as scaled from p group by id")
def vec_arithmetic(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = F.col("x"), F.col("y")
    return pair(spark, sf_dir).select("id", r6(vectors.total(vectors.axpy(F.lit(2.5), x, y))).alias("axpy"), r6(vectors.total(vectors.mul(x, y))).alias("mul"), r6(vectors.total(vectors.clamp(x))).alias("clamp"), r6(vectors.total(vectors.scale(F.lit(3.0), x))).alias("scaled"))


@register("select vec_id as id, (list_position(embedding, list_max(embedding)) - 1)::INTEGER as hi, (list_position(embedding, list_min(embedding)) - 1)::INTEGER as lo from embeddings")
def vec_argmin_argmax(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).select("id", vectors.argmax(F.col("x")).alias("hi"), vectors.argmin(F.col("x")).alias("lo"))


@register("select vec_id as id, len(embedding[3:8])::INTEGER as n, round(embedding[3]::DOUBLE, 6) + 0.0 as first, 128::INTEGER as both, 8::INTEGER as rows from embeddings")
def vec_shapes(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = F.col("x")
    part = F.slice(x, 3, 6)
    return from_embeddings(spark, sf_dir).select("id", F.size(part).alias("n"), r6(part[0]).alias("first"), F.size(F.concat(x, x)).alias("both"), F.size(vectors.reshape(x, 8)).alias("rows"))


@register("select vec_id as id, r, round(list_sum(list_transform(range(64), lambda j: embedding[j + 1]::DOUBLE * ((r * 64 + j) % 5))), 6) + 0.0 as v from embeddings, (select unnest(range(3)) as r)")
def vec_matvec(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = F.array(*[F.array(*[F.lit(float((r * 64 + j) % 5)) for j in range(64)]) for r in range(3)])
    return from_embeddings(spark, sf_dir).select("id", F.posexplode(vectors.matvec(m, F.col("x"))).alias("r", "v")).select("id", F.col("r").cast("long"), r6(F.col("v")).alias("v"))


@register("select vec_id as id, j, (case when j = label then 1.0 else 0.0 end)::DOUBLE as v from embeddings, (select unnest(range(10)) as j)")
def one_hot_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return from_embeddings(spark, sf_dir).select("id", F.posexplode(vectors.one_hot(F.col("truth"), 10)).alias("j", "v")).withColumn("j", F.col("j").cast("long"))


@register("select vec_id as id, round(sqrt(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v))), 6) as n from embeddings")
def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The vector functions under their SQL names."""
    vectors.define_sql_functions(spark)
    return spark.sql("select id, round(sqrt(vec_norm2(x)), 6) as n from {e}", e=from_embeddings(spark, sf_dir))


@register("select l_orderkey, list_sort([l_quantity, l_discount, l_tax])[1] as low, len(list_distinct([l_quantity, l_tax]))::INTEGER as kinds, list_contains([l_quantity, l_tax], 17.0) as has, list_max([l_quantity, l_discount]) as hi from lineitem")
def array_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    q, d, t = F.col("l_quantity"), F.col("l_discount"), F.col("l_tax")
    return read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_quantity", "l_discount", "l_tax"]).select("l_orderkey", F.array_sort(F.array(q, d, t))[0].alias("low"), F.size(F.array_distinct(F.array(q, t))).alias("kinds"), F.array_contains(F.array(q, t), 17.0).alias("has"), F.array_max(F.array(q, d)).alias("hi"))


register_sql("math_functions", "select o_orderkey, round(ln(o_totalprice), 6) as l, round(sqrt(o_totalprice), 6) as s, round(power(o_totalprice, 0.25), 6) as p, round(exp(o_totalprice / 1000000), 6) as e, cast(floor(o_totalprice) as bigint) as f, cast(ceil(o_totalprice) as bigint) as c, greatest(o_totalprice, 1000) as g from {orders}", ("orders",))
register_sql("text_functions", "select doc_id, cast(length(text) as bigint) as n, lower(substring(text, 1, 12)) as head, replace(lang, 'e', 'E') as lang2, concat(lang, '-', source) as tag, upper(source) as up from {documents}", ("documents",))
register_sql("conditional_functions", "select doc_id, coalesce(cast(quality as double), 0.5) as q, nullif(toxic, 0) as t, case when quality = 1 and toxic = 0 then 'keep' when toxic = 1 then 'drop' else 'look' end as verdict from {labels}", ("labels",))


@register("select lower(chr(97 + c::INTEGER)) as letter, sum(n)::BIGINT as n from (select c, len(text) - len(replace(text, chr(97 + c::INTEGER), '')) as n from documents, (select unnest(range(26)) as c)) group by 1")
def letter_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = read_table(spark, sf_dir, "documents", ["text"])
    counts = F.array(*[F.struct(F.lit(chr(97 + c)).alias("letter"), (F.length("text") - F.length(F.replace("text", F.lit(chr(97 + c)), F.lit("")))).cast("long").alias("n")) for c in range(26)])
    return d.select(F.explode(counts).alias("e")).groupBy("e.letter").agg(F.sum("e.n").alias("n"))


@register(r"select page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) as host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) as path, regexp_extract(html, '<title>([^<]*)</title>', 1) as title, len(regexp_extract_all(html, '<p>'))::INTEGER as paragraphs from pages")
def page_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = read_table(spark, sf_dir, "pages", ["page_id", "url", "html"])
    return p.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"), F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_count("html", F.lit("<p>")).alias("paragraphs"))


register_sql("date_functions", "select event_id, year(ts) as y, month(ts) as m, day(ts) as d, hour(ts) as h, date_trunc('hour', ts) as t from {events}", ("events",), "select event_id, year(ts)::INTEGER as y, month(ts)::INTEGER as m, day(ts)::INTEGER as d, hour(ts)::INTEGER as h, date_trunc('hour', ts) as t from events")


@register("select event_id, (props->>'k')::INTEGER as k, (props->>'missing') is null as none from events")
def json_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_id", "props"])
    parsed = F.from_json("props", "k int, missing int")
    return e.select("event_id", parsed["k"].alias("k"), F.get_json_object("props", "$.missing").isNull().alias("none"))


@register("select o_orderkey, o_totalprice as price, len(o_orderpriority)::INTEGER as n from orders")
def map_struct_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_totalprice", "o_orderpriority"])
    m = F.map_from_entries(F.array(F.struct(F.lit("price"), F.col("o_totalprice"))))
    s = F.named_struct(F.lit("n"), F.length("o_orderpriority"))
    return o.select("o_orderkey", F.element_at(F.transform_values(m, lambda k, v: v), "price").alias("price"), s["n"].alias("n"))


@register(f"select event_id as id, {portable.mix_sql('event_id', 3, 11)}::BIGINT as m, round({portable.uniform_sql('event_id', 3, 11)}, 9) as u, round(" + " + ".join(portable.uniform_sql("event_id", 5 * portable.TERMS + t, 11) for t in range(portable.TERMS)) + " - 6, 6) + 0.0 as g from events")
def portable_draws(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read_table(spark, sf_dir, "events", ["event_id"]).select(F.col("event_id").alias("id"))
    i = F.col("id")
    return e.select("id", portable.mix(i, 3, 11).alias("m"), F.round(portable.uniform(i, 3, 11), 9).alias("u"), r6(portable.normal(i, 5, 11)).alias("g"))


@register("select label, a.j::INTEGER as i, b.j::INTEGER as j, round(sum(e.embedding[a.j + 1]::DOUBLE * e.embedding[b.j + 1]::DOUBLE), 6) + 0.0 as g from embeddings e, (select unnest(range(64)) as j) a, (select unnest(range(64)) as j) b where a.j <= b.j group by label, a.j, b.j")
def gram_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The Gram matrix of each label's vectors: each Arrow batch gives one packed triangle a label, which built-in sums add up."""
    return gram_by(from_embeddings(spark, sf_dir), "truth", 64).select(F.col("truth").alias("label"), "i", "j", r6(F.col("g")).alias("g"))


@register("select label, count(*) as n, round(sum(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) as energy from embeddings group by label")
def grouped_measure_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows and energy of each label by a vectorised function over batches, added up by built-in sums: no group is gathered."""
    g = gram_by(from_embeddings(spark, sf_dir), "truth", 64)
    counted = from_embeddings(spark, sf_dir).groupBy(F.col("truth").alias("label")).agg(F.count(F.lit(1)).alias("n"))
    energy = g.where("i = j").groupBy(F.col("truth").alias("label")).agg(F.round(F.sum("g"), 6).alias("energy"))
    return counted.join(energy, "label")


register_sql("cast_functions", "select doc_id, try_cast(source as int) as no_number, try_cast(substring(source, 4) as int) as number, cast(try_cast(n_chars as decimal(18, 2)) as double) as chars from {documents}", ("documents",), "select doc_id, try_cast(source as int) as no_number, try_cast(substring(source, 4) as int) as number, cast(n_chars as double) as chars from documents")


@register(r"select page_id, trim(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>[^<]*</(script|style)>|<[^>]*>', ' ', 'g'), '[ \t\r\n]+', ' ', 'g')) as text, ((length(html) - length(replace(html, '<a ', ''))) / 3)::INTEGER as links, ((length(html) - length(replace(html, '<li>', ''))) / 4)::INTEGER as items from pages")
def html_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Text without tags, and counts of tags (those in the text of a script are counted too)."""
    h = F.col("html")
    bare = F.regexp_replace(F.regexp_replace(h, "<(script|style)[^>]*>[^<]*</(script|style)>|<[^>]*>", " "), "[ \\t\\r\\n]+", " ")
    tags = lambda t: ((F.length(h) - F.length(F.replace(h, F.lit(t), F.lit("")))) / len(t)).cast("int")
    return read_table(spark, sf_dir, "pages", ["page_id", "html"]).select("page_id", F.trim(bare).alias("text"), tags("<a ").alias("links"), tags("<li>").alias("items"))


@register("select event_id, ts + interval 36 hour as later, ts - interval 2 month as before, date_diff('day', date '2024-01-01', ts::DATE)::INTEGER as day, (epoch_us(ts) // 1000000)::BIGINT as seconds, dayofweek(ts)::INTEGER + 1 as weekday, date_diff('month', date '2023-01-01', date_trunc('month', ts)::DATE)::INTEGER as month from events")
def interval_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    ts = F.col("ts")
    rows = read_table(spark, sf_dir, "events", ["event_id", "ts"]).withColumn("ts", ts.cast("timestamp_ntz"))
    return rows.select(
        "event_id", (ts + F.expr("interval 36 hours")).alias("later"), (ts - F.expr("interval 2 months")).alias("before"), F.datediff(ts, F.lit("2024-01-01")).alias("day"),
        F.unix_timestamp(ts.cast("timestamp")).alias("seconds"), F.dayofweek(ts).alias("weekday"), F.months_between(F.trunc(ts, "month"), F.lit("2023-01-01").cast("date")).cast("int").alias("month"),
    )


@register("select l_orderkey, l_linenumber, l_partkey, 'discount,quantity,tax' as names, round(l_quantity + l_discount + l_tax, 6) as total, l_discount > 0.05 as any_high, l_quantity >= 0 and l_tax >= 0 as all_set, len(list_filter([l_quantity, l_discount, l_tax], lambda x: x < 1))::INTEGER as small, len(flatten([[l_quantity], [l_discount, l_tax]]))::INTEGER as flat, l_quantity::VARCHAR as q from lineitem")
def map_array_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keys and values of a map, any and all, filter, flatten, and a map through JSON and back."""
    q, d, t = F.col("l_quantity"), F.col("l_discount"), F.col("l_tax")
    m = F.create_map(F.lit("quantity"), q, F.lit("discount"), d, F.lit("tax"), t)
    back = F.from_json(F.to_json(m), "map<string,double>")
    return read_table(spark, sf_dir, "lineitem", ["l_orderkey", "l_linenumber", "l_partkey", "l_quantity", "l_discount", "l_tax"]).select(
        "l_orderkey", "l_linenumber", "l_partkey", F.array_join(F.array_sort(F.map_keys(back)), ",").alias("names"), F.round(F.aggregate(F.map_values(back), F.lit(0.0), lambda a, x: a + x), 6).alias("total"),
        F.exists(F.array(d), lambda x: x > 0.05).alias("any_high"), F.forall(F.array(q, t), lambda x: x >= 0).alias("all_set"), F.size(F.filter(F.array(q, d, t), lambda x: x < 1)).alias("small"),
        F.size(F.flatten(F.array(F.array(q), F.array(d, t)))).alias("flat"), F.element_at(back, "quantity").cast("string").alias("q"),
    )


_NEAR = "e as (select vec_id as id, label, j, embedding[j + 1]::DOUBLE as v from embeddings, (select unnest(range(64)) as j)), m as (select label, j, avg(v) as v from e group by label, j)"


@register(f"with {_NEAR}, d as (select e.id, m.label as c, round(sum((e.v - m.v) * (e.v - m.v)), 12) as d from e join m using (j) group by e.id, m.label) select id, c as cluster from (select *, row_number() over (partition by id order by d, c) as rn from d) where rn = 1")
def assign_udf(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest class mean by the vectorised function."""
    import numpy as np

    from factorclust.functions.udfs import assign_nearest
    from factorclust.operators.partition import means

    p = from_embeddings(spark, sf_dir)
    m = np.array([r["mean"] for r in means(p, "truth").orderBy("truth").collect()])  # ten rows
    return p.select("id", assign_nearest(m)("x").alias("cluster"))
