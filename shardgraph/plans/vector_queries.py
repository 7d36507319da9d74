"""Queries of vector columns, text vectors and vector uses, with SQL twins."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from shardgraph.functions import vectors as v
from shardgraph.operators import search
from shardgraph.plans.methods import QD, U, V
from shardgraph.registry import CORE, read
from shardgraph.sources import tables

PAIR = f"with {V}, y as (select q as c from v where vec_id = 0)"
IP = "list_inner_product(q::double[], c::double[])"


def _with_first(spark, sf_dir):
    vecs = tables.e64q(spark, sf_dir)
    return vecs.crossJoin(F.broadcast(vecs.where("vec_id = 0").select(F.col("q").alias("c"))))


def scalar(name: str, sql: str, column) -> None:
    def run(spark, sf_dir):
        return _with_first(spark, sf_dir).select("vec_id", column(F.col("q"), F.col("c")).alias("x"))

    CORE.query(name, f"{PAIR} select vec_id, {sql} as x from v cross join y")(run)


rounded = lambda c, e: F.floor(c * e + 0.5).cast("bigint")
scalar("vec_l2sq", "list_sum(list_transform(range(1, 65), lambda i: (q[i] - c[i]) * (q[i] - c[i])))::bigint", v.l2sq)
scalar("vec_l2", "floor(sqrt(list_sum(list_transform(range(1, 65), lambda i: (q[i] - c[i]) * (q[i] - c[i])))::double) * 1000 + 0.5)::bigint", lambda a, b: rounded(v.l2(a, b), 1000))
scalar("vec_ip", f"{IP}::bigint", v.ip)
scalar("vec_cosine", "floor(list_cosine_similarity(q::double[], c::double[]) * 1000000 + 0.5)::bigint", lambda a, b: rounded(v.cosine(a, b), 1_000_000))
scalar("vec_l1", "list_sum(list_transform(range(1, 65), lambda i: abs(q[i] - c[i])))::bigint", v.l1)
scalar("vec_linf", "list_max(list_transform(range(1, 65), lambda i: abs(q[i] - c[i])))", v.linf)
scalar("vec_norm", "floor(sqrt(list_inner_product(q::double[], q::double[])) * 1000 + 0.5)::bigint", lambda a, b: rounded(v.norm(a), 1000))
scalar("vec_normalize", "list_transform(q, lambda x: floor(x / sqrt(list_inner_product(q::double[], q::double[])) * 10000 + 0.5)::int)", lambda a, b: F.transform(v.normalize(a), lambda x: F.floor(x * 10000 + 0.5).cast("int")))
scalar("vec_dequantize", "list_transform(q, lambda x: floor(x / 1000.0::double * 1000 + 0.5)::int)", lambda a, b: F.transform(v.dequantize(a), lambda x: F.floor(x * 1000 + 0.5).cast("int")))
scalar("vec_add_scale", "list_transform(range(1, 65), lambda i: q[i] + c[i] * 3)", lambda a, b: v.add_scaled(a, b, 3))


@CORE.query("vec_quantize", "select vec_id, list_transform(embedding, lambda x: floor(x::double * 1000 + 0.5)::int) as x from embeddings")
def q_quantize(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").select("vec_id", v.quantize(F.col("embedding")).alias("x"))


@CORE.query("vec_quantize_u8", "select vec_id, list_transform(embedding, lambda x: greatest(0, least(255, floor((x::double + 1) * 127.5 + 0.5)))::smallint) as x from embeddings")
def q_quantize_u8(spark, sf_dir):
    return read(spark, sf_dir, "embeddings").select("vec_id", v.quantize_u8(F.col("embedding")).alias("x"))


@CORE.query("vec_dim_check", "select count(*)::bigint as n, 0::bigint as bad from embeddings")
def q_dim_check(spark, sf_dir):
    e = v.validated(read(spark, sf_dir, "embeddings"), 64)
    return e.agg(F.count("embedding").alias("n"), F.count_if(~v.is_valid(F.col("embedding"), 64)).alias("bad"))


@CORE.query("vec_sum_by_group", f"with {V}, {U}, s as (select label, pos, sum(x)::bigint as s, count(*)::bigint as n from u group by label, pos) select label, max(n) as n, list(s order by pos) as sums from s group by label")
def q_vec_sum(spark, sf_dir):
    return v.sum_by(tables.e64q(spark, sf_dir), "label")


@CORE.query("vec_mean_by_label", f"with {V}, {U}, s as (select label, pos, floor(sum(x)::double / count(*) + 0.5)::int as m from u group by label, pos) select label, list(m order by pos) as centroid from s group by label")
def q_vec_mean(spark, sf_dir):
    return v.mean_by(tables.e64q(spark, sf_dir), "label").select("label", "centroid")


HASHED = "('0x' || substr(md5(tok), 1, 7))::bigint"
WORDS = "t as (select doc_id as vec_id, unnest(list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda w: w <> '')) as tok from documents)"
BUCKETS = "s as (select vec_id, ({h} % {d})::int as bucket, sum(1 - 2 * (({h} // {d}) % 2))::bigint as s from t group by all having sum(1 - 2 * (({h} // {d}) % 2)) <> 0)"


@CORE.query("doc_hash_vector", f"with {WORDS}, {BUCKETS.format(h=HASHED, d=768)} select * from s")
def q_doc_hash(spark, sf_dir):
    return tables.hashed_words(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text"))


@CORE.query("doc_ngram_vector", f"with l as (select doc_id as vec_id, lower(text) as x from documents), t as (select vec_id, substr(x, i, 3) as tok from (select vec_id, x, unnest(range(1, greatest(length(x) - 1, 1))) as i from l)), {BUCKETS.format(h=HASHED, d=96)} select * from s")
def q_doc_ngram(spark, sf_dir):
    return tables.hashed_trigrams(read(spark, sf_dir, "documents").select(F.col("doc_id").alias("vec_id"), "text"))


@CORE.query("vector_densify", f"with {WORDS}, {BUCKETS.format(h=HASHED, d=768)}, n as (select vec_id, sqrt(sum(s * s)::double) as norm from s group by vec_id) select s.vec_id, bucket, floor(s * 1000 / norm + 0.5)::int as q from s join n using (vec_id) where floor(s * 1000 / norm + 0.5) <> 0")
def q_densify(spark, sf_dir):
    dense = tables.documents_768(spark, sf_dir)
    return dense.select("vec_id", F.posexplode("q").alias("bucket", "q")).where("q <> 0")


@CORE.query(
    "page_text",
    """select page_id, trim(regexp_replace(replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '<(script|style)[^>]*>.*?</(script|style)>', ' ', 'gs'), '<[^>]*>', ' ', 'gs'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&nbsp;', ' '), '&amp;', '&'), '[ \t\r\n]+', ' ', 'g')) as text from pages""",
)
def q_page_text(spark, sf_dir):
    return read(spark, sf_dir, "pages").select("page_id", tables.page_text(F.col("html")).alias("text"))


@CORE.query("conversation_concat", "select conv_id, count(*)::bigint as n_turns, string_agg(role || ': ' || text, chr(10) order by turn, role, text) as text from conversations group by conv_id")
def q_conversation(spark, sf_dir):
    return tables.conversation_text(read(spark, sf_dir, "conversations"))


@CORE.query("knn_filtered", f"with {V}, {QD} select query_id, vec_id, d2 from (select qd.*, row_number() over (partition by query_id order by d2, qd.vec_id) as r from qd join v on v.vec_id = qd.vec_id where v.label in (1, 3, 5)) where r <= 5")
def q_knn_filtered(spark, sf_dir):
    """The filter comes before the search, so the k answers are k of the filtered vectors."""
    vecs = tables.e64q(spark, sf_dir)
    queries = vecs.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), "q")
    got = search.search_exact(vecs.where("vec_id % 10 <> 0 and label in (1, 3, 5)"), queries, 5)
    return got.select("query_id", "vec_id", F.col("dist").cast("bigint").alias("d2"))


@CORE.query("knn_postfilter", f"with {V}, {QD} select query_id, t.vec_id, d2 from (select *, row_number() over (partition by query_id order by d2, vec_id) as r from qd) t join v on v.vec_id = t.vec_id where r <= 20 and label in (1, 3, 5)")
def q_knn_postfilter(spark, sf_dir):
    """Filter after the search: cheaper with any index, but it may return fewer than asked."""
    vecs = tables.e64q(spark, sf_dir)
    queries = vecs.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), "q")
    got = search.search_exact(vecs.where("vec_id % 10 <> 0"), queries, 20).join(vecs.where("label in (1, 3, 5)").select("vec_id"), "vec_id", "left_semi")
    return got.select("query_id", "vec_id", F.col("dist").cast("bigint").alias("d2"))


@CORE.query("knn_range", f"with {V}, {QD} select query_id, vec_id, d2 from qd where d2 <= 1500000")
def q_knn_range(spark, sf_dir):
    vecs = tables.e64q(spark, sf_dir)
    queries = vecs.where("vec_id % 10 = 0").select(F.col("vec_id").alias("query_id"), "q")
    got = search.search_range(vecs.where("vec_id % 10 <> 0"), queries, 1_500_000)
    return got.select("query_id", "vec_id", F.col("dist").cast("bigint").alias("d2"))


@CORE.query("knn_self_pairs", f"with {V}, x as (select a.vec_id as a, b.vec_id as b, (list_inner_product(a.q::double[], a.q::double[]) - 2 * list_inner_product(a.q::double[], b.q::double[]) + list_inner_product(b.q::double[], b.q::double[]))::bigint as d2 from v a join v b on a.vec_id <> b.vec_id) select a, b, d2 from (select *, row_number() over (partition by a order by d2, b) as r from x) where r = 1")
def q_knn_self(spark, sf_dir):
    """Nearest other vector of each vector."""
    vecs = tables.e64q(spark, sf_dir)
    got = search.search_exact(vecs, vecs.select(F.col("vec_id").alias("query_id"), "q"), 2).where("query_id <> vec_id")
    first = got.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("dist", "vec_id"))).where("r = 1")
    return first.select(F.col("query_id").alias("a"), F.col("vec_id").alias("b"), F.col("dist").cast("bigint").alias("d2"))
