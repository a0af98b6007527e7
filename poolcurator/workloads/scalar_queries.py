"""Queries of scalar, nested, JSON and vector functions, and of the extension surface."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from poolcurator.functions import text as X
from poolcurator.registry import query
from poolcurator.workloads.common import FDOC, NOISE_SQL, r6, read_table, share_sql, tokens_sql


def docs(spark, d):
    return read_table(spark, d, "documents")


@query("str_case_trim", "SELECT p_partkey, upper(p_name) AS u, lower(p_brand) AS l, trim(concat('  ', p_type, ' ')) AS t, lpad(p_size::varchar, 4, '0') AS p, reverse(p_brand) AS r FROM part")
def str_case_trim(spark, d):
    return read_table(spark, d, "part").select("p_partkey", F.upper("p_name").alias("u"), F.lower("p_brand").alias("l"), F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("t"), F.lpad(F.col("p_size").cast("string"), 4, "0").alias("p"), F.reverse("p_brand").alias("r"))


@query("str_split_join", "SELECT p_partkey, split_part(p_name, ' ', 1) AS first, array_to_string(string_split(p_name, ' '), '-') AS joined, len(string_split(p_name, ' '))::int AS n FROM part")
def str_split_join(spark, d):
    parts = F.split("p_name", " ")
    return read_table(spark, d, "part").select("p_partkey", F.split_part("p_name", F.lit(" "), F.lit(1)).alias("first"), F.array_join(parts, "-").alias("joined"), F.size(parts).alias("n"))


@query("str_regex", "SELECT doc_id, regexp_extract(text, '([A-Za-z]+)', 1) AS word, md5(regexp_replace(text, '[aeiou]', '_', 'g')) AS masked, len(regexp_extract_all(text, '[0-9]+')) AS numbers FROM documents")
def str_regex(spark, d):
    return docs(spark, d).select("doc_id", F.regexp_extract("text", "([A-Za-z]+)", 1).alias("word"), F.md5(F.regexp_replace("text", "[aeiou]", "_")).alias("masked"), F.regexp_count("text", F.lit("[0-9]+")).cast("long").alias("numbers"))


@query("str_hash", "SELECT doc_id, md5(text) AS m, sha256(text) AS s, md5(to_base64(encode(text))) AS b FROM documents")
def str_hash(spark, d):
    return docs(spark, d).select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"), F.md5(F.translate(F.base64(F.encode("text", "UTF-8")), "\r\n", "")).alias("b"))


@query("str_distance", "SELECT n_nationkey, levenshtein(n_name, 'FRANCE')::int AS d FROM nation")
def str_distance(spark, d):
    return read_table(spark, d, "nation").select("n_nationkey", F.levenshtein("n_name", F.lit("FRANCE")).alias("d"))


@query("math_basic", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS l, round(sqrt(l_quantity), 6) AS s, round(pow(l_discount, 2), 9) AS p, greatest(l_tax, l_discount) AS g, sign(l_quantity - 25)::double AS sg FROM lineitem")
def math_basic(spark, d):
    return read_table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", r6(F.log("l_extendedprice")).alias("l"), r6(F.sqrt("l_quantity")).alias("s"), F.round(F.pow("l_discount", F.lit(2)), 9).alias("p"), F.greatest("l_tax", "l_discount").alias("g"), F.signum(F.col("l_quantity") - 25).alias("sg"))


@query("math_round", "SELECT o_orderkey, round(o_totalprice / 7, 4) AS r, floor(o_totalprice)::bigint AS f, ceil(o_totalprice)::bigint AS c FROM orders")
def math_round(spark, d):
    return read_table(spark, d, "orders").select("o_orderkey", F.round(F.col("o_totalprice") / 7, 4).alias("r"), F.floor("o_totalprice").alias("f"), F.ceil("o_totalprice").alias("c"))


@query("math_bucket", "SELECT o_orderkey, CASE WHEN o_totalprice < 0 THEN 0 WHEN o_totalprice >= 400000 THEN 9 ELSE (o_totalprice / 50000)::int - CASE WHEN (o_totalprice / 50000)::int > o_totalprice / 50000 THEN 1 ELSE 0 END + 1 END AS b, o_custkey % 7 AS m FROM orders")
def math_bucket(spark, d):
    return read_table(spark, d, "orders").select("o_orderkey", F.width_bucket("o_totalprice", F.lit(0.0), F.lit(400000.0), F.lit(8)).alias("b"), F.pmod("o_custkey", F.lit(7)).alias("m"))


@query("math_safe", "SELECT doc_id, CASE WHEN doc_id % 5 = 0 THEN NULL ELSE n_chars / (doc_id % 5) END AS q, try_cast(source AS int) AS i FROM documents")
def math_safe(spark, d):
    return docs(spark, d).select("doc_id", F.try_divide("n_chars", F.col("doc_id") % 5).alias("q"), F.col("source").try_cast("int").alias("i"))


@query("date_trunc_diff", "SELECT o_orderkey, date_trunc('month', o_orderdate)::timestamp AS m, date_diff('day', o_orderdate::date, DATE '1999-01-01')::int AS days FROM orders")
def date_trunc_diff(spark, d):
    return read_table(spark, d, "orders").select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("m"), F.datediff(F.lit("1999-01-01").cast("date"), F.to_date("o_orderdate")).alias("days"))


@query("date_parts", "SELECT l_orderkey, l_linenumber, year(l_shipdate)::int AS y, month(l_shipdate)::int AS m, day(l_shipdate)::int AS d, quarter(l_shipdate)::int AS q FROM lineitem")
def date_parts(spark, d):
    return read_table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", F.year("l_shipdate").alias("y"), F.month("l_shipdate").alias("m"), F.dayofmonth("l_shipdate").alias("d"), F.quarter("l_shipdate").alias("q"))


@query("date_add", "SELECT o_orderkey, (o_orderdate::date + INTERVAL 1 MONTH)::date AS m, (o_orderdate::date + 10)::date AS t FROM orders")
def date_add(spark, d):
    return read_table(spark, d, "orders").select("o_orderkey", F.add_months(F.to_date("o_orderdate"), 1).alias("m"), F.date_add(F.to_date("o_orderdate"), 10).alias("t"))


@query("arr_hof", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::int AS positive, round(list_sum(list_transform(embedding::double[], lambda x: x * x)), 6) AS energy, list_bool_or(list_transform(embedding, lambda x: x > 0.3)) AS large FROM embeddings")
def arr_hof(spark, d):
    e = "embedding"
    return read_table(spark, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).alias("positive"), r6(X.dot(e, e)).alias("energy"), F.exists(e, lambda x: x > 0.3).alias("large"))


TWO = f"{FDOC}, two AS (SELECT sample_id AS doc_id, list_distinct({tokens_sql('instruction')}) AS a, list_distinct({tokens_sql('output')}) AS b FROM fdoc)"


@query("arr_sets", f"WITH {TWO} SELECT doc_id, list_sort(list_intersect(a, b)) AS i, list_sort(list_filter(a, lambda x: NOT list_contains(b, x))) AS e, len(list_distinct(list_concat(a, b)))::int AS u, list_has_any(a, b) AS o FROM two")
def arr_sets(spark, d):
    t = docs(spark, d).select("doc_id", F.array_distinct(X.tokens(X.lead_line("text"))).alias("a"), F.array_distinct(X.tokens(X.rest_lines("text"))).alias("b"))
    return t.select("doc_id", F.sort_array(F.array_intersect("a", "b")).alias("i"), F.sort_array(F.array_except("a", "b")).alias("e"), F.size(F.array_union("a", "b")).alias("u"), F.arrays_overlap("a", "b").alias("o"))


@query("arr_explode", "SELECT vec_id, i::int AS i, x FROM (SELECT vec_id, unnest(range(3)) AS i, unnest(embedding[1:3]) AS x FROM embeddings)")
def arr_explode(spark, d):
    return read_table(spark, d, "embeddings").select("vec_id", F.posexplode(F.slice("embedding", 1, 3)).alias("i", "x"))


@query("arr_zip", "SELECT vec_id, round(list_inner_product(embedding[1:32]::double[], embedding[33:64]::double[]), 6) AS p FROM embeddings")
def arr_zip(spark, d):
    z = F.arrays_zip(F.slice("embedding", 1, 32).alias("a"), F.slice("embedding", 33, 32).alias("b"))
    return read_table(spark, d, "embeddings").select("vec_id", r6(F.aggregate(z, F.lit(0.0), lambda s, t: s + t["a"].cast("double") * t["b"].cast("double"))).alias("p"))


@query("map_ops", "SELECT doc_id, quality * 4 + 1 AS clean, 5 - toxic * 4 AS safe, round((quality * 4 + 1) * 0.6 + (5 - toxic * 4) * 0.4, 6)::double AS q FROM labels")
def map_ops(spark, d):
    scores = F.create_map(F.lit("clean"), F.col("quality") * 4 + 1, F.lit("safe"), 5 - F.col("toxic") * 4)
    weights = F.map_from_arrays(F.array(F.lit("clean"), F.lit("safe")), F.array(F.lit(0.6), F.lit(0.4)))
    m = F.map_zip_with(scores, weights, lambda k, s, w: s * w)
    return read_table(spark, d, "labels").select("doc_id", F.element_at(scores, "clean").alias("clean"), F.element_at(scores, "safe").alias("safe"), r6(F.aggregate(F.map_values(m), F.lit(0.0), lambda a, x: a + x)).alias("q"))


@query("json_extract", "SELECT event_id, (props::json->>'$.k') AS k FROM events")
def json_extract(spark, d):
    return read_table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@query("json_schema", "SELECT event_id, try_cast(props::json->>'$.k' AS int) AS k FROM events")
def json_schema(spark, d):
    return read_table(spark, d, "events").select("event_id", F.from_json("props", "k int").alias("p")).select("event_id", F.col("p.k").alias("k"))


@query("variant_path", "SELECT event_id, try_cast(props::json->>'$.k' AS bigint) AS k FROM events")
def variant_path(spark, d):
    return read_table(spark, d, "events").select("event_id", F.try_variant_get(F.try_parse_json("props"), "$.k", "bigint").alias("k"))


@query("struct_ops", "SELECT doc_id, lang AS a, n_chars + 1 AS b FROM documents")
def struct_ops(spark, d):
    s = docs(spark, d).select("doc_id", F.struct("lang", "n_chars", "source").alias("s"))
    s = s.withColumn("s", F.col("s").withField("n_chars", F.col("s.n_chars") + 1).dropFields("source"))
    return s.select("doc_id", F.col("s.lang").alias("a"), F.col("s.n_chars").alias("b"))


E0 = "(SELECT embedding::double[] AS e FROM embeddings WHERE vec_id = 0)"


@query("vec_cosine", f"SELECT vec_id, round(list_cosine_similarity(embedding::double[], e), 6) AS c FROM embeddings, {E0}")
def vec_cosine(spark, d):
    v = read_table(spark, d, "embeddings")
    one = v.where("vec_id = 0").select(F.col("embedding").alias("e"))
    return v.crossJoin(F.broadcast(one)).select("vec_id", r6(X.cosine("embedding", "e")).alias("c"))  # one row


@query("vec_topk", f"SELECT vec_id, round(list_cosine_similarity(embedding::double[], e), 6) AS c FROM embeddings, {E0} ORDER BY c DESC, vec_id LIMIT 10")
def vec_topk(spark, d):
    return vec_cosine(spark, d).orderBy(F.desc("c"), "vec_id").limit(10)


@query("vec_centroid", "SELECT label, i::int AS i, round(avg(x), 6) AS v FROM (SELECT label, unnest(range(64)) AS i, unnest(embedding::double[]) AS x FROM embeddings) GROUP BY ALL")
def vec_centroid(spark, d):
    return read_table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(r6(F.avg(F.col("x").cast("double"))).alias("v"))


@query("udf_sql", f"SELECT doc_id, round({share_sql('text', '[A-Za-z]')}, 6) AS en, round({share_sql('text', NOISE_SQL)}, 6) AS noise FROM documents")
def udf_sql(spark, d):
    X.register_sql_functions(spark)
    docs(spark, d).createOrReplaceTempView("pc_documents")
    return spark.sql("SELECT doc_id, round(en_ratio(text), 6) AS en, round(noise_ratio(text), 6) AS noise FROM pc_documents")


@F.pandas_udf(T.LongType())
def _longest_word(s: pd.Series) -> pd.Series:
    return s.map(lambda t: max(map(len, t.split()), default=0))


@query("udf_arrow", r"SELECT doc_id, list_max(list_transform(regexp_extract_all(text, '[^ \n\t\r]+'), lambda w: length(w))) AS n FROM documents")
def udf_arrow(spark, d):
    return docs(spark, d).select("doc_id", _longest_word("text").alias("n"))


@query("udf_pandas_grouped", "SELECT label, count(*) AS n, round(sqrt(sum(m * m)), 6) AS norm FROM (SELECT label, i, avg(x) AS m, count(*) AS c FROM (SELECT label, unnest(range(64)) AS i, unnest(embedding::double[]) AS x FROM embeddings) GROUP BY label, i) GROUP BY label")
def udf_pandas_grouped(spark, d):
    """Grouped map over the bounded per-label means (64 rows a label), not over raw groups."""
    means = read_table(spark, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x")).groupBy("label", "i").agg(F.avg(F.col("x").cast("double")).alias("m"))

    def norm(g: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"label": [int(g["label"].iloc[0])], "n": [len(g)], "norm": [round(float(np.linalg.norm(g["m"])), 6)]})

    return means.groupBy("label").applyInPandas(norm, "label int, n long, norm double")


@F.pandas_udf(T.DoubleType())
def _geometric_mean(v: pd.Series) -> float:
    return float(np.exp(np.log(v).mean()))


@query("udaf_pandas", "SELECT lang, round(exp(avg(ln(n))), 4) AS g FROM (SELECT lang, n_chars AS n FROM documents) GROUP BY lang")
def udaf_pandas(spark, d):
    return docs(spark, d).groupBy("lang").agg(F.round(_geometric_mean("n_chars"), 4).alias("g"))


@udtf(returnType=T.StructType().add("pos", T.IntegerType()).add("shingle", T.StringType()))
class Shingles:
    """Runs of n words of a text."""

    def eval(self, text: str, n: int) -> Iterator[tuple]:
        words = (text or "").lower().split()
        for i in range(len(words) - n + 1):
            yield i, " ".join(words[i : i + n])


@udtf(returnType=T.StructType().add("step", T.IntegerType()).add("body", T.StringType()))
class SplitSteps:
    """Non-empty lines of a text as numbered steps."""

    def eval(self, text: str) -> Iterator[tuple]:
        for i, line in enumerate(x for x in (text or "").split("\n") if x.strip()):
            yield i, line


@query("udtf_shingles", r"WITH w AS (SELECT item_id, regexp_extract_all(lower(text), '[^ \n\t\r]+') AS w FROM benchmark) SELECT item_id, (i - 1)::int AS pos, array_to_string(w[i:i + 4], ' ') AS shingle FROM (SELECT item_id, w, unnest(range(1, len(w) - 3)) AS i FROM w)")
def udtf_shingles(spark, d):
    spark.udtf.register("pc_shingles", Shingles)
    read_table(spark, d, "benchmark").createOrReplaceTempView("pc_benchmark")
    return spark.sql("SELECT item_id, pos, shingle FROM pc_benchmark, LATERAL pc_shingles(text, 5)")


@udtf(returnType=T.StructType().add("conv_id", T.LongType()).add("turn", T.LongType()).add("prompt", T.StringType()).add("answer", T.StringType()))
class ChatPairs:
    """User turns and the assistant turns that follow them, of a table partitioned by conversation and ordered by turn."""

    def __init__(self):
        self.last = None

    def eval(self, row) -> Iterator[tuple]:
        if row["role"] == "assistant" and self.last is not None:
            yield row["conv_id"], self.last["turn"], self.last["text"], row["text"]
        self.last = row if row["role"] == "user" else None


@query("udtf_chat_pairs", """SELECT conv_id, turn, text AS prompt, said AS answer FROM (SELECT *, lead(role) OVER w AS next_role, lead(text) OVER w AS said FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn))
  WHERE role = 'user' AND next_role = 'assistant'""")
def udtf_chat_pairs(spark, d):
    """A table function with a partitioned table argument: state lives within a conversation."""
    spark.udtf.register("pc_chat_pairs", ChatPairs)
    read_table(spark, d, "conversations").createOrReplaceTempView("pc_conversations")
    return spark.sql("SELECT conv_id, turn, prompt, answer FROM pc_chat_pairs(TABLE(SELECT conv_id, turn, role, text FROM pc_conversations) PARTITION BY conv_id ORDER BY turn)")


@query("udf_cogrouped", "SELECT coalesce(c.k, s.k) AS nation, coalesce(c.n, 0) AS customers, coalesce(s.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY ALL) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY ALL) s ON c.k = s.k")
def udf_cogrouped(spark, d):
    """Two tables' counts by nation and segment meet in a cogrouped map; raw rows are added up before it."""
    c = read_table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    s = read_table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("n"))

    def both(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"nation": [key[0]], "customers": [int(a["n"].sum())], "suppliers": [int(b["n"].sum())]})

    kind = dict(c.dtypes)["k"]
    return c.groupBy("k").cogroup(s.groupBy("k")).applyInPandas(both, f"nation {kind}, customers long, suppliers long")


@query("udtf_steps", "SELECT item_id, count(*) AS steps FROM (SELECT item_id, unnest(string_split(text, chr(10))) AS line FROM benchmark) WHERE trim(line) <> '' GROUP BY item_id")
def udtf_steps(spark, d):
    spark.udtf.register("pc_steps", SplitSteps)
    read_table(spark, d, "benchmark").createOrReplaceTempView("pc_benchmark")
    return spark.sql("SELECT item_id, count(*) AS steps FROM pc_benchmark, LATERAL pc_steps(text) GROUP BY item_id")
