"""Functions in SQL, and the live index against the batch build."""

from __future__ import annotations

from liveindex.functions import udfs
from liveindex.operators import postings as P
from liveindex.registry import register
from liveindex.sources import collections as S
from liveindex.sources import querylog as L
from liveindex.streaming import ingest
from liveindex.workloads import sqlparts as Q
from liveindex.workloads.search import _QT, _all


@register("sql_udf_len", f"SELECT term, d, {Q.plen('g', 'f', 4)}::BIGINT AS bytes FROM {Q.post('docs')}")
def sql_udf_len(spark, sf_dir):
    udfs.register(spark)
    P.postings_doc(S.docs(spark, sf_dir)).createOrReplaceTempView("li_postings")
    return spark.sql("SELECT term, d, CAST(pair_len(g, f, 4) AS BIGINT) AS bytes FROM li_postings")


@register("sql_topk", f"WITH post AS MATERIALIZED {Q.counts('docs')}, s AS (SELECT d, round(sum(ln(1 + f) * ln(1 + (SELECT count(*) FROM documents) / ft::DOUBLE)), 6) AS score FROM post JOIN (SELECT term, count(*) AS ft FROM post GROUP BY term) USING (term) WHERE term IN ('the', 'und') GROUP BY d) SELECT d, score FROM s ORDER BY score DESC, d LIMIT 10")
def sql_topk(spark, sf_dir):
    udfs.register(spark)
    P.postings_doc(S.docs(spark, sf_dir)).createOrReplaceTempView("li_postings")
    n = S.table(spark, sf_dir, "documents").count()
    return spark.sql("SELECT d, round(sum(tf_idf(f, :n, ft)), 6) AS score FROM li_postings JOIN (SELECT term, count(*) AS ft FROM li_postings GROUP BY term) USING (term) WHERE term IN ('the', 'und') GROUP BY d ORDER BY score DESC, d LIMIT 10", args={"n": n})


@register("standing", f"WITH {_QT}, {_all('docs', 'c')} SELECT qid, d FROM c")
def standing(spark, sf_dir):
    return ingest.standing_queries(S.docs(spark, sf_dir), L.query_log(spark, sf_dir)).select("qid", "d")
