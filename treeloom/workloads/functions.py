"""Queries through the SQL surface, and over sources and sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treeloom.engine.columnar import Columnar
from treeloom.engine.serialize import subtrees
from treeloom.functions.udfs import path_count, register_functions
from treeloom.sources.store import shared_root
from treeloom.sources.trees import open_tree, table
from treeloom.workloads.registry import register


@register("udf_path_count", "SELECT page_id, len(regexp_extract_all(html, '<a '))::BIGINT AS n FROM pages")
def udf_path_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", path_count("//li/a")("html").alias("n"))


@register("udtf_parse_tree", "SELECT page_id, len(regexp_extract_all(html, '<p>'))::BIGINT AS n FROM pages")
def udtf_parse_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_functions(spark)
    table(spark, sf_dir, "pages").createOrReplaceTempView("treeloom_pages")
    return spark.sql("SELECT p.page_id, count_if(t.label = 'p') AS n FROM treeloom_pages p, LATERAL parse_tree(p.html) t WHERE t.kind = 'elem' GROUP BY p.page_id")


@register(
    "udtf_path_query",
    "SELECT conv_id AS doc, count(*)::BIGINT AS n FROM conversations b WHERE contains(text, 'the') AND EXISTS (SELECT 1 FROM conversations a WHERE a.conv_id = b.conv_id AND a.turn < b.turn AND a.role = 'user') GROUP BY 1",
)
def udtf_path_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A path as a table function over a node table, in SQL."""
    register_functions(spark)
    open_tree(spark, sf_dir, "threads").all.createOrReplaceTempView("treeloom_threads")
    path = '//turn[@role = "user"]//turn[contains(., "the")]'
    return spark.sql(f"SELECT doc, count(*) AS n FROM path_query(TABLE(treeloom_threads) PARTITION BY (doc) ORDER BY (pre), '{path}') GROUP BY doc")


@register("udtf_locate", "SELECT item_id, unnest(list_filter(range(1, length(text) + 1), lambda i: substr(text, i, 3) = 'the'))::INTEGER AS position FROM benchmark")
def udtf_locate(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_functions(spark)
    table(spark, sf_dir, "benchmark").createOrReplaceTempView("treeloom_benchmark")
    return spark.sql("SELECT b.item_id, t.position FROM treeloom_benchmark b, LATERAL locate_all(b.text, 'the') t")


@register("udaf_longest", "SELECT p_brand, arg_min(p_name, (-length(p_name), p_name)) AS longest FROM part GROUP BY 1")
def udaf_longest(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_functions(spark)
    table(spark, sf_dir, "part").createOrReplaceTempView("treeloom_part")
    return spark.sql("SELECT p_brand, longest_string(p_name) AS longest FROM treeloom_part GROUP BY p_brand")


def _through(spark: SparkSession, df: DataFrame, fmt: str, **options: str) -> DataFrame:
    """``df`` written in a format and read again with the same schema."""
    path = f"{shared_root(spark)}/treeloom-sink-{fmt}-{uuid.uuid4().hex}"
    df.write.format(fmt).options(**options).save(path)
    return spark.read.format(fmt).schema(df.schema).options(**options).load(path)


_HITS = "SELECT doc_id AS doc, lang FROM documents WHERE lang = 'fr'"
for _fmt, _opts in {"json": {}, "csv": {"header": "true"}, "orc": {}, "parquet": {"compression": "zstd"}, "xml": {"rowTag": "hit"}}.items():

    @register(f"sink_source_{_fmt}", _HITS)
    def round_trip(spark: SparkSession, sf_dir: str, fmt: str = _fmt, opts: dict = _opts) -> DataFrame:
        """Hits of a path written to a sink and read back."""
        tree = open_tree(spark, sf_dir, "citations")
        hits = Columnar(tree).select('//citation[@lang = "fr"]').select("doc", F.lit("fr").alias("lang"))
        return _through(spark, hits, fmt, **opts)


@register("sink_partitioned", "SELECT lang, count(*)::BIGINT AS n FROM documents WHERE lang IN ('de', 'es') GROUP BY 1")
def partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A table partitioned by language: the filter prunes folders."""
    path = f"{shared_root(spark)}/treeloom-partitioned-{uuid.uuid4().hex}"
    table(spark, sf_dir, "documents").select("doc_id", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.schema("doc_id long, lang string").parquet(path).filter("lang in ('de', 'es')").groupBy("lang").agg(F.count("*").alias("n"))


@register("source_markup_files", "SELECT count(*)::BIGINT AS n FROM customer WHERE c_custkey % 4 = 0")
def markup_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All members without persona written as text files, read again, and those with a label counted."""
    tree = open_tree(spark, sf_dir, "market")
    xml = subtrees(tree, Columnar(tree).select("/market/members/member[not(persona)]"))
    path = f"{shared_root(spark)}/treeloom-markup-{uuid.uuid4().hex}"
    xml.select("xml").write.text(path)
    return spark.read.text(path).filter(F.xpath_string("value", F.lit("/member/label")) != "").agg(F.count("*").alias("n"))


@register("xml_functions", "SELECT doc_id AS doc, (1992 + doc_id % 7)::VARCHAR AS yr FROM documents WHERE lang = 'es'")
def xml_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = open_tree(spark, sf_dir, "citations")
    whole = subtrees(tree, Columnar(tree).select('/citation[@lang = "es"]'))
    return whole.select("doc", F.xpath_string("xml", F.lit("/citation/art/yr")).alias("yr"))


@register("serialise_round_trip", "SELECT 0::BIGINT AS lost")
def serialise_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes that differ after pages are serialised, parsed and encoded again."""
    from treeloom.sources.html import parse_html
    from treeloom.sources.trees import whole_documents
    from treeloom.tree.encode import encode_records

    tree = open_tree(spark, sf_dir, "pages")
    xml = subtrees(tree, Columnar(tree).select("/html")).select("doc", "xml")
    again = whole_documents(encode_records(xml, parse_html, ["xml"], ["doc"]))
    cols = ["doc", "pre", "last", "label", "kind"]
    one, two = tree.nodes.select(*cols).filter("kind = 'elem'"), again.select(*cols).filter("kind = 'elem'")
    return one.exceptAll(two).unionAll(two.exceptAll(one)).agg(F.count("*").alias("lost"))
