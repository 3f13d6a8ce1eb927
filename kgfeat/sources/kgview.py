"""Knowledge-graph views of the given tables.

Each part is one SELECT of (s, p, o) that both Spark and DuckDB run, written with table names in
braces; where the two dialects differ a part has a second text.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_TOKEN = re.compile(r"\{(\w+)\}")

PARTS: dict[str, str | tuple[str, str]] = {
    "placed": "SELECT 'customer:'||o_custkey AS s, 'placed' AS p, 'order:'||o_orderkey AS o FROM {orders}",
    "contains": "SELECT 'order:'||l_orderkey AS s, 'contains' AS p, 'part:'||l_partkey AS o FROM {lineitem}",
    "fulfilledBy": "SELECT 'order:'||l_orderkey AS s, 'fulfilledBy' AS p, 'supplier:'||l_suppkey AS o FROM {lineitem}",
    "suppliedBy": "SELECT 'part:'||l_partkey AS s, 'suppliedBy' AS p, 'supplier:'||l_suppkey AS o FROM {lineitem}",
    "livesIn": "SELECT 'customer:'||c_custkey AS s, 'livesIn' AS p, 'nation:'||c_nationkey AS o FROM {customer}",
    "basedIn": "SELECT 'supplier:'||s_suppkey AS s, 'basedIn' AS p, 'nation:'||s_nationkey AS o FROM {supplier}",
    "inRegion": "SELECT 'nation:'||n_nationkey AS s, 'inRegion' AS p, 'region:'||n_regionkey AS o FROM {nation}",
    "did": "SELECT 'user:'||user_id AS s, 'did' AS p, 'event:'||event_id AS o FROM {events}",
    "fromSource": "SELECT 'doc:'||doc_id AS s, 'fromSource' AS p, 'source:'||source AS o FROM {documents} WHERE source IS NOT NULL",
    "inLang": "SELECT 'doc:'||doc_id AS s, 'inLang' AS p, 'lang:'||lang AS o FROM {documents} WHERE lang IS NOT NULL",
    "hasLine": (
        "SELECT 'doc:'||doc_id AS s, 'hasLine' AS p, 'line:'||md5(line) AS o FROM {documents} LATERAL VIEW explode(split(text, '\\n')) x AS line WHERE line <> ''",
        "SELECT 'doc:'||doc_id AS s, 'hasLine' AS p, 'line:'||md5(line) AS o FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM {documents}) WHERE line <> ''",
    ),
    "quotes": "SELECT 'doc:'||d.doc_id AS s, 'quotes' AS p, 'bench:'||b.item_id AS o FROM {documents} d JOIN {benchmark} b ON contains(d.text, b.text)",
    "onHost": "SELECT 'page:'||page_id AS s, 'onHost' AS p, 'host:'||regexp_extract(url, '://([^/?#]+)', 1) AS o FROM {pages} WHERE url IS NOT NULL",
    "linksTo": (
        "SELECT 'page:'||page_id AS s, 'linksTo' AS p, 'path:'||href AS o FROM {pages} LATERAL VIEW explode(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) x AS href WHERE href <> ''",
        "SELECT 'page:'||page_id AS s, 'linksTo' AS p, 'path:'||href AS o FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM {pages}) WHERE href <> ''",
    ),
    "hasTurn": "SELECT 'conv:'||conv_id AS s, 'hasTurn' AS p, 'turn:'||conv_id||'/'||turn AS o FROM {conversations} WHERE turn = 0",
    "next": "SELECT 'turn:'||a.conv_id||'/'||a.turn AS s, 'next' AS p, 'turn:'||b.conv_id||'/'||b.turn AS o FROM {conversations} a JOIN {conversations} b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "prov": "SELECT 'part:'||p_partkey AS s, 'prov:loadedFrom' AS p, 'prov:part' AS o FROM {part} UNION ALL SELECT 'supplier:'||s_suppkey, 'prov:loadedFrom', 'prov:supplier' FROM {supplier} UNION ALL SELECT 'nation:'||n_nationkey, 'prov:loadedFrom', 'prov:nation' FROM {nation}",
    # classes of individuals
    "type_part": "SELECT 'part:'||p_partkey AS s, 'rdf:type' AS p, 'cls:Brand/'||p_brand||'/Type/'||p_type AS o FROM {part}",
    "type_order": "SELECT 'order:'||o_orderkey AS s, 'rdf:type' AS p, 'cls:Priority/'||o_orderpriority AS o FROM {orders} UNION ALL SELECT 'order:'||o_orderkey, 'rdf:type', 'cls:Status/'||o_orderstatus FROM {orders}",
    "type_customer": "SELECT 'customer:'||c_custkey AS s, 'rdf:type' AS p, 'cls:Segment/'||c_mktsegment AS o FROM {customer}",
    "type_supplier": "SELECT 'supplier:'||s_suppkey AS s, 'rdf:type' AS p, CASE WHEN s_acctbal < 0 THEN 'cls:SupDebt' ELSE 'cls:SupCredit' END AS o FROM {supplier}",
    "type_nation": "SELECT 'nation:'||n_nationkey AS s, 'rdf:type' AS p, 'cls:NationOf/'||r_name AS o FROM {nation} JOIN {region} ON n_regionkey = r_regionkey",
    "type_region": "SELECT 'region:'||r_regionkey AS s, 'rdf:type' AS p, 'cls:Region' AS o FROM {region}",
    "type_event": "SELECT 'event:'||event_id AS s, 'rdf:type' AS p, 'cls:Event/'||event_type AS o FROM {events}",
    "type_doc": "SELECT 'doc:'||doc_id AS s, 'rdf:type' AS p, 'cls:Doc/'||lang AS o FROM {documents} WHERE lang IS NOT NULL",
    "type_host": "SELECT 'host:'||h AS s, 'rdf:type' AS p, 'cls:Tld/'||regexp_extract(h, '([^.]+)$', 1) AS o FROM (SELECT regexp_extract(url, '://([^/?#]+)', 1) AS h FROM {pages} WHERE url IS NOT NULL)",
    "type_page": "SELECT 'page:'||page_id AS s, 'rdf:type' AS p, 'cls:PageOf/'||regexp_extract(regexp_extract(url, '://([^/?#]+)', 1), '([^.]+)$', 1) AS o FROM {pages} WHERE url IS NOT NULL",
    "type_turn": "SELECT 'turn:'||conv_id||'/'||turn AS s, 'rdf:type' AS p, 'cls:Turn/'||role AS o FROM {conversations}",
    # the hierarchy
    "sub_part": "SELECT 'cls:Brand/'||p_brand||'/Type/'||p_type AS s, 'rdfs:subClassOf' AS p, 'cls:Brand/'||p_brand AS o FROM {part} UNION SELECT 'cls:Brand/'||p_brand||'/Type/'||p_type, 'rdfs:subClassOf', 'cls:Type/'||p_type FROM {part} UNION SELECT 'cls:Brand/'||p_brand, 'rdfs:subClassOf', 'cls:Part' FROM {part} UNION SELECT 'cls:Type/'||p_type, 'rdfs:subClassOf', 'cls:Part' FROM {part}",
    "sub_order": "SELECT 'cls:Priority/'||o_orderpriority AS s, 'rdfs:subClassOf' AS p, 'cls:Order' AS o FROM {orders} UNION SELECT 'cls:Status/'||o_orderstatus, 'rdfs:subClassOf', 'cls:Order' FROM {orders}",
    "sub_customer": "SELECT 'cls:Segment/'||c_mktsegment AS s, 'rdfs:subClassOf' AS p, 'cls:Customer' AS o FROM {customer} UNION SELECT 'cls:Customer', 'rdfs:subClassOf', 'cls:Agent' FROM {customer}",
    "sub_supplier": "SELECT 'cls:SupDebt' AS s, 'rdfs:subClassOf' AS p, 'cls:Supplier' AS o FROM {supplier} UNION SELECT 'cls:SupCredit', 'rdfs:subClassOf', 'cls:Supplier' FROM {supplier} UNION SELECT 'cls:Supplier', 'rdfs:subClassOf', 'cls:Agent' FROM {supplier}",
    "sub_place": "SELECT 'cls:NationOf/'||r_name AS s, 'rdfs:subClassOf' AS p, 'cls:Nation' AS o FROM {region} UNION SELECT 'cls:Nation', 'rdfs:subClassOf', 'cls:Place' FROM {region} UNION SELECT 'cls:Region', 'rdfs:subClassOf', 'cls:Place' FROM {region}",
    "sub_event": "SELECT 'cls:Event/'||event_type AS s, 'rdfs:subClassOf' AS p, 'cls:Event' AS o FROM {events}",
    # literals as vertices, one a bucket of 500 (Spark makes them with extensions.literal_vertices)
    "balance": "SELECT 'customer:'||c_custkey AS s, 'balance' AS p, 'num:balance/'||cast(floor(c_acctbal / 500) AS bigint) AS o FROM {customer} WHERE c_acctbal IS NOT NULL",
    # identity
    "same_part": "SELECT s, p, o FROM (SELECT 'part:'||p_partkey AS s, 'owl:sameAs' AS p, 'part:'||lead(p_partkey) OVER (PARTITION BY p_name, p_brand, p_type ORDER BY p_partkey) AS o FROM {part}) WHERE o IS NOT NULL",
    # a star around the least id: its counts combine before the shuffle, and the join can split the copies of one text
    "same_doc": "SELECT 'doc:'||d.doc_id AS s, 'owl:sameAs' AS p, 'doc:'||m.least AS o FROM (SELECT doc_id, md5(text) AS h FROM {documents} WHERE text IS NOT NULL) d JOIN (SELECT md5(text) AS h, min(doc_id) AS least FROM {documents} WHERE text IS NOT NULL GROUP BY md5(text) HAVING min(doc_id) < max(doc_id)) m ON d.h = m.h WHERE d.doc_id > m.least",
    "same_user": "SELECT DISTINCT 'user:'||user_id AS s, 'owl:sameAs' AS p, 'customer:'||user_id AS o FROM {events} JOIN {customer} ON user_id = c_custkey",
}

#: groups of parts that workloads use
STAR = ("placed", "contains", "fulfilledBy", "suppliedBy", "livesIn", "basedIn", "inRegion")
CLASSES = ("type_part", "type_order", "type_customer", "type_supplier", "type_nation", "type_region", "sub_part", "sub_order", "sub_customer", "sub_supplier", "sub_place")
VIEWS: dict[str, tuple[str, ...]] = {
    "part": ("suppliedBy", "basedIn", "inRegion", "type_part", "type_supplier", "type_nation", "type_region", "sub_part", "sub_supplier", "sub_place"),
    "part_same": ("same_part", "suppliedBy", "basedIn", "inRegion", "type_part", "type_supplier", "type_nation", "type_region", "sub_part", "sub_supplier", "sub_place"),
    "part_prov": ("prov", "suppliedBy", "basedIn", "inRegion", "type_part", "type_supplier", "type_nation", "type_region", "sub_part", "sub_supplier", "sub_place"),
    "customer": (*STAR, "did", "same_user", *CLASSES, "type_event", "sub_event"),
    "star": (*STAR, *CLASSES),
    "doc": ("fromSource", "inLang", "hasLine", "quotes", "same_doc", "type_doc"),
    "page": ("onHost", "linksTo", "type_host", "type_page"),
    "conversation": ("hasTurn", "next", "type_turn"),
}

#: seeds of the workloads, one SELECT of (seed)
SEEDS: dict[str, str] = {
    "part": "SELECT 'part:'||p_partkey AS seed FROM {part} WHERE p_type = 'ECONOMY'",
    "customer": "SELECT 'customer:'||c_custkey AS seed FROM {customer} WHERE c_mktsegment = 'BUILDING'",
    "doc": "SELECT 'doc:'||d.doc_id AS seed FROM {labels} l JOIN {documents} d ON l.doc_id = d.doc_id",
    "page": "SELECT 'page:'||page_id AS seed FROM {pages} WHERE regexp_extract(regexp_extract(url, '://([^/?#]+)', 1), '([^.]+)$', 1) = 'com'",
    "conversation": "SELECT DISTINCT 'conv:'||conv_id AS seed FROM {conversations}",
}


def tables_of(sql: str) -> list[str]:
    return sorted(set(_TOKEN.findall(sql)))


def spark_text(part: str) -> str:
    x = PARTS[part]
    return x if isinstance(x, str) else x[0]


def duck_text(part: str) -> str:
    x = PARTS[part]
    return _TOKEN.sub(r"\1", x if isinstance(x, str) else x[1])


def select(spark: SparkSession, sf_dir: str, sql: str) -> DataFrame:
    """Run a SELECT over the Parquet tables of a folder."""
    return spark.sql(sql, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in tables_of(sql)})


def triples(spark: SparkSession, sf_dir: str, view: str | tuple[str, ...], as_set: bool = True) -> DataFrame:
    """(s, p, o) of a named view or of given parts; mining makes a set of integers of them itself."""
    parts = VIEWS[view] if isinstance(view, str) else view
    out = reduce(DataFrame.union, [quotes(spark, sf_dir) if x == "quotes" else select(spark, sf_dir, spark_text(x)) for x in parts])
    return out.distinct() if as_set else out


def quotes(spark: SparkSession, sf_dir: str, width: int = 24) -> DataFrame:
    """The part ``quotes``: documents that contain a test item's text, without holding every document against
    every item. Each item is looked up by one piece of ``width`` characters, the piece that begins at a word
    and is rarest in a hash order, among the pieces of documents that begin at a word; what meets is tested.

    An item begins at a word of the document or within one: pieces begin after its first blank, so the word
    that its beginning may cut is left out. Items without such a piece are few and short; they are tested
    against all documents.
    """
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").select("item_id", F.col("text").alias("item")).filter("item is not null")

    def pieces(text: Column) -> Column:
        return F.regexp_extract_all(text, F.lit(rf"(?s)(?<=[ ])(?=(?=[^ ])(.{{{width}}}))"), F.lit(1))

    keyed = items.withColumn("piece", F.array_min(F.transform(pieces(F.col("item")), lambda x: F.struct(F.xxhash64(x).alias("h"), x.alias("x"))))["x"])
    at = docs.select("doc_id", F.explode(F.array_distinct(pieces(F.col("text")))).alias("piece"))
    cand = at.join(keyed.filter("piece is not null"), "piece").select("doc_id", "item_id", "item").distinct()  # ids, not texts
    met = docs.join(cand, "doc_id").filter(F.contains("text", "item")).select("doc_id", "item_id")
    short = keyed.filter("piece is null")
    if not short.isEmpty():
        met = met.union(docs.join(short, F.contains("text", "item")).select("doc_id", "item_id"))
    return met.distinct().select(F.concat(F.lit("doc:"), "doc_id").alias("s"), F.lit("quotes").alias("p"), F.concat(F.lit("bench:"), "item_id").alias("o"))


def duck_triples(view: str | tuple[str, ...]) -> str:
    """The same view as DuckDB SQL."""
    parts = VIEWS[view] if isinstance(view, str) else view
    return " UNION ".join(f"SELECT s, p, o FROM ({duck_text(x)})" for x in parts)


def seeds(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return select(spark, sf_dir, SEEDS[name])


def duck_seeds(name: str) -> str:
    return _TOKEN.sub(r"\1", SEEDS[name])
