"""The experiment domains: tables dealt to virtual sources that name and render the same property differently.

A domain says once which fields it has; Spark's instances come from it by projection and unpivot, and SQL text for other
engines from the same constants. The field is the reference property that a source's property is aligned to. A source's
number modulo 4 picks its variant of name and rendering.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

CAP = 100


@dataclass(frozen=True)
class Field:
    ref: str
    column: str
    kind: str  # text, money, number, date
    names: tuple[str, str, str, str]
    only: tuple[int, ...] | None = None  # source numbers that have it; None: all


@dataclass(frozen=True)
class Domain:
    cls: str
    prefix: str
    fields: tuple[Field, ...]
    sources: int
    noise: tuple[int, int] = (12, 2)  # properties without reference: of source 0, of the others
    cap: int | None = None
    base_sql: str = ""
    extra: tuple[str, ...] = field(default=())


def deal(column: str, buckets: list[int]) -> str:
    """SQL that maps column % sum(buckets) to a source number, source i getting buckets[i] of the remainders."""
    upto, out = 0, []
    for i, n in enumerate(buckets[:-1]):
        upto += n
        out.append(f"WHEN {column} % {sum(buckets)} < {upto} THEN {i}")
    return f"CASE {' '.join(out)} ELSE {len(buckets) - 1} END"


#: The variants of names and their sources.
GOODS = Domain(
    "goods", "g",
    (
        Field("name", "p_name", "text", ("name", "title", "called", "product name")),
        Field("brand", "p_brand", "text", ("brand", "maker", "manufacturer", "label")),
        Field("type", "p_type", "text", ("type", "category", "item type", "sort")),
        Field("size", "p_size", "number", ("size", "dimension", "item size", "extent")),
        Field("retail price", "p_retailprice", "money", ("retail price", "list cost", "msrp", "price tag")),
        Field("max quantity", "max_quantity", "number", ("max quantity", "most units", "largest amount", "qty limit")),
        Field("max extended price", "max_extended", "money", ("max extended price", "highest total", "top sum", "item price")),
        Field("max discount", "max_discount", "number", ("max discount", "highest rebate", "largest reduction", "disc")),
        Field("max tax", "max_tax", "number", ("max tax", "highest duty", "levy", "tax ceiling")),
        Field("last ship date", "last_ship", "date", ("last shipped", "dispatch day", "ship date", "sent on")),
        Field("return flag", "return_flag", "text", ("return flag", "returned mark", "rf", "back code")),
        Field("line status", "line_status", "text", ("line status", "row state", "ls", "line condition")),
    ),
    24, (24, 2), CAP,
    "SELECT p_partkey AS entity, CAST(p_partkey % 24 AS INT) AS src, p_name, p_brand, p_type, p_size, p_retailprice, max(l_quantity) AS max_quantity, "
    "max(l_extendedprice) AS max_extended, max(l_discount) AS max_discount, max(l_tax) AS max_tax, max(l_shipdate) AS last_ship, "
    "max(l_returnflag) AS return_flag, max(l_linestatus) AS line_status FROM part JOIN lineitem ON p_partkey = l_partkey "
    "GROUP BY p_partkey, p_name, p_brand, p_type, p_size, p_retailprice",
)
PARTY = Domain(
    "party", "p",
    (
        Field("name", "name", "text", ("name", "customer name", "title", "called")),
        Field("nation", "nation", "text", ("nation", "country", "land", "nationality")),
        Field("region", "region", "text", ("region", "area", "continent", "part of world")),
        Field("balance", "balance", "money", ("account balance", "acct bal", "funds", "credit")),
        Field("segment", "segment", "text", ("market segment", "sector", "segment", "mkt"), (0, 1, 2, 3, 4, 5)),
    ),
    9, (6, 1), None,
    f"SELECT concat('c', CAST(c_custkey AS STRING)) AS entity, CAST({deal('c_custkey', [8, 3, 2, 1, 1, 1])} AS INT) AS src, c_name AS name, n_name AS nation, r_name AS region, "
    "c_acctbal AS balance, c_mktsegment AS segment FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey "
    "UNION ALL SELECT concat('s', CAST(s_suppkey AS STRING)), CAST(6 + s_suppkey % 3 AS INT), s_name, n_name, r_name, s_acctbal, NULL "
    "FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
)
ORDER = Domain(
    "order", "o",
    (
        Field("customer", "o_custkey", "number", ("customer", "client number", "buyer", "cust id")),
        Field("status", "o_orderstatus", "text", ("order status", "state", "stage", "os")),
        Field("total", "o_totalprice", "money", ("total price", "order sum", "total cost", "amount due")),
        Field("order date", "o_orderdate", "date", ("order date", "purchased on", "", "placed")),
        Field("order date", "order_year", "number", ("", "", "order year", "")),
        Field("order date", "order_month", "number", ("", "", "order month", "")),
        Field("priority", "o_orderpriority", "text", ("order priority", "urgency", "importance", "prio")),
    ),
    10, (6, 1), None,
    f"SELECT o_orderkey AS entity, CAST({deal('o_orderkey', [4, 3, 2, 1, 1, 1, 1, 1, 1, 1])} AS INT) AS src, o_custkey, o_orderstatus, o_totalprice, o_orderdate, "
    "year(o_orderdate) AS order_year, month(o_orderdate) AS order_month, o_orderpriority FROM orders",
)
EVENT = Domain(
    "event", "e",
    (
        Field("time", "ts", "date", ("time stamp", "event date", "day", "happened")),
        Field("user", "user_id", "number", ("user", "visitor", "member number", "uid")),
        Field("kind", "event_type", "text", ("event type", "action", "kind of activity", "what")),
        Field("amount", "value", "money", ("amount", "event value", "sum", "worth")),
        Field("key", "k", "text", ("key", "props key", "index", "k")),
    ),
    8, (6, 1), None,
    "SELECT event_id AS entity, CAST(user_id % 8 AS INT) AS src, ts, user_id, event_type, value, {json_k} AS k FROM events",
)
DOMAINS = {d.cls: d for d in (GOODS, PARTY, ORDER, EVENT)}
_TABLES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events"]


def fields_of(domain: Domain, k: int) -> list[tuple[Field, str, str]]:
    """(field, column, property name) of variant k."""
    return [(f, f.column, f.names[k]) for f in domain.fields if f.names[k]]


def source_name(domain: Domain, src: int) -> str:
    return f"{domain.prefix}{src:02d}"


def alignment(domain: Domain) -> list[tuple[str, str, str, str]]:
    """ALIGN rows: a constant of the domain."""
    return [
        (domain.cls, source_name(domain, s), name, f.ref)
        for s in range(domain.sources) for f, _, name in fields_of(domain, s % 4) if f.only is None or s in f.only
    ]


def align_table(spark: SparkSession, domains: list[str] | None = None) -> DataFrame:
    from propalign.model import ALIGN

    return spark.createDataFrame([r for d in domains or DOMAINS for r in alignment(DOMAINS[d])], ALIGN)


def _render(c: Column, kind: str, k: int) -> Column:
    if kind == "money":
        plain = c.cast("decimal(18,2)").cast("string")
        return [plain, F.concat(F.lit("USD "), plain), F.concat(plain, F.lit(" usd")), F.floor(c).cast("bigint").cast("string")][k]
    if kind == "number":
        return c
    if kind == "date":
        return F.date_format(c, ["yyyy-MM-dd", "dd.MM.yyyy", "yyyy", "MM"][k])
    return [c, F.upper(c), F.lower(c), F.concat(F.lit("the "), c)][k]


def base(spark: SparkSession, sf_dir: str, cls: str, tasks: int = 0) -> DataFrame:
    """(entity, src, fields) of a domain, at most its cap of entities for each source. tasks: rows of an uncapped domain whose
    tables are read by fewer are dealt to so many."""
    domain = DOMAINS[cls]
    tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in _TABLES if f" {t}" in domain.base_sql}
    sql = domain.base_sql.format(json_k="get_json_object(props, '$.k')") if "{json_k}" in domain.base_sql else domain.base_sql
    # Tables go in by argument, so no view is left in the session.
    for t in sorted(tables, key=len, reverse=True):
        sql = sql.replace(f"FROM {t}", f"FROM {{{t}}} AS {t}").replace(f"JOIN {t} ", f"JOIN {{{t}}} AS {t} ")
    df = spark.sql(sql, **tables)
    if domain.cap:
        order = Window.partitionBy("src").orderBy("entity")
        df = df.withColumn("_row", F.row_number().over(order)).where(F.col("_row") <= domain.cap).drop("_row")
    elif tasks and max(t.rdd.getNumPartitions() for t in tables.values()) < tasks:
        df = df.repartition(tasks)
    return df


def instances(spark: SparkSession, sf_dir: str, cls: str, tasks: int = 0) -> DataFrame:
    """INSTANCE rows of a domain. tasks: as base() has it."""
    if cls == "text":
        return text_instances(spark, sf_dir)
    domain, rows = DOMAINS[cls], base(spark, sf_dir, cls, tasks)
    entity = F.col("entity").cast("string")
    source = F.concat(F.lit(domain.prefix), F.lpad(F.col("src").cast("string"), 2, "0"))

    def text(f: Field, c: str, k: int) -> Column:
        rendered = _render(F.col(c), f.kind, k)
        number = f.kind == "number" and dict(rows.dtypes)[c] == "double"
        return rendered.cast("decimal(18,2)").cast("string") if number else rendered.cast("string")

    # One array of (property, value) for the source's variant, exploded: a single pass over the rows.
    cases = None
    for k in range(4):
        structs = [
            F.struct(
                F.lit(name).alias("prop"),
                (F.when(F.col("src").isin(*f.only), text(f, c, k)) if f.only is not None else text(f, c, k)).alias("value"),
            )
            for f, c, name in fields_of(domain, k)
        ]
        cond = F.col("src") % 4 == k
        cases = F.when(cond, F.array(*structs)) if cases is None else cases.when(cond, F.array(*structs))
    first, others = domain.noise
    noise = F.transform(
        F.sequence(F.lit(1), F.when(F.col("src") == 0, first).otherwise(others)),
        lambda i: F.struct(
            F.concat(F.lit("internal id "), i.cast("string")).alias("prop"),
            F.substring(F.md5(F.concat_ws(":", i.cast("string"), entity)), F.lit(1), 4 + i % 8).alias("value"),
        ),
    )
    parts = rows.select(source.alias("_source"), entity.alias("_entity"), F.concat(cases, noise).alias("_parts"))
    long = parts.select(F.lit(cls).alias("cls"), F.col("_source").alias("source"), F.col("_entity").alias("entity"), F.inline("_parts"))
    return long.where("value is not null")


def text_instances(spark: SparkSession, sf_dir: str) -> DataFrame:
    """INSTANCE rows of documents, pages, conversations and benchmark items, whose sources are different by nature."""
    from propalign.sources.readers import pages, unpivot

    t = lambda n: spark.read.parquet(f"{sf_dir}/{n}.parquet")
    docs = t("documents").join(t("labels"), "doc_id", "left").select(
        "doc_id", "source", F.col("text").alias("body"), F.col("lang").alias("language"), F.col("n_chars").alias("length"), "quality", F.col("toxic").alias("toxicity")
    )
    talk = t("conversations").select(F.concat_ws("-", "conv_id", "turn").alias("entity"), F.col("role").alias("speaker"), F.col("text").alias("message"))
    parts = [
        unpivot(docs, "text", F.col("source"), F.col("doc_id"), ["body", "language", "length", "quality", "toxicity"]),
        pages(t("pages")),
        unpivot(talk, "text", F.lit("talks"), F.col("entity"), ["speaker", "message"]),
        unpivot(t("benchmark").withColumnRenamed("text", "content"), "text", F.lit("benchmark"), F.col("item_id"), ["content"]),
    ]
    return reduce(DataFrame.unionByName, parts)


#: Which natural properties mean the same.
TEXT_ALIGN = {"body": "body", "message": "body", "content": "body", "language": "language", "length": "length", "quality": "quality", "toxicity": "toxicity", "title": "title", "heading": "title", "address": "address", "speaker": "role"}


def text_align(properties: DataFrame) -> DataFrame:
    """ALIGN rows of the natural sources. properties: (cls, source, prop)."""
    of = F.create_map(*[F.lit(x) for kv in TEXT_ALIGN.items() for x in kv])
    return properties.select("cls", "source", "prop", of[F.col("prop")].alias("ref_prop")).where("ref_prop is not null")


# --- the same in SQL for another engine ------------------------------------------------------------------------------


def _render_sql(c: str, kind: str, k: int) -> str:
    if kind == "money":
        plain = f"CAST(CAST({c} AS DECIMAL(18,2)) AS VARCHAR)"
        return [plain, f"'USD ' || {plain}", f"{plain} || ' usd'", f"CAST(CAST(floor({c}) AS BIGINT) AS VARCHAR)"][k]
    if kind == "number":
        return f"CASE WHEN typeof({c}) = 'DOUBLE' THEN CAST(CAST({c} AS DECIMAL(18,2)) AS VARCHAR) ELSE CAST({c} AS VARCHAR) END"
    if kind == "date":
        return f"strftime({c}, '{['%Y-%m-%d', '%d.%m.%Y', '%Y', '%m'][k]}')"
    return [c, f"upper({c})", f"lower({c})", f"'the ' || {c}"][k]


def instances_sql(cls: str) -> str:
    """SELECT of a domain's INSTANCE rows in DuckDB."""
    if cls == "text":
        return TEXT_SQL
    domain = DOMAINS[cls]
    rows = domain.base_sql.replace("STRING", "VARCHAR").format(json_k="json_extract_string(props, '$.k')")
    if domain.cap:
        rows = f"SELECT * FROM ({rows}) QUALIFY row_number() OVER (PARTITION BY src ORDER BY entity) <= {domain.cap}"
    parts = []
    head = f"SELECT '{cls}' AS cls, '{domain.prefix}' || lpad(CAST(src AS VARCHAR), 2, '0') AS source, CAST(entity AS VARCHAR) AS entity"
    for k in range(4):
        for f, c, name in fields_of(domain, k):
            only = f" AND src IN ({', '.join(map(str, f.only))})" if f.only is not None else ""
            parts.append(f"{head}, '{name}' AS prop, {_render_sql(c, f.kind, k)} AS value FROM b WHERE src % 4 = {k}{only}")
    first, others = domain.noise
    parts.append(
        f"{head}, 'internal id ' || i AS prop, substr(md5(i || ':' || CAST(entity AS VARCHAR)), 1, CAST(4 + i % 8 AS INT)) AS value "
        f"FROM b, range(1, {first + 1}) t(i) WHERE i <= CASE WHEN src = 0 THEN {first} ELSE {others} END"
    )
    return f"SELECT * FROM (WITH b AS ({rows}) {' UNION ALL '.join(parts)}) WHERE value IS NOT NULL"


_PAGE = "SELECT 'text' AS cls, regexp_extract(url, '://([^/?#]+)', 1) AS source, CAST(page_id AS VARCHAR) AS entity"
TEXT_SQL = f"""SELECT * FROM (
SELECT 'text' AS cls, source, CAST(d.doc_id AS VARCHAR) AS entity, x.prop, x.value FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id,
 LATERAL (VALUES ('body', d.text), ('language', d.lang), ('length', CAST(d.n_chars AS VARCHAR)), ('quality', CAST(l.quality AS VARCHAR)), ('toxicity', CAST(l.toxic AS VARCHAR))) x(prop, value)
UNION ALL {_PAGE}, 'title' AS prop, nullif(regexp_extract(html, '(?is)<title[^>]*>([^<]*)</title>', 1), '') AS value FROM pages
UNION ALL {_PAGE}, 'heading', nullif(regexp_extract(html, '(?is)<h1[^>]*>([^<]*)</h1>', 1), '') FROM pages
UNION ALL {_PAGE}, 'language', nullif(regexp_extract(html, '(?i)<html[^>]* lang=["'']?([a-z-]+)', 1), '') FROM pages
UNION ALL {_PAGE}, 'address', url FROM pages
UNION ALL SELECT 'text', 'talks', conv_id || '-' || turn, x.prop, x.value FROM conversations, LATERAL (VALUES ('speaker', role), ('message', text)) x(prop, value)
UNION ALL SELECT 'text', 'benchmark', CAST(item_id AS VARCHAR), 'content', text FROM benchmark
) WHERE value IS NOT NULL"""
