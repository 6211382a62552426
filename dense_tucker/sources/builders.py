"""Tensors over relational tables: cells are the measure summed by the mode indices, absent cells are zero.

Indices are 0-based and come from fixed domains, never from the facts, so sizes do not move with the data; only vectors and hosts are
counted. Rows outside a domain have no cell; outside_rows() counts them.
Facts are summed before the domain is filled. `cells` gives exactly the product of the lengths; the block
packer fills zeros itself and takes `filled_cells`.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def _case(column: str, labels: list[str]) -> str:
    return "case " + column + "".join(f" when '{v}' then {i}" for i, v in enumerate(labels)) + " end"


#: Fixed label domains of the given tables.
FLAGS = ["A", "N", "R"]
STATUSES = ["F", "O"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
TYPES = ["ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD"]
EVENTS = ["click", "error", "purchase", "signup", "view"]
LANGS = ["de", "en", "es", "fr"]
ROLES = ["assistant", "system", "user"]

_LENGTH = "cast(greatest(1, least(16, floor(log2({0})))) as int) - 1"
_CENTS = "cast(round(l_extendedprice * 100) as bigint)"


@dataclass(frozen=True)
class Spec:
    """modes: SQL index expressions; joins: (table, condition); measure: SQL aggregate input, summed."""

    L: tuple[int, ...]
    K: tuple[int, ...]
    table: str
    modes: tuple[str, ...]
    measure: str
    joins: tuple[tuple[str, str], ...] = ()
    where: str = "true"
    rename: dict = field(default_factory=dict)


def specs() -> dict[str, Spec]:
    flag, status = _case("l_returnflag", FLAGS), _case("l_linestatus", STATUSES)
    brand = "cast(regexp_extract(p_brand, '([0-9]+)', 1) as int) - 1"
    year = "year(l_shipdate) - 1995"
    star = (("orders", "l_orderkey = o_orderkey"), ("customer", "o_custkey = c_custkey"), ("part", "l_partkey = p_partkey"))
    hour, day = "hour(ts)", "day(ts) - 1"
    return {
        "ta": Spec((3, 2, 11, 9, 7), (2, 2, 4, 3, 3), "lineitem", (flag, status, "cast(round(l_discount * 100) as int)", "cast(round(l_tax * 100) as int)", "l_linenumber - 1"), "cast(l_quantity as bigint)"),
        "tb": Spec((25, 25, 7), (8, 8, 4), "lineitem", ("c_nationkey", brand, year), _CENTS, star),
        "tc": Spec((5, 5, 6, 7, 5, 3), (3, 3, 3, 4, 3, 2), "lineitem", (_case("c_mktsegment", SEGMENTS), _case("o_orderpriority", PRIORITIES), _case("p_type", TYPES), year, "n_regionkey", flag), "cast(l_quantity as bigint)", (*star, ("nation", "c_nationkey = n_nationkey"))),
        "td": Spec((5, 7, 24), (3, 3, 6), "events", (_case("event_type", EVENTS), "datediff(cast(ts as date), date '2023-12-31') % 7", hour), "cast(round(value * 100) as bigint)"),
        "td4": Spec((15, 5, 30, 24), (5, 3, 8, 6), "events", ("cast(user_id % 15 as int)", _case("event_type", EVENTS), day, hour), "1"),
        "te": Spec((500, 8, 8), (10, 4, 4), "embeddings", ("cast(vec_id as int)", "cast(floor(pos / 8) as int)", "cast(pos % 8 as int)"), "cast(x as double)"),
        "tf": Spec((4, 20, 16), (2, 5, 4), "documents", (_case("lang", LANGS), "cast(substring(source, 4) as int)", _LENGTH.format("n_chars")), "1"),
        "tg": Spec((3, 8, 16), (2, 3, 4), "conversations", (_case("role", ROLES), "cast(turn as int)", _LENGTH.format("length(text)")), "1"),
        "th": Spec((4, 20, 2, 2), (2, 5, 2, 2), "documents", (_case("lang", LANGS), "cast(substring(source, 4) as int)", "cast(quality as int)", "cast(toxic as int)"), "1", (("labels", "documents.doc_id = labels.doc_id"),)),
        "ti": Spec((32, 8, 16), (6, 4, 4), "documents", ("cast(doc_id % 32 as int)", "class", "bucket"), "n"),
        "tj": Spec((200, 200, 83), (20, 20, 16), "lineitem", ("cast(o_custkey % 200 as int)", "cast(l_partkey % 200 as int)", "(year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1"), "cast(l_quantity as bigint)", (("orders", "l_orderkey = o_orderkey"),)),
        "tk": Spec((25, 25, 7), (8, 8, 4), "lineitem", ("s_nationkey", "c_nationkey", year), _CENTS, (("supplier", "l_suppkey = s_suppkey"), ("orders", "l_orderkey = o_orderkey"), ("customer", "o_custkey = c_custkey"))),
        "tl": Spec((60, 16, 6), (8, 4, 3), "pages", ("host", _LENGTH.format("n_html"), "class"), "n"),
    }


#: Character classes of ti, as bracket expressions both engines read alike; the last takes the rest.
CLASSES = ("[a-m]", "[n-z]", "[A-Z]", "[0-9]", "[ ]", "[\\n\\t\\r]", "[!-/:-@\\[-`{-~]")
#: Tags counted for tl.
TAGS = ("<p>", "<li>", "<a ", "<div", "<h1>", "<b>")


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _special(spark: SparkSession, sf_dir: str, name: str, spec: Spec) -> DataFrame:
    """Base rows of the tensors whose modes are not plain columns."""
    base = read(spark, sf_dir, spec.table)
    if name == "te":
        return base.select("vec_id", F.posexplode("embedding").alias("pos", "x"))
    if name == "ti":  # counts per segment and class; no row for each character
        parts = base.where(F.length("text") > 0).select("doc_id", "text", F.explode(F.sequence(F.lit(0), F.lit(15))).alias("bucket"))
        cut = parts.select("doc_id", "bucket", F.expr("substring(text, cast(ceil(bucket * length(text) / 16.0) as int) + 1, cast(ceil((bucket + 1) * length(text) / 16.0) as int) - cast(ceil(bucket * length(text) / 16.0) as int))").alias("piece"))
        counts = [F.length("piece") - F.length(F.regexp_replace("piece", c, "")) for c in CLASSES]
        rest = F.length("piece") - reduce(lambda a, b: a + b, counts)
        return cut.select("doc_id", "bucket", F.posexplode(F.array(*counts, rest)).alias("class", "n"))
    if name == "tl":
        host = F.regexp_extract("url", "://([^/?#]+)", 1)
        # one row for each index of the mode
        ranked = base.select(host.alias("h")).distinct().select("h", (F.dense_rank().over(Window.orderBy("h")) - 1).alias("host"))
        tags = F.array(*[((F.length("html") - F.length(F.replace("html", F.lit(t), F.lit("")))) / len(t)).cast("bigint") for t in TAGS])
        return base.withColumn("h", host).join(ranked, "h").select("host", F.length("html").alias("n_html"), F.posexplode(tags).alias("class", "n"))
    return base


def lengths(spark: SparkSession, sf_dir: str, name: str) -> tuple[int, ...]:
    """Lengths of the modes; the first ones of the vector and page tensors are the numbers of vectors and hosts."""
    spec = specs()[name]
    if name == "te":
        return (read(spark, sf_dir, "embeddings").count(), 8, 8)
    if name == "tl":
        hosts = read(spark, sf_dir, "pages").select(F.count_distinct(F.regexp_extract("url", "://([^/?#]+)", 1))).first()[0]
        return (hosts, *spec.L[1:])
    return spec.L


def _indexed(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, Column]:
    """Facts with their indices, and whether a row lies in the domain."""
    spec = specs()[name]
    df = _special(spark, sf_dir, name, spec) if name in ("te", "ti", "tl") else read(spark, sf_dir, spec.table)
    if spec.joins:
        df = df.alias(spec.table)
        for table, condition in spec.joins:
            df = df.join(read(spark, sf_dir, table).alias(table), F.expr(condition))
    picked = df.select(*[F.expr(e).cast("int").alias(f"i{k}") for k, e in enumerate(spec.modes)], F.expr(spec.measure).alias("v"))
    inside = reduce(lambda a, b: a & b, [(F.col(f"i{k}") >= 0) & (F.col(f"i{k}") < n) for k, n in enumerate(lengths(spark, sf_dir, name))])
    return picked, F.coalesce(inside, F.lit(False))


def filled_cells(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """i0.., v of cells that occur."""
    picked, inside = _indexed(spark, sf_dir, name)
    return picked.where(inside).groupBy(*picked.columns[:-1]).agg(F.sum("v").cast("double").alias("v"))


def outside_rows(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """tensor, facts and outside: how many rows the tensor is made of and how many of them have no cell."""
    picked, inside = _indexed(spark, sf_dir, name)
    return picked.agg(F.count("*").alias("facts"), F.count_if(~inside).alias("outside")).select(F.lit(name).alias("tensor"), "facts", "outside")


def domain(spark: SparkSession, L: tuple[int, ...]) -> DataFrame:
    """All coordinates, by arithmetic on one range."""
    total = reduce(lambda a, b: a * b, L, 1)
    df, step = spark.range(total), total
    columns = []
    for k, n in enumerate(L):
        step //= n
        columns.append(F.expr(f"cast((id div {step}) % {n} as int)").alias(f"i{k}"))
    return df.select(*columns)


def cells(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """i0.., v of every cell of the domain."""
    L = lengths(spark, sf_dir, name)
    keys = [f"i{k}" for k in range(len(L))]
    return domain(spark, L).join(filled_cells(spark, sf_dir, name), keys, "left").select(*keys, F.coalesce("v", F.lit(0.0)).alias("v"))


def _lengths_sql(name: str) -> list[str]:
    L = [str(n) for n in specs()[name].L]
    counted = {"te": "(select count(*) from embeddings)", "tl": "(select count(distinct regexp_extract(url, '://([^/?#]+)', 1)) from pages)"}
    return [counted[name], *L[1:]] if name in counted else L


def facts_sql(name: str) -> str:
    """Indices and measure of all facts, for DuckDB."""
    spec = specs()[name]
    source = spec.table + "".join(f" join {t} on {c}" for t, c in spec.joins)
    if name == "te":
        source = "(select vec_id, unnest(range(64)) as pos, unnest(embedding) as x from embeddings)"
    if name == "ti":
        branches = "".join(f" when regexp_matches(c, '{e}') then {i}" for i, e in enumerate(CLASSES))
        source = f"(select doc_id, case{branches} else 7 end as class, cast(floor(16 * p / n) as int) as bucket, 1 as n from (select doc_id, length(text) as n, unnest(string_split(text, '')) as c, unnest(range(length(text))) as p from documents))"
    if name == "tl":
        tags = ", ".join(f"cast((length(html) - length(replace(html, '{t}', ''))) / {len(t)} as bigint)" for t in TAGS)
        source = f"(select host, n_html, unnest(range(6)) as class, unnest([{tags}]) as n from (select dense_rank() over (order by regexp_extract(url, '://([^/?#]+)', 1)) - 1 as host, length(html) as n_html, html from pages))"
    modes = [m.replace("datediff(cast(ts as date), date '2023-12-31')", "datediff('day', date '2023-12-31', cast(ts as date))") for m in spec.modes]
    return f"select {', '.join(f'cast({m} as int) as i{k}' for k, m in enumerate(modes))}, {spec.measure} as v from {source}"


def outside_sql(name: str) -> str:
    inside = " and ".join(f"i{k} >= 0 and i{k} < {n}" for k, n in enumerate(_lengths_sql(name)))
    return f"select '{name}' as tensor, count(*) as facts, count(*) filter (where not coalesce({inside}, false)) as outside from ({facts_sql(name)})"


def cells_sql(name: str) -> str:
    """The cells by a cross join of domains, for DuckDB."""
    L, facts = _lengths_sql(name), facts_sql(name)
    keys = ", ".join(f"i{k}" for k in range(len(L)))
    summed = f"select {keys}, cast(sum(v) as double) as v from ({facts}) group by {keys}"
    domains = ", ".join(f"(select unnest(range({n}))::int as i{k})" for k, n in enumerate(L))
    return f"select {keys}, coalesce(v, 0.0) as v from (select * from {domains}) left join ({summed}) using ({keys})"


def mode_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """mode, idx and label of tensor ta's label modes."""
    rows = [(m + 1, i, v) for m, labels in enumerate((FLAGS, STATUSES)) for i, v in enumerate(labels)]
    return spark.createDataFrame(rows, "mode int, idx int, label string")


def random_cells(spark: SparkSession, L: tuple[int, ...], modulus: int = 1009) -> DataFrame:
    """Deterministic pseudo-random integer cells: a linear congruence of the cell's number."""
    total = reduce(lambda a, b: a * b, L, 1)
    step, columns = total, []
    for k, n in enumerate(L):
        step //= n
        columns.append(F.expr(f"cast((id div {step}) % {n} as int)").alias(f"i{k}"))
    return spark.range(total).select(*columns, F.expr(f"cast(((id % 1000003) * 7919 + 104729) % {modulus} as double)").alias("v"))
