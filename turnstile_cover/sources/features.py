"""Users and their features: wide tables of the fingerprinting and clustering workloads."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from .tables import table


@dataclass(frozen=True)
class Wide:
    """One row a user: uid and attributes in order; numeric ones sort as numbers. sql: the same rows."""

    df: DataFrame | None
    attributes: tuple[str, ...]
    text: frozenset[str]
    sql: str

    def over(self, df: DataFrame) -> Wide:
        return Wide(df, self.attributes, self.text, self.sql)

    def feature(self, a: str, value: Column) -> Column:
        """Key of the one-hot feature a = value; keys sort by attribute, then value."""
        n = self.attributes.index(a)
        coded = value if a in self.text else F.lpad((value.cast("long") + 100_000).cast("string"), 8, "0")
        return F.concat(F.lit(f"{n:02d}:{a}="), coded)

    def feature_sql(self, a: str) -> str:
        n = self.attributes.index(a)
        coded = a if a in self.text else f"lpad(CAST(CAST({a} AS BIGINT) + 100000 AS VARCHAR), 8, '0')"
        return f"'{n:02d}:{a}=' || {coded}"

    def long(self) -> DataFrame:
        """uid and f, one row a user and attribute: the one-hot form's nonzeros."""
        return self.df.select("uid", F.explode(F.array(*(self.feature(a, F.col(a)) for a in self.attributes))).alias("f"))

    def long_sql(self) -> str:
        return " UNION ALL ".join(f"SELECT uid, {self.feature_sql(a)} AS f FROM w" for a in self.attributes)

    def dictionaries(self, most: int = 100_000) -> dict[str, dict[str, int]]:
        """Codes of the text attributes' values in their order, from 0; an attribute of more than most values is left out."""
        if not self.text:
            return {}
        names = [a for a in self.attributes if a in self.text]
        pairs = self.df.select(F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.col(a).alias("v")) for a in names))).alias("x")).select("x.*").distinct()
        rows = pairs.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("v"))).where(F.col("r") <= most + 1).select("a", "v").collect()
        out: dict[str, dict[str, int]] = {a: {} for a in names}
        for a, v in sorted(rows, key=lambda x: (x[0], x[1] or "")):
            out[a][v] = len(out[a])
        return {a: d for a, d in out.items() if len(d) <= most}

    def codes(self) -> Codes:
        """The table once, as integers: joins and text are paid for once, and every round reads narrow columns."""
        from ..operators.checkpoints import cut

        books = self.dictionaries()

        def code(a: str) -> Column:
            if a not in self.text:
                return F.col(a).cast("long")
            if a not in books:
                return F.xxhash64(a)
            return F.create_map(*(F.lit(x) for v, n in books[a].items() for x in (v, n)))[F.col(a)].cast("long")

        df = cut(self.df.select("uid", *(code(a).alias(a) for a in self.attributes)))
        return Codes(self, df, {a: {n: v for v, n in d.items()} for a, d in books.items()})

    def coded(self) -> DataFrame:
        """Attributes as integers that are never 0 (0 is never set): text codes from 1, numbers not below 0 plus 1."""
        c = self.codes()
        return c.df.select("uid", *(F.when(F.col(a) >= 0, F.col(a) + 1).otherwise(F.col(a)).alias(a) for a in self.attributes))


@dataclass(frozen=True)
class Codes:
    """A wide table as integers (uid, attributes), and the text values of its codes."""

    wide: Wide
    df: DataFrame
    names: dict[str, dict[int, str]]

    @property
    def attributes(self) -> tuple[str, ...]:
        return self.wide.attributes

    def name(self, a: str, code: int) -> str:
        """Key of the one-hot feature of a code."""
        n = self.attributes.index(a)
        if a not in self.wide.text:
            return f"{n:02d}:{a}={str(code + 100_000).rjust(8, '0')}"
        if a in self.names:
            return f"{n:02d}:{a}={self.names[a][code]}"
        row = self.wide.df.where(F.xxhash64(a) == code).select(a).first()
        return f"{n:02d}:{a}={row[0]}"

    def pairs(self, keep: list[str] = ()) -> Column:
        """Array of (place of the attribute, code), one for each attribute not in keep."""
        return F.array(*(F.struct(F.lit(n).alias("a"), F.col(a).alias("v")) for n, a in enumerate(self.attributes) if a not in keep))


PEOPLE = Wide(
    None,
    ("status", "priority", "segment", "nation", "year", "month", "dow", "pricebin", "balbin"),
    frozenset(("status", "priority", "segment")),
    "SELECT o_orderkey AS uid, o_orderstatus AS status, o_orderpriority[1] AS priority, c_mktsegment AS segment, c_nationkey AS nation, year(o_orderdate) AS year, month(o_orderdate) AS month, dayofweek(o_orderdate) AS dow, floor(o_totalprice / 50000)::BIGINT AS pricebin, floor(c_acctbal / 2000)::BIGINT AS balbin FROM orders JOIN customer ON o_custkey = c_custkey",
)


def people(spark: SparkSession, d: str) -> Wide:
    """Orders with their customers: 9 attributes, 80 one-hot features."""
    o = table(spark, d, "orders").join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    ts = F.col("o_orderdate")
    df = o.select(F.col("o_orderkey").alias("uid"), F.col("o_orderstatus").alias("status"), F.substring("o_orderpriority", 1, 1).alias("priority"), F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"), F.year(ts).alias("year"), F.month(ts).alias("month"), (F.dayofweek(ts) - 1).alias("dow"), F.floor(F.col("o_totalprice") / 50000).alias("pricebin"), F.floor(F.col("c_acctbal") / 2000).alias("balbin"))
    return PEOPLE.over(df)


CENSUS = Wide(
    None,
    ("qty", "disc", "tax", "rflag", "lstat", "lnum", "syear", "smonth", "brand", "ptype", "psize", "segment", "priority", "ostatus"),
    frozenset(("rflag", "lstat", "brand", "ptype", "segment", "priority", "ostatus")),
    "SELECT l_orderkey || '.' || l_linenumber || '.' || l_partkey || '.' || l_suppkey AS uid, l_quantity::INT AS qty, round(l_discount * 100)::INT AS disc, round(l_tax * 100)::INT AS tax, l_returnflag AS rflag, l_linestatus AS lstat, l_linenumber AS lnum, year(l_shipdate) AS syear, month(l_shipdate) AS smonth, p_brand AS brand, p_type AS ptype, p_size AS psize, c_mktsegment AS segment, o_orderpriority[1] AS priority, o_orderstatus AS ostatus FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey",
)


def census(spark: SparkSession, d: str) -> Wide:
    """Order lines with their orders, customers and parts: 14 attributes, 195 one-hot features."""
    lines = table(spark, d, "lineitem").join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey")).join(table(spark, d, "part"), F.col("l_partkey") == F.col("p_partkey"))
    cents = lambda c: F.round(F.col(c) * 100).cast("int")
    uid = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    df = lines.select(uid.alias("uid"), F.col("l_quantity").cast("int").alias("qty"), cents("l_discount").alias("disc"), cents("l_tax").alias("tax"), F.col("l_returnflag").alias("rflag"), F.col("l_linestatus").alias("lstat"), F.col("l_linenumber").alias("lnum"), F.year("l_shipdate").alias("syear"), F.month("l_shipdate").alias("smonth"), F.col("p_brand").alias("brand"), F.col("p_type").alias("ptype"), F.col("p_size").alias("psize"), F.col("c_mktsegment").alias("segment"), F.substring("o_orderpriority", 1, 1).alias("priority"), F.col("o_orderstatus").alias("ostatus"))
    return CENSUS.over(df)


LINES = Wide(
    None,
    ("qty", "disc", "tax", "rflag", "lstat", "lnum", "syear", "smonth", "suppkey"),
    frozenset(("rflag", "lstat")),
    "SELECT l_orderkey || '.' || l_linenumber || '.' || l_partkey || '.' || l_suppkey AS uid, l_quantity::INT AS qty, round(l_discount * 100)::INT AS disc, round(l_tax * 100)::INT AS tax, l_returnflag AS rflag, l_linestatus AS lstat, l_linenumber AS lnum, year(l_shipdate) AS syear, month(l_shipdate) AS smonth, l_suppkey AS suppkey FROM lineitem",
)


def lines_only(spark: SparkSession, d: str) -> Wide:
    cents = lambda c: F.round(F.col(c) * 100).cast("int")
    df = table(spark, d, "lineitem").select(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("uid"), F.col("l_quantity").cast("int").alias("qty"), cents("l_discount").alias("disc"), cents("l_tax").alias("tax"), F.col("l_returnflag").alias("rflag"), F.col("l_linestatus").alias("lstat"), F.col("l_linenumber").alias("lnum"), F.year("l_shipdate").alias("syear"), F.month("l_shipdate").alias("smonth"), F.col("l_suppkey").alias("suppkey"))
    return LINES.over(df)


EVOLVING = Wide(
    None,
    ("event_type", "hour", "k"),
    frozenset(("event_type",)),
    "SELECT user_id AS uid, arg_max(event_type, (ts, event_id)) AS event_type, arg_max(hour(ts), (ts, event_id)) AS hour, arg_max(CAST(props->>'$.k' AS INT), (ts, event_id)) AS k FROM events GROUP BY user_id",
)


def evolving(spark: SparkSession, d: str) -> Wide:
    """Event users and the last value of each feature."""
    e = table(spark, d, "events").select("user_id", "ts", "event_id", "event_type", F.hour("ts").alias("hour"), F.get_json_object("props", "$.k").cast("int").alias("k"))
    last = lambda c: F.max_by(c, F.struct("ts", "event_id")).alias(c)
    df = e.groupBy(F.col("user_id").alias("uid")).agg(last("event_type"), last("hour"), last("k"))
    return EVOLVING.over(df)


LETTERS = "aeiounrstdhlcéñüö"


def letter_frequencies(spark: SparkSession, d: str, least: int = 200) -> tuple[DataFrame, list[str]]:
    """doc_id, lang and the relative frequency of each letter in documents of at least so many characters."""
    t = table(spark, d, "documents").where(F.length("text") >= least).select("doc_id", "lang", F.lower("text").alias("t"))
    names = [f"x{n}" for n in range(len(LETTERS))]
    share = lambda ch: (F.length("t") - F.length(F.replace("t", F.lit(ch), F.lit("")))) / F.length("t")
    return t.select("doc_id", "lang", *(share(ch).alias(n) for n, ch in zip(names, LETTERS, strict=True))), names


def letters_sql(least: int = 200) -> str:
    cols = ", ".join(f"(length(t) - length(replace(t, '{ch}', '')))::DOUBLE / length(t) AS x{n}" for n, ch in enumerate(LETTERS))
    return f"SELECT doc_id, lang, {cols} FROM (SELECT doc_id, lang, lower(text) AS t FROM documents WHERE length(text) >= {least})"


def embedding_dims(spark: SparkSession, d: str) -> tuple[DataFrame, list[str]]:
    e = table(spark, d, "embeddings")
    names = [f"x{n}" for n in range(64)]
    return e.select(F.col("vec_id").alias("doc_id"), F.col("label").cast("string").alias("lang"), *(F.element_at("embedding", n + 1).cast("double").alias(x) for n, x in enumerate(names))), names


def quantised(df: DataFrame, names: list[str], bins: int = 10) -> DataFrame:
    """Each column as an equal-width bin of its range, from 0."""
    ends = df.agg(*(f(n).alias(f"{p}_{n}") for n in names for p, f in (("lo", F.min), ("hi", F.max))))  # one row
    cut = lambda n: F.least(F.floor((F.col(n) - F.col(f"lo_{n}")) * bins / F.greatest(F.col(f"hi_{n}") - F.col(f"lo_{n}"), F.lit(1e-300))), F.lit(bins - 1)).cast("int").alias(n)
    rest = [c for c in df.columns if c not in names]
    return df.crossJoin(F.broadcast(ends)).select(*rest, *map(cut, names))
