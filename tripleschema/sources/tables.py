"""The given tables as triple graphs: one scan per table, all its triples from one explode."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tripleschema.model import TRIPLE_SCHEMA, Atom, is_var


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def iri(prefix: str, *keys: str | Column) -> Column:
    """An IRI of key columns, null if any of them is."""
    parts: list[Column] = []
    for k in keys:
        parts += [F.lit("_"), F.col(k).cast("string") if isinstance(k, str) else k]
    return F.concat(F.lit(f"{prefix}:"), *parts[1:])


def money(c: str) -> Column:
    return F.col(c).cast("decimal(18,2)").cast("string")


@dataclass(frozen=True)
class Edge:
    """A triple that each row gives."""

    s: Column
    p: str
    o: Column
    lit: Column
    const: str | None

    def column(self) -> Column:
        return F.struct(self.s.alias("s"), F.lit(self.p).alias("p"), self.o.alias("o"), self.lit.alias("o_lit"))

    def wanted(self, atoms: Sequence[Atom] | None) -> bool:
        """Whether a triple of this edge can match one of the atoms, by its predicate and fixed object."""
        return atoms is None or any((is_var(a.p) or a.p == self.p) and (self.const is None or is_var(a.o) or a.o == self.const) for a in atoms)


def edge(s: Column, p: str, o: Column | str, lit: bool | Column = False) -> Edge:
    return Edge(s, p, F.lit(o) if isinstance(o, str) else o, F.lit(lit) if isinstance(lit, bool) else lit, o if isinstance(o, str) else None)


def triples(df: DataFrame, edges: Sequence[Edge], wanted: Sequence[Atom] | None = None, unique: bool = False) -> DataFrame | None:
    """The distinct triples that each row gives, of the edges that are wanted; None if none is.

    An edge with a null subject or object is none.  With ``unique`` the rows have a primary key, which is the subject of
    all edges, so no triple comes twice and nothing is shuffled."""
    edges = [e for e in edges if e.wanted(wanted)]
    if not edges:
        return None
    if len(edges) == 1:
        e = edges[0]
        rows = df.select(e.s.alias("s"), F.lit(e.p).alias("p"), e.o.alias("o"), e.lit.alias("o_lit"))
    else:
        rows = df.select(F.explode(F.array(*(e.column() for e in edges))).alias("t")).select("t.s", "t.p", "t.o", "t.o_lit")
    rows = rows.where("s is not null and o is not null")
    return rows if unique else rows.distinct()


def union(parts: Sequence[DataFrame | None], spark: SparkSession) -> DataFrame:
    parts = [p for p in parts if p is not None]
    return reduce(DataFrame.unionByName, parts) if parts else spark.createDataFrame([], TRIPLE_SCHEMA)


# Each graph takes the atoms that are asked: tables and columns that cannot match any are not read.


def events(spark: SparkSession, sf_dir: str, wanted: Sequence[Atom] | None = None) -> DataFrame:
    """Readings at places, and the badge tags that are held."""
    ev = iri("ev", "event_id")
    error = F.col("event_type") == "error"
    result = F.when(F.col("event_type") == "purchase", iri("tag", F.get_json_object("props", "$.k"))).when(error, F.when(F.col("value") >= 100, "1").otherwise("0")).otherwise(money("value"))
    readings = triples(table(spark, sf_dir, "events"), [edge(ev, ":senses", iri("prop", "event_type")), edge(ev, ":at", iri("place", "user_id")), edge(ev, ":reads", result, F.col("event_type") != "purchase")], wanted, unique=True)
    held = table(spark, sf_dir, "supplier").where("s_acctbal > 0")
    tags = triples(held, [edge(iri("tag", "s_suppkey"), "a", ":BadgeTag"), edge(iri("tag", "s_suppkey"), ":heldBy", iri("supp", "s_suppkey"))], wanted, unique=True)
    return union([readings, tags], spark)


def star(spark: SparkSession, sf_dir: str, wanted: Sequence[Atom] | None = None) -> DataFrame:
    """Regions, nations, customers, suppliers, orders and their lines."""
    t = lambda n: table(spark, sf_dir, n)
    of = lambda n, edges, unique=True: triples(t(n), edges, wanted, unique)
    reg, nat, cust, supp, order = iri("reg", "r_regionkey"), iri("nat", "n_nationkey"), iri("cust", "c_custkey"), iri("supp", "s_suppkey"), iri("ord", "o_orderkey")
    line = iri("line", "l_orderkey", "l_linenumber")
    return union([
        of("region", [edge(reg, "a", ":Region"), edge(reg, ":label", F.col("r_name"), True)]),
        of("nation", [edge(nat, "a", ":Nation"), edge(nat, ":label", F.col("n_name"), True), edge(nat, ":within", iri("reg", "n_regionkey"))]),
        of("customer", [edge(cust, "a", ":Customer"), edge(cust, ":within", iri("nat", "c_nationkey")), edge(cust, ":segment", iri("seg", "c_mktsegment")), edge(cust, ":balance", money("c_acctbal"), True)]),
        of("supplier", [edge(supp, "a", ":Supplier"), edge(supp, ":within", iri("nat", "s_nationkey")), edge(supp, ":suppliedFrom", iri("nat", "s_nationkey")), edge(supp, ":balance", money("s_acctbal"), True)]),
        of("orders", [edge(order, "a", ":Order"), edge(order, ":placedBy", iri("cust", "o_custkey")), edge(order, ":status", iri("st", "o_orderstatus")), edge(order, ":priority", iri("pr", "o_orderpriority")), edge(order, ":total", money("o_totalprice"), True)]),
        of("lineitem", [edge(line, "a", ":Line"), edge(line, ":ofOrder", iri("ord", "l_orderkey")), edge(line, ":fromSupplier", iri("supp", "l_suppkey"))], unique=False),
    ], spark)


def documents(spark: SparkSession, sf_dir: str, wanted: Sequence[Atom] | None = None) -> DataFrame:
    """Documents with language, source, size, and the marks of those that are labelled."""
    doc = iri("doc", "doc_id")
    docs = triples(table(spark, sf_dir, "documents"), [edge(doc, "a", ":Document"), edge(doc, ":lang", iri("lang", "lang")), edge(doc, ":source", iri("src", "source")), edge(doc, ":chars", F.col("n_chars").cast("string"), True)], wanted)
    marks = triples(table(spark, sf_dir, "labels"), [edge(doc, ":quality", F.col("quality").cast("string"), True), edge(doc, ":toxic", F.col("toxic").cast("string"), True)], wanted)
    return union([docs, marks], spark)


def conversations(spark: SparkSession, sf_dir: str, wanted: Sequence[Atom] | None = None) -> DataFrame:
    """Turns of conversations and which one follows which."""
    turn = iri("turn", "conv_id", "turn")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role")
    turns = triples(rows, [edge(turn, "a", ":Turn"), edge(turn, ":inConv", iri("conv", "conv_id")), edge(turn, ":role", iri("role", "role"))], wanted)
    after = rows.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("turn").alias("t1")).distinct()
    follows = rows.select("conv_id", "turn").distinct().join(after, ["conv_id", "turn"])
    return union([turns, triples(follows, [edge(turn, ":next", iri("turn", "conv_id", "t1"))], wanted, unique=True)], spark)


def pages(spark: SparkSession, sf_dir: str, wanted: Sequence[Atom] | None = None) -> DataFrame:
    """Pages, their hosts, and the paths they link to."""
    page = iri("page", "page_id")
    rows = table(spark, sf_dir, "pages")
    hosts = triples(rows.withColumn("host", F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1)), [edge(page, ":host", iri("host", "host"))], wanted)
    links = rows.select("page_id", F.explode(F.regexp_extract_all("html", F.lit(r'href="(/[^"]*)"'), F.lit(1))).alias("path"))
    return union([hosts, triples(links, [edge(page, ":linksTo", iri("path", "path"))], wanted)], spark)


GRAPHS = {"events": events, "star": star, "documents": documents, "conversations": conversations, "pages": pages}
