"""Access policies A to E on the derived vectors, as tags (vec_id, roles) and, for comparison, as DuckDB SQL."""

from __future__ import annotations

import string
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import doc, emb, emb_ids, lin, lin_ids, table

CUT = 10007


@dataclass(frozen=True)
class Zipf:
    """Shifted Zipf generator: block i weighs (i + s)^-alpha, a department's number of blocks follows (j + s2)^-alpha2, and a role reads some departments."""

    blocks: int
    s: float
    alpha: float
    departments: int
    s2: float
    alpha2: float
    roles: int

    def limits(self) -> list[int]:
        """Upper limits of the blocks' intervals, out of CUT."""
        w = [(i + self.s) ** -self.alpha for i in range(self.blocks)]
        out, run = [], 0.0
        for x in w:
            run += x
            out.append(round(CUT * run / sum(w)))
        out[-1] = CUT
        return out

    def roles_of(self) -> list[list[int]]:
        """Roles that read each block."""
        w = [(j + self.s2) ** -self.alpha2 for j in range(self.departments)]
        owned: list[set[int]] = [set() for _ in range(self.blocks)]
        for j, x in enumerate(w):
            n = max(1, -int(-self.blocks * x // sum(w)))
            for k in range(n):
                owned[(j * 37 + k * 11) % self.blocks].add(j)
        for i in range(self.blocks):
            owned[i].add((i * 5) % self.departments)
        reads = [{r for r in range(self.roles) if (r * 31 + j * 17 + r * j) % 7 < 2} | {j % self.roles} for j in range(self.departments)]
        return [sorted(set().union(*[reads[j] for j in own])) for own in owned]


D = Zipf(40, 1, 1.5, 12, 2, 1.5, 10)
E = Zipf(60, 1, 1.5, 24, 2, 1.5, 16)
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
LANGS = ("de", "en", "es", "fr")
ROLES = {"A": range(1, 6), "B": range(13), "C": range(14), "D": range(10), "E": range(16)}


def _roles(*when: tuple[int, Column]) -> Column:
    return F.array_compact(F.array(*[F.when(cond, F.lit(r)) for r, cond in when]))


def spread(vec_id: Column) -> Column:
    """A number below CUT for each id."""
    return (vec_id % CUT * 7919 + 13) % CUT


def zipf_tags(rows: DataFrame, z: Zipf) -> DataFrame:
    """vec_id, roles: the block of each id by its spread number. A row for each of the CUT numbers is told to all tasks."""
    limits = z.limits()
    blocks = list(zip([0, *limits], limits, z.roles_of(), strict=False))
    spans = rows.sparkSession.createDataFrame([b for b in blocks if b[0] < b[1]], "lo bigint, hi bigint, roles array<int>")
    codes = spans.select(F.explode(F.sequence("lo", F.col("hi") - 1)).alias("_u"), "roles")
    return rows.select("vec_id", spread(F.col("vec_id")).alias("_u")).join(F.broadcast(codes), "_u").select("vec_id", "roles")


def tags(spark: SparkSession, sf_dir: str, policy: str) -> DataFrame:
    """vec_id, roles (sorted): the tag of each vector."""
    c = F.col
    if policy == "A":
        conds = [c("vec_id") % 2 == 0, c("vec_id") % 3 == 0, c("vec_id") % 5 == 0, c("label") >= 5]
        free = ~(conds[0] | conds[1] | conds[2] | conds[3])
        return emb_ids(spark, sf_dir).select("vec_id", _roles(*enumerate([*conds, free], 1)).alias("roles"))
    if policy == "B":
        # customer and nation follow from their keys; orders and line items join by the order key
        nation = F.broadcast(table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey"))  # 25 rows by definition
        cust = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment").join(nation, c("c_nationkey") == c("n_nationkey"))
        orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderpriority").join(cust, c("o_custkey") == c("c_custkey"))
        rows = lin_ids(spark, sf_dir).join(orders, c("l_orderkey") == c("o_orderkey"))
        pairs = [(r, c("n_regionkey") == r) for r in range(5)] + [(5 + i, c("c_mktsegment") == s) for i, s in enumerate(SEGMENTS)]
        pairs += [(10, c("l_returnflag") == "R"), (11, c("l_linestatus") == "O"), (12, c("o_orderpriority") == "1-URGENT")]
        return rows.select("vec_id", _roles(*pairs).alias("roles"))
    if policy == "C":
        docs = table(spark, sf_dir, "documents").where("text is not null").select("doc_id", "lang", "source").join(table(spark, sf_dir, "labels"), "doc_id", "left")
        group = F.substring("source", 4, 10).cast("int") % 8
        pairs = [(i, c("lang") == x) for i, x in enumerate(LANGS)] + [(4 + g, group == g) for g in range(8)] + [(12, c("toxic") == 1), (13, c("quality") == 1)]
        return docs.select(c("doc_id").alias("vec_id"), _roles(*pairs).alias("roles"))
    if policy == "D":
        return zipf_tags(emb_ids(spark, sf_dir), D)
    return zipf_tags(lin_ids(spark, sf_dir), E)


def vectors(spark: SparkSession, sf_dir: str, policy: str) -> DataFrame:
    make = {"A": emb, "B": lin, "C": doc, "D": emb, "E": lin}[policy]
    return make(spark, sf_dir).select("vec_id", "embedding")


_LIN_IDS = "(SELECT *, CAST('0x' || substr(md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber)), 1, 15) AS BIGINT) AS vec_id FROM lineitem)"


def grants_sql(policy: str) -> str:
    """DuckDB: distinct (vec_id, role_id) of a policy."""
    if policy == "A":
        return """SELECT vec_id, r AS role_id FROM (SELECT vec_id, label, unnest([1, 2, 3, 4, 5]) AS r FROM embeddings)
        WHERE (r = 1 AND vec_id % 2 = 0) OR (r = 2 AND vec_id % 3 = 0) OR (r = 3 AND vec_id % 5 = 0) OR (r = 4 AND label >= 5)
        OR (r = 5 AND NOT (vec_id % 2 = 0 OR vec_id % 3 = 0 OR vec_id % 5 = 0 OR label >= 5))"""
    if policy == "B":
        segments = ", ".join(f"'{s}'" for s in SEGMENTS)
        return f"""SELECT vec_id, r AS role_id FROM (SELECT *, unnest(range(13)) AS r FROM {_LIN_IDS} JOIN orders ON l_orderkey = o_orderkey
        JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)
        WHERE n_regionkey = r OR (r BETWEEN 5 AND 9 AND [{segments}][r - 4] = c_mktsegment) OR (r = 10 AND l_returnflag = 'R')
        OR (r = 11 AND l_linestatus = 'O') OR (r = 12 AND o_orderpriority = '1-URGENT')"""
    if policy == "C":
        langs = ", ".join(f"'{s}'" for s in LANGS)
        return f"""SELECT doc_id AS vec_id, r AS role_id FROM (SELECT d.*, toxic, quality, unnest(range(14)) AS r FROM documents d LEFT JOIN labels l USING (doc_id) WHERE text IS NOT NULL)
        WHERE (r < 4 AND [{langs}][r + 1] = lang) OR (r BETWEEN 4 AND 11 AND CAST(substr(source, 4) AS INTEGER) % 8 = r - 4) OR (r = 12 AND toxic = 1) OR (r = 13 AND quality = 1)"""
    z, source = (D, "embeddings") if policy == "D" else (E, _LIN_IDS)
    limits = z.limits()
    values = ", ".join(f"({lo}, {hi}, {r})" for lo, hi, own in zip([0, *limits], limits, z.roles_of(), strict=False) for r in own)
    return f"SELECT vec_id, role_id FROM {source} JOIN (VALUES {values}) AS z(lo, hi, role_id) ON (vec_id % {CUT} * 7919 + 13) % {CUT} >= lo AND (vec_id % {CUT} * 7919 + 13) % {CUT} < hi"


def vectors_sql(policy: str) -> str:
    """DuckDB: vec_id, embedding of a policy's vectors."""
    if policy in "AD":
        return "SELECT vec_id, embedding FROM embeddings"
    if policy == "C":
        letters = ", ".join(f"(length(text) - length(replace(lower(text), '{x}', ''))) / greatest(length(text), 1)" for x in string.ascii_lowercase)
        return f"SELECT doc_id AS vec_id, [{letters}] AS embedding FROM documents WHERE text IS NOT NULL"
    return f"SELECT vec_id, [l_quantity / 50, l_extendedprice / 105000, l_discount / 0.1, l_tax / 0.08, l_linenumber / 7, month(l_shipdate) / 12, day(l_shipdate) / 31, (l_partkey % 1000) / 1000] AS embedding FROM {_LIN_IDS}"
