"""Claims: how often a key character at a template column goes with a value of an attribute."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Key that stands for a gap where gaps are asked for as keys.
GAP_KEY = "∅"


def unpivot_counts(df: DataFrame, code: str, attrs: list[str], allow_double: bool = False) -> DataFrame:
    """(code, attr, value, n): one scan and one shuffle of the tuples; all that follows is per distinct code.

    Null codes and values are left out. Arrays, maps and structs count by their JSON; doubles need
    allow_double, as equality on them is brittle.
    """
    kinds = dict(df.dtypes)
    if not allow_double and (bad := [a for a in attrs if kinds[a] in ("double", "float")]):
        raise ValueError(f"attributes of floating type: {bad}")
    text = [(F.to_json(a) if kinds[a].startswith(("array", "map", "struct")) else F.col(a).cast("string")).alias(a) for a in attrs]
    long = df.where(F.col(code).isNotNull()).select(F.col(code).alias("__code"), *text).unpivot("__code", attrs, "attr", "value")
    return long.where("value is not null").groupBy(F.col("__code").alias("code"), "attr", "value").agg(F.count("*").alias("n"))


def node_claims(members: DataFrame, counts: DataFrame, gap_as_key: bool = False) -> DataFrame:
    """(block, rep, card, col_ix, attr, key, value, n) for all members of all given nodes."""
    keys = members.select("block", "rep", "card", "code", F.posexplode("aligned").alias("pos", "ch"))
    keys = keys.select("block", "rep", "card", "code", (F.col("pos") + 1).alias("col_ix"), (F.coalesce("ch", F.lit(GAP_KEY)) if gap_as_key else F.col("ch")).alias("key")).where("key is not null")
    return keys.join(counts, "code").groupBy("block", "rep", "card", "col_ix", "attr", "key", "value").agg(F.sum("n").alias("n"))


def pair_claims(members: DataFrame, counts: DataFrame) -> DataFrame:
    """As node_claims, keyed by two columns: col_ix is the text 'i,j', key the two characters."""
    at = F.transform(F.sequence(F.lit(1), F.size("aligned")), lambda i: F.struct(i.alias("i"), F.element_at("aligned", i).alias("c")))
    real = F.filter(at, lambda x: x["c"].isNotNull())
    pairs = F.flatten(F.transform(real, lambda x: F.transform(F.filter(real, lambda y: y["i"] > x["i"]), lambda y: F.struct(F.concat_ws(",", x["i"], y["i"]).alias("col_ix"), F.concat(x["c"], y["c"]).alias("key")))))
    keys = members.select("block", "rep", "card", "code", F.explode(pairs).alias("p")).select("block", "rep", "card", "code", "p.col_ix", "p.key")
    return keys.join(counts, "code").groupBy("block", "rep", "card", "col_ix", "attr", "key", "value").agg(F.sum("n").alias("n"))


def measures(claims: DataFrame, by: list[str]) -> DataFrame:
    """support, claims, confidence, diversity and inner_support of each group of claims (key, value, n).

    Sums run over partial aggregates: (by, key, value), then (by, key), then by.
    """
    kv = claims.groupBy(*by, "key", "value").agg(F.sum("n").alias("n"))
    top = kv.groupBy(*by, "key").agg(F.max("n").alias("most"), F.sum("n").alias("all")).groupBy(*by).agg(F.sum("most").alias("support"), F.sum("all").alias("claims"), F.max("most").alias("inner_support"))
    kinds = kv.groupBy(*by).agg(F.count_distinct("value").alias("diversity"))
    joined = top.join(kinds, by) if by else top.crossJoin(F.broadcast(kinds))  # without groups both are one row
    return joined.withColumn("confidence", F.col("support") / F.col("claims")).select(*by, "support", "confidence", "diversity", "inner_support", "claims")


def satisfies(claims: DataFrame, by: list[str]) -> DataFrame:
    """Whether no key has two values, for each group."""
    keys = claims.groupBy(*by, "key").agg(F.count_distinct("value").alias("values"))
    return keys.groupBy(*by).agg(F.max("values").alias("most")).select(*by, (F.col("most") == 1).alias("satisfied"))


def largest_count(keys: DataFrame, key: str = "key") -> DataFrame:
    """Occurrences of the most frequent value."""
    return keys.groupBy(key).agg(F.count("*").alias("n")).agg(F.max("n").alias("eta"))
