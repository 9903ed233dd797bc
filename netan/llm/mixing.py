"""Mixing sources to target weights, in DataFrame functions only.

The tree is domain - language - source. Weights are relative among siblings. Budgets go down the tree: a node's budget is
shared among its children by weight; a child that can't use its share (its supply times the allowed epochs) takes what it can,
and its siblings share the shortage by weight. What all children of a node together can't use has been left to the node's
own siblings before, since a node's supply is that of all leaves below it. So siblings come before ancestors.

A leaf's budget buys whole epochs of its documents and then a token-prefix of one more: documents in the order of a hash of
(seed, epoch, id) as long as their tokens fit. Prefixes are found in steps: sums over at most 2^16 hash ranges of a leaf, for
large leaves sums over as many parts of the one range where the budget ends, then an order within the last range. So a
leaf, however large, gives a task neither more than 2^16 sums nor more rows than about RANGE_ROWS to put in order.

Nulls: null texts hold no token; rows without tokens are never chosen; null language or source is a node named "null". Rows
that repeat an id have the same hash; they are taken in the order of their tokens, and equal rows together if both fit. Very
long texts are documents like any other; one that doesn't fit is left out with all behind it. Columns beside id, text, lang,
source and those to keep are not read, whatever their names. Empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from netan.storage import written

LEVELS = ("domain", "lang", "source")
#: Documents that share one hash range of a leaf, on average.
RANGE_ROWS = 512
#: Bits of the hash by which one step divides.
LEVEL_BITS = 16


def hash01(seed: int, epoch: Column, key: Column) -> Column:
    """A number from 0 to 2^32 - 1 out of seed, epoch and key."""
    text = F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(key.cast("string"), F.lit("null")))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def words(text: Column) -> Column:
    """Tokens of a text as this operator counts them: runs that hold no ASCII white space."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def share(nodes: DataFrame, parent: list[str], budget: str, out: str) -> DataFrame:
    """nodes with `out`, the part of the parent's `budget` that each child (weight, supply) gets; whole tokens, rounded down."""
    full = F.col("supply") / F.col("weight")
    order = [full.asc(), *(F.col(c).asc() for c in LEVELS if c in nodes.columns)]
    before = Window.partitionBy(*parent).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    rest = Window.partitionBy(*parent).orderBy(*order).rowsBetween(0, Window.unboundedFollowing)
    level = (F.col(budget) - F.coalesce(F.sum("supply").over(before), F.lit(0))) / F.sum("weight").over(rest)
    # children come by the level at which they are full; the first that isn't full sets the level for the rest
    nodes = nodes.withColumn("_level", level).withColumn("_open", F.col("_level") < full)
    first = Window.partitionBy(*parent)
    nodes = nodes.withColumn("_stop", F.min(F.when(F.col("_open"), F.struct(full.alias("full"), F.col("_level").alias("level")))).over(first))
    got = F.when(F.col("_stop").isNull() | (full < F.col("_stop.full")), F.col("supply").cast("double"))
    got = got.otherwise(F.least(F.col("supply").cast("double"), F.floor(F.col("weight") * F.col("_stop.level")).cast("double")))
    return nodes.withColumn(out, got.cast("long")).drop("_level", "_open", "_stop")


def budgets(supplies: DataFrame, weight: Column, total: Column, epochs: int) -> DataFrame:
    """(domain, lang, source, tokens, rows, budget) of each leaf; weight: of a node by its (domain, lang, source), null above a leaf."""
    leaves = supplies.withColumn("supply", F.col("tokens") * F.lit(epochs))
    null = F.lit(None).cast("string")
    mids = leaves.groupBy("domain", "lang").agg(F.sum("supply").alias("supply"))
    tops = mids.groupBy("domain").agg(F.sum("supply").alias("supply"))
    tops = tops.withColumn("lang", null).withColumn("source", null).withColumn("weight", weight)
    tops = share(tops.withColumn("whole", F.lit(1)).withColumn("total", total), ["whole"], "total", "domain_budget").select("domain", "domain_budget")
    mids = mids.withColumn("source", null).withColumn("weight", weight).join(tops, "domain")
    mids = share(mids, ["domain"], "domain_budget", "lang_budget").select("domain", "lang", "lang_budget")
    leaves = leaves.withColumn("weight", weight).join(mids, ["domain", "lang"])
    return share(leaves, ["domain", "lang"], "lang_budget", "budget").select(*LEVELS, "tokens", "rows", "budget")


def mix(docs: DataFrame, domain: Column, weight: Column, share_of_supply: float = 0.5, epochs: int = 4, seed: int = 1, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, domain, lang, source, n_tokens, copies[, keep...]) of each chosen row: copies says in how many epochs it is used.

    domain: of a row by lang and source. weight: whole numbers of 1 or more. The total is share_of_supply of one epoch's tokens.
    """
    name = lambda c: F.coalesce(docs[c].cast("string"), F.lit("null"))
    rows = docs.select(docs["doc_id"].alias("doc_id"), name("lang").alias("lang"), name("source").alias("source"), words(docs["text"]).alias("n_tokens"), *(docs[c].alias(f"_{c}") for c in keep))
    rows = rows.withColumn("domain", domain)
    thin = docs.select(docs["doc_id"].alias("doc_id"), name("lang").alias("lang"), name("source").alias("source"), words(docs["text"]).alias("n_tokens")).withColumn("domain", domain)
    supplies = thin.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("tokens"), F.count("*").alias("rows")).where("tokens > 0")
    supplies = written(supplies, "leaf-supplies")  # a row per leaf
    whole = supplies.agg(F.floor(F.sum("tokens") * F.lit(share_of_supply)).alias("total"))
    total = whole.first()["total"] or 0  # one row
    leaves = written(budgets(supplies, weight, F.lit(float(total)), epochs), "leaf-budgets")
    leaves = leaves.select(
        *LEVELS,
        F.floor(F.col("budget") / F.col("tokens")).alias("epochs"),
        (F.col("budget") % F.col("tokens")).alias("rest"),
        # ranges of a leaf: a power of two of the 2^32 hash values each
        F.least(F.lit(32), F.greatest(F.lit(0), F.ceil(F.log2(F.col("rows") / F.lit(float(RANGE_ROWS)))))).cast("int").alias("bits"),
    )

    bits = leaves.agg(F.max("bits")).first()[0] or 0  # one row

    def ranged(rows: DataFrame, leaves: DataFrame, bits: Column) -> DataFrame:
        """rows with the leaf's columns, the hash and the range of `bits` bits that holds it."""
        rows = rows.where("n_tokens > 0").join(F.broadcast(leaves), list(LEVELS))
        rows = rows.withColumn("h", hash01(seed, F.col("epochs") + 1, F.col("doc_id")))
        return rows.withColumn("range", F.floor(F.col("h") / F.pow(F.lit(2.0), F.lit(32) - bits)).cast("long"))

    def ends(rows: DataFrame, before: Column) -> DataFrame:
        """(levels, edge, edge_before): of each leaf, the range in which its budget ends; before: tokens ahead of all these ranges."""
        sums = rows.groupBy(*LEVELS, "range", "rest", before.alias("base")).agg(F.sum("n_tokens").alias("n"))
        over = Window.partitionBy(*LEVELS).orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
        sums = sums.withColumn("before", F.col("base") + F.coalesce(F.sum("n").over(over), F.lit(0)))
        return sums.where("before <= rest AND before + n > rest").select(*LEVELS, F.col("range").alias("edge"), F.col("before").alias("edge_before"))

    coarse = F.least("bits", F.lit(LEVEL_BITS))
    edge = ends(ranged(thin, leaves, coarse), F.lit(0).cast("long"))
    if bits > LEVEL_BITS:
        edge = written(edge, "leaf-edges")
        inside = ranged(thin, leaves.join(edge, list(LEVELS)), F.col("bits"))
        inside = inside.where(F.floor(F.col("range") / F.pow(F.lit(2.0), F.col("bits") - coarse)).cast("long") == F.col("edge"))
        edge = ends(inside, F.col("edge_before"))
    rows = ranged(rows, leaves, F.col("bits")).join(F.broadcast(edge), list(LEVELS))
    sure = rows.where("range <> edge").withColumn("copies", F.col("epochs") + F.when(F.col("range") < F.col("edge"), 1).otherwise(0))
    over = Window.partitionBy(*LEVELS).orderBy("h", F.col("doc_id").asc_nulls_first(), "n_tokens").rowsBetween(Window.unboundedPreceding, 0)
    last = rows.where("range = edge").withColumn("upto", F.col("edge_before") + F.sum("n_tokens").over(over))
    last = last.withColumn("copies", F.col("epochs") + F.when(F.col("upto") <= F.col("rest"), 1).otherwise(0)).drop("upto")
    out = sure.unionByName(last).where("copies > 0")
    return out.select("doc_id", *LEVELS, "n_tokens", F.col("copies").cast("long").alias("copies"), *(F.col(f"_{c}") for c in keep))


def sql(domain: str, weights: tuple[str, str, str], share_of_supply: float, epochs: int, seed: int) -> str:
    """mix() for DuckDB, with one running sum over each whole leaf; domain by lang and source, weights of domains, languages, sources."""

    def shared(nodes: str, parent: str, budget: str, key: str) -> str:
        w = f"PARTITION BY {parent} ORDER BY supply / weight, {key}"
        return f"""(SELECT *, CASE WHEN stop IS NULL OR supply / weight < stop.f THEN supply ELSE least(supply, floor(weight * stop.l)::BIGINT) END AS got FROM (
          SELECT *, min(CASE WHEN lv < supply / weight THEN struct_pack(f := supply / weight, l := lv) END) OVER (PARTITION BY {parent}) AS stop FROM (
          SELECT *, ({budget} - coalesce(sum(supply) OVER ({w} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE / sum(weight) OVER ({w} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)::DOUBLE AS lv FROM {nodes})))"""

    leaf = "domain, lang, source"
    return f"""
WITH d0 AS (SELECT doc_id, coalesce(lang, 'null') AS lang, coalesce(source, 'null') AS source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::BIGINT AS n_tokens FROM documents),
d AS MATERIALIZED (SELECT *, {domain} AS domain FROM d0),
leaves AS MATERIALIZED (SELECT {leaf}, sum(n_tokens)::BIGINT AS tokens, sum(n_tokens)::BIGINT * {epochs} AS supply, {weights[2]} AS weight FROM d GROUP BY {leaf} HAVING sum(n_tokens) > 0),
whole AS (SELECT floor(sum(tokens) * {share_of_supply})::BIGINT AS total FROM leaves),
tops AS MATERIALIZED (SELECT domain, got AS top FROM {shared(f"(SELECT domain, sum(supply)::BIGINT AS supply, {weights[0]} AS weight, 1 AS one, (SELECT total FROM whole) AS total FROM leaves GROUP BY domain)", "one", "total", "domain")}),
mids AS MATERIALIZED (SELECT domain, lang, got AS mid FROM {shared(f"(SELECT domain, lang, supply, {weights[1]} AS weight, top FROM (SELECT domain, lang, sum(supply)::BIGINT AS supply FROM leaves GROUP BY domain, lang) JOIN tops USING (domain))", "domain", "top", "lang")}),
budgets AS MATERIALIZED (SELECT {leaf}, got // tokens AS e, got % tokens AS rest FROM {shared("(SELECT * FROM leaves JOIN mids USING (domain, lang))", "domain, lang", "mid", "source")}),
ranked AS (SELECT doc_id, {leaf}, n_tokens, e, rest, sum(n_tokens) OVER (PARTITION BY {leaf} ORDER BY ('0x' || substr(md5(concat_ws(':', '{seed}', e + 1, coalesce(doc_id::VARCHAR, 'null'))), 1, 8))::BIGINT, doc_id NULLS FIRST, n_tokens ROWS UNBOUNDED PRECEDING) AS upto FROM d JOIN budgets USING ({leaf}) WHERE n_tokens > 0)
SELECT doc_id, {leaf}, n_tokens, (e + (upto <= rest)::INT)::BIGINT AS copies FROM ranked WHERE e + (upto <= rest)::INT > 0"""
