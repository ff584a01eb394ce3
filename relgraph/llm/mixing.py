"""Mixing sources to target weights, by hierarchical budgeting.

A token budget flows down a tree of domains, languages and sources. At each node it is shared among the
children by weight; a child that cannot use its share, because its documents times the allowed epochs hold
fewer tokens, passes what is short to its siblings, and only what no sibling can take goes to the siblings
of the parent, as a parent's capacity is that of its leaves. A leaf with a quota of q tokens and a tokens of
text gives q div a whole epochs and the first q mod a tokens of one more, in an order seeded by epoch.

The prefix of a leaf is found without gathering it: the hash that orders it is read eight bits at a time,
token sums over these bits tell in which part the prefix ends, and after three readings only that part is
put in order.

Null tree values count as empty names, null and empty texts as one token, null or missing weights as 0 (then the node
gets nothing unless all its siblings have none, when they share evenly). Very long texts are one document and the one
at the end of a prefix is cut, not dropped. Ties in order fall to doc_id; a null doc_id is ordered by a hash of the text.
Rows that repeat a doc_id are documents of their own; those that share a place in the order are taken alike. Columns of
the input are kept where documents are returned; own columns start with an underscore, or with more where the
input has such a name already, so names do not clash. Empty tables or budgets: no rows.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.llm.common import staged

LEVELS, BITS, DIGITS = 3, 8, 15
#: Most leaves that are broadcast; with more, documents and leaves are joined by shuffling.
FEW_LEAVES = 50_000
FINE = "long"


def tokens(text: str = "text") -> Column:
    """Tokens of a text, counted as its blanks and line ends plus one."""
    t = F.coalesce(F.col(text), F.lit(""))
    return (F.length(t) - F.length(F.translate(t, " \n", "")) + 1).cast(FINE)


def prefix(text: str, count: Column) -> Column:
    """The first so many tokens of a text, without the blank or line end behind them."""
    head = F.call_function("substring_index", F.translate(F.col(text), "\n", " "), F.lit(" "), count.cast("int"))
    return F.substring(F.col(text), F.lit(1), F.length(head))


def free_names(wanted: Sequence[str], taken: Sequence[str]) -> list[str]:
    """The names with an underscore before them, and more of these until none is taken; case does not tell names apart."""
    line, known = "_", {c.lower() for c in taken}
    while any((line + n).lower() in known for n in wanted):
        line += "_"
    return [line + n for n in wanted]


def order_key(seed: int, epoch: Column, key: Column) -> Column:
    """60 bits that order a leaf in an epoch: the first 15 hexadecimal digits of an md5."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), key.cast("string"))), 1, DIGITS), 16, 10).cast(FINE)


def share(nodes: DataFrame, parents: Sequence[str], name: str) -> DataFrame:
    """Add `_quota` to siblings with columns _budget (of their parent), _capacity and _weight.

    Siblings that the water level covers are those with the least capacity for their weight.
    """
    w = Window.partitionBy(*parents) if parents else Window.partitionBy(F.lit(0))
    ratio = F.col("_capacity").cast("double") / F.col("_weight")
    rising = w.orderBy(F.when(F.col("_weight") > 0, ratio).otherwise(F.lit(float("inf"))), name)
    before, rest = rising.rowsBetween(Window.unboundedPreceding, -1), rising.rowsBetween(0, Window.unboundedFollowing)
    nodes = nodes.withColumn("_weight", F.when(F.sum("_weight").over(w) > 0, F.col("_weight")).otherwise(F.lit(1).cast(FINE)))
    nodes = nodes.withColumn("_used", F.coalesce(F.sum("_capacity").over(before), F.lit(0))).withColumn("_open", F.sum("_weight").over(rest))
    full = (F.col("_weight") > 0) & (F.col("_capacity") * F.col("_open") <= (F.col("_budget") - F.col("_used")) * F.col("_weight"))
    nodes = nodes.withColumn("_full", full)
    taken = F.sum(F.when(F.col("_full"), F.col("_capacity")).otherwise(0)).over(w)
    heavy = F.sum(F.when(F.col("_full"), 0).otherwise(F.col("_weight"))).over(w)
    nodes = nodes.withColumn("_taken", taken).withColumn("_heavy", heavy)
    part = F.expr("(_budget - _taken) * _weight div _heavy")
    quota = F.when(F.col("_full"), F.col("_capacity")).when(F.col("_heavy") > 0, part).otherwise(0)
    return nodes.withColumn("_quota", quota.cast(FINE)).drop("_used", "_open", "_full", "_taken", "_heavy", "_budget")


def quotas(leaves: DataFrame, tree: Sequence[str], weights: Sequence[Column], budget: int, epochs: int) -> DataFrame:
    """Leaves (tree columns, _tokens) with `_quota`, at most `epochs` times their tokens."""
    leaves = leaves.withColumn("_capacity", F.col("_tokens") * epochs)
    above = None
    for depth in range(1, len(tree) + 1):
        names = list(tree[:depth])
        nodes = leaves.groupBy(*names).agg(F.sum("_capacity").alias("_capacity"))
        nodes = nodes.withColumn("_weight", F.coalesce(weights[depth - 1].cast(FINE), F.lit(0)))
        if above is None:
            nodes = nodes.withColumn("_budget", F.lit(budget).cast(FINE))
        else:
            nodes = nodes.join(above.withColumnRenamed("_quota", "_budget"), names[:-1])
        above = share(nodes, names[:-1], names[-1]).select(*names, "_quota")
    return leaves.join(above, list(tree)).drop("_capacity")


def chosen(df: DataFrame, tree: Sequence[tuple[str, Column]], weights: Sequence[Column], budget: int | float, epochs: int = 4, seed: int = 1, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Documents with their tree columns, `_epoch` (from 0), `_tokens` and `_take`, a row for each epoch they serve in;
    these come last and have more underscores where the input has such names.

    tree: name and value of each level; weights: an integer for each level, from the tree columns so far.
    A budget below 1 is a share of all tokens, others are tokens. The document at the end of a prefix is
    taken in part (`_take` below `_tokens`).
    """
    names = [n for n, _ in tree]
    own = free_names([*names, "epoch", "tokens", "take"], df.columns)
    ident = F.when(F.col(key).isNull(), F.concat(F.lit("n"), F.xxhash64(text).cast("string"))).otherwise(F.col(key).cast("string"))
    levels = [F.coalesce(v.cast("string"), F.lit("")).alias(n) for n, v in tree]
    # The input's columns travel in one struct, apart from all names used here.
    docs = df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("_row"), ident.alias("_ident"), tokens(text).alias("_tokens"), *levels)
    key = "_ident"
    leaves = staged(docs.groupBy(*names).agg(F.sum("_tokens").alias("_tokens")), "leaves")
    total, count = leaves.agg(F.coalesce(F.sum("_tokens"), F.lit(0)), F.count("*")).first()
    budget = int(total * budget) if budget < 1 else int(budget)
    found = quotas(leaves, names, weights, budget, epochs)
    found = found.withColumn("_whole", F.expr("_quota div _tokens")).withColumn("_rest", F.expr("_quota % _tokens"))
    found = staged(found.select(*names, "_whole", "_rest").withColumn("_part", F.lit(0).cast(FINE)), "quotas")
    small = count <= FEW_LEAVES
    near = lambda leaf: F.broadcast(leaf) if small else leaf
    keyed = docs.select(key, "_tokens", *names).join(near(found.select(*names, "_whole")), names)
    keyed = staged(keyed.withColumn("_order", order_key(seed, F.col("_whole"), F.col(key))).drop("_whole"), "order")
    for level in range(LEVELS):
        left = 4 * DIGITS - BITS * (level + 1)
        cut = F.shiftrightunsigned("_order", left)
        inside = keyed.withColumn("_bits", cut).join(near(found.select(*names, "_part", "_rest")), names).where(F.shiftright("_bits", BITS) == F.col("_part"))
        sums = inside.groupBy(*names, "_rest", "_bits").agg(F.sum("_tokens").alias("_n"))  # 256 rows a leaf at most
        rising = Window.partitionBy(*names).orderBy("_bits").rowsBetween(Window.unboundedPreceding, -1)
        sums = sums.withColumn("_before", F.coalesce(F.sum("_n").over(rising), F.lit(0)))
        ends = sums.where((F.col("_before") < F.col("_rest")) & (F.col("_rest") <= F.col("_before") + F.col("_n")))
        ends = ends.select(*names, F.col("_bits").alias("_next"), (F.col("_rest") - F.col("_before")).alias("_left"))
        found = staged(
            found.join(ends, names, "left").select(*names, "_whole", F.coalesce("_next", F.lit(0).cast(FINE)).alias("_part"), F.coalesce("_left", F.lit(0).cast(FINE)).alias("_rest")), "quotas"
        )
    cut = F.shiftrightunsigned("_order", 4 * DIGITS - BITS * LEVELS)
    last = keyed.withColumn("_bits", cut).join(near(found.select(*names, "_part", "_rest")), names).where(F.col("_bits") == F.col("_part"))
    rising = Window.partitionBy(*names).orderBy("_order", key).rowsBetween(Window.unboundedPreceding, -1)
    last = last.withColumn("_before", F.coalesce(F.sum("_tokens").over(rising), F.lit(0))).where(F.col("_before") < F.col("_rest"))
    last = last.groupBy(*names, key).agg(F.max(F.least(F.col("_tokens"), F.col("_rest") - F.col("_before"))).alias("_partial"))
    last = last.withColumnsRenamed({n: f"_l_{n}" for n in [*names, key]})
    docs = docs.join(near(found), names)
    order = F.shiftrightunsigned(order_key(seed, F.col("_whole"), F.col(key)), 4 * DIGITS - BITS * LEVELS)
    docs = docs.withColumn("_bits", order)
    same = F.col(key).eqNullSafe(F.col(f"_l_{key}"))
    for n in names:
        same = same & (F.col(n) == F.col(f"_l_{n}"))
    docs = docs.join(last, same, "left").drop(*(f"_l_{n}" for n in [*names, key]))
    more = F.when(F.col("_bits") < F.col("_part"), F.col("_tokens")).otherwise(F.coalesce("_partial", F.lit(0).cast(FINE)))
    docs = docs.withColumn("_more", more)
    docs = docs.withColumn("_epoch", F.explode(F.sequence(F.lit(0).cast(FINE), F.col("_whole")))).where((F.col("_epoch") < F.col("_whole")) | (F.col("_more") > 0))
    docs = docs.withColumn("_take", F.when(F.col("_epoch") < F.col("_whole"), F.col("_tokens")).otherwise(F.col("_more")))
    made = [F.col(c).alias(o) for c, o in zip([*names, "_epoch", "_tokens", "_take"], own, strict=True)]
    return docs.select("_row", *made).select("_row.*", *own)


def corpus_tree() -> list[tuple[str, Column]]:
    """Levels of the documents table: a domain is the first four letters of the source."""
    return [("domain", F.substring("source", 1, 4)), ("language", F.col("lang")), ("origin", F.col("source"))]


def corpus_weights() -> list[Column]:
    """Domains count alike but for src0, which counts three times; English five, others two each; sources alike."""
    return [F.when(F.col("domain") == "src0", 3).otherwise(1), F.when(F.col("language") == "en", 5).otherwise(2), F.lit(1)]


def mix(df: DataFrame, budget: int | float = 0.5, epochs: int = 4, seed: int = 1) -> DataFrame:
    """(doc_id, domain, language, origin, epoch, tokens, take) of what the documents table gives to the mix."""
    found = chosen(df, corpus_tree(), corpus_weights(), budget, epochs, seed)
    return found.select("doc_id", *(F.col(f"_{n}").alias(n) for n in ("domain", "language", "origin", "epoch", "tokens", "take")))


def _sql_share(level: int, names: list[str], weight: str, above: str | None) -> str:
    """One level of the budget as SQL, for DuckDB."""
    own, parents = names[level], names[:level]
    by = f"PARTITION BY {', '.join(parents)}" if parents else ""
    join = f"JOIN {above} USING ({', '.join(parents)})" if above else ""
    budget = "quota" if above else "(SELECT CAST(floor(sum(tokens) * 0.5) AS BIGINT) FROM leaves)"
    every = ", ".join(names[: level + 1])
    return f"""
n{level} AS (SELECT {every}, CAST(sum(capacity) AS BIGINT) AS capacity, CAST(max({weight}) AS BIGINT) AS weight FROM leaves GROUP BY {every}),
b{level} AS (SELECT {every}, capacity, weight, {budget} AS budget FROM n{level} {join}),
r{level} AS (SELECT *, coalesce(sum(capacity) OVER (f ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS used,
  sum(weight) OVER (f ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS heavy FROM b{level}
  WINDOW f AS ({by} ORDER BY CAST(capacity AS DOUBLE) / weight, {own})),
s{level} AS (SELECT *, capacity * heavy <= (budget - used) * weight AS covered FROM r{level}),
q{level} AS (SELECT {every}, CAST(CASE WHEN covered THEN capacity ELSE (budget - sum(CASE WHEN covered THEN capacity ELSE 0 END) OVER p) * weight
  // sum(CASE WHEN covered THEN 0 ELSE weight END) OVER p END AS BIGINT) AS quota FROM s{level} WINDOW p AS ({by}))"""


def mix_sql() -> str:
    """SQL with the rows of `mix`, for DuckDB."""
    names = ["domain", "language", "origin"]
    weights = ["CASE WHEN domain = 'src0' THEN 3 ELSE 1 END", "CASE WHEN language = 'en' THEN 5 ELSE 2 END", "1"]
    parts = [_sql_share(i, names, weights[i], f"q{i - 1}" if i else None) for i in range(3)]
    return f"""WITH docs AS (SELECT doc_id, substr(coalesce(source, ''), 1, 4) AS domain, coalesce(lang, '') AS language, coalesce(source, '') AS origin,
  length(coalesce(text, '')) - length(replace(replace(coalesce(text, ''), ' ', ''), chr(10), '')) + 1 AS tokens FROM documents),
leaves AS (SELECT domain, language, origin, CAST(sum(tokens) AS BIGINT) AS tokens, CAST(sum(tokens) AS BIGINT) * 4 AS capacity FROM docs GROUP BY ALL),
{",".join(parts)},
leaf AS (SELECT domain, language, origin, quota // l.tokens AS whole, quota % l.tokens AS rest FROM leaves l JOIN q2 USING (domain, language, origin)),
ordered AS (SELECT d.*, whole, rest, ('0x' || substr(md5('1:' || whole || ':' || doc_id), 1, 15))::BIGINT AS h FROM docs d JOIN leaf USING (domain, language, origin)),
placed AS (SELECT *, coalesce(sum(tokens) OVER (PARTITION BY domain, language, origin ORDER BY h, doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM ordered)
SELECT doc_id, domain, language, origin, epoch, tokens, CAST(CASE WHEN epoch < whole THEN tokens ELSE least(tokens, rest - before) END AS BIGINT) AS take
FROM (SELECT *, unnest(range(0, whole + 1)) AS epoch FROM placed) WHERE epoch < whole OR before < rest"""
