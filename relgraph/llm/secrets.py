"""Secret scans with a randomness test battery, in DataFrame functions only.

Base patterns find assignments, access ids and hexadecimal runs. The battery looks at every maximal run of
20 or more encoding characters. An equals sign can only end a run, as padding, so names do not join their values; a
slash beside a lower-case word or hexadecimal digits parts runs, as in paths. An encoding is inferred from the
run's characters, and its symbols are tested for uniform use of the alphabet (chi-squared), for the number of runs of upper and lower halves, and
for serial correlation. A run that fails these at 0.001 is no random string. For the others, the chance that
text of this length would use the alphabet so evenly is a p-value against "this is text", so a short run
must be more even than a long one to count. Discoveries are controlled at a false rate of 0.01 within
classes of length, by the step-up rule on a histogram of p-values, whose size is fixed.

Positions are code points, ends exclusive, and cost the same for each match however many a text has (running sums of
64, 64 by 64, and so on). Null or empty texts have no spans. Very long texts are scanned whole, a row at a time. Rows that
repeat a doc_id are scanned each; spans that start together are ordered by kind. Other columns are left out, so names
cannot clash. Empty tables: no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.llm.common import staged

KINDS = ("assign", "access", "hex", "random")
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
# A whole run is at least as long as asked exactly if it matches with that length, as runs are maximal.
ACCESS = r"AKIA[A-Z0-9]{12,}"
HEX = r"(?<![0-9a-f])[0-9a-f]{32,}+"
RUN = r"(?<![A-Za-z0-9+_-])(?:[A-Za-z0-9+_-]|(?<![a-z]{3}|[0-9a-fA-F]{20})/(?![a-z]{3}|[0-9a-fA-F]{20})){20,}+={0,2}"
#: Encodings, the first that fits: pattern, alphabet, sum of squared letter shares of text in it.
ENCODINGS = (
    (r"^[0-9a-f]+$", "0123456789abcdef", 0.13),
    (r"^[0-9A-F]+$", "0123456789ABCDEF", 0.13),
    (r"^[a-z]+$", "abcdefghijklmnopqrstuvwxyz", 0.0655),
    (r"^[A-Z]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", 0.0655),
    (r"^[A-Z2-7]+=*$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 0.0655),
    (r"^[A-Za-z0-9]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789", 0.0655),
    (r"", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/-_", 0.0655),
)
WRONG, FALSE_RATE, CLASSES, STEPS = 0.001, 0.01, 8, 300


#: Values that one running sum goes over.
BLOCK_BITS = 6


def bound(value: Column, f) -> Column:
    """f of a value that is worked out once, however often f names it."""
    return F.element_at(F.transform(F.array(value), f), 1)


def running(sizes: Column, depth: int = 3) -> Column:
    """Sums of all values before each, of an array that is not empty."""
    total = lambda part: F.aggregate(part, F.lit(0), lambda s, x: s + x)
    if not depth:
        return F.transform(sizes, lambda x, i: total(F.slice(sizes, F.lit(1), i)))
    blocks = F.sequence(F.lit(0), F.shiftright(F.size(sizes) - 1, BLOCK_BITS))
    sums = F.transform(blocks, lambda k: total(F.slice(sizes, F.shiftleft(k, BLOCK_BITS) + 1, F.lit(1 << BLOCK_BITS))))

    def within(before):
        first = lambda i: F.shiftleft(F.shiftright(i, BLOCK_BITS), BLOCK_BITS)
        return F.transform(sizes, lambda x, i: F.get(before, F.shiftright(i, BLOCK_BITS)) + total(F.slice(sizes, first(i) + 1, i - first(i))))

    return bound(bound(sums, lambda s: running(s, depth - 1)), within)


def spans(matches: Column, pieces: Column) -> Column:
    """Start and end of each match, from the matches and the pieces between them."""

    def placed(both):
        steps = F.transform(both["m"], lambda x, i: F.length(F.get(both["p"], i)) + F.length(x))
        at = lambda before: F.transform(
            both["m"],
            lambda x, i: F.struct(
                (F.get(before, i) + F.length(F.get(both["p"], i))).alias("start"),
                (F.get(before, i) + F.length(F.get(both["p"], i)) + F.length(x)).alias("end"),
            ),
        )
        return bound(bound(steps, lambda s: running(s)), at)

    return bound(F.struct(matches.alias("m"), pieces.alias("p")), placed)


def tail(z: Column) -> Column:
    """Chance that a standard normal value is below z."""
    far = F.exp(-z * z / 2) / (-z * F.lit(2.5066282746310002))
    return F.when(z < -3, far).otherwise(1 / (1 + F.exp(-(0.07056 * z * z * z + 1.5976 * z))))


def battery(x: Column) -> Column:
    """Struct of the tests of one run of characters: n, chi2, df, wrong (p against randomness), text (p against text)."""
    # Each step is a struct, so that it is worked out once.
    pick = lambda k: _first([(p, F.lit(e[k])) for p, e in ((e[0], e) for e in ENCODINGS)], x)
    start = F.struct(
        F.split(F.rtrim(x, F.lit("=")), "").alias("c"), pick(1).alias("alphabet"), pick(2).alias("even")
    )

    def counts(s):
        at = F.transform(s["c"], lambda c: F.instr(s["alphabet"], c) - 1)
        k = F.length(s["alphabet"]).cast("double")
        each = F.transform(F.array_distinct(s["c"]), lambda d: F.size(F.filter(s["c"], lambda c: c == d)).cast("double"))
        return F.struct(
            at.alias("at"), k.alias("k"), s["even"].alias("even"), F.size(s["c"]).cast("double").alias("n"),
            F.aggregate(each, F.lit(0.0), lambda a, v: a + v * v).alias("squares"),
            F.aggregate(at, F.lit(0.0), lambda a, v: a + v).alias("total"),
        )

    def sums(s):
        mean = s["total"] / s["n"]
        pairs = F.arrays_zip(F.slice(s["at"], F.lit(1), F.size(s["at"]) - 1).alias("a"), F.slice(s["at"], F.lit(2), F.size(s["at"]) - 1).alias("b"))
        half = s["k"] / 2
        return F.struct(
            s["n"].alias("n"), s["k"].alias("k"), s["even"].alias("even"), (s["k"] / s["n"] * s["squares"] - s["n"]).alias("chi2"),
            F.size(F.filter(s["at"], lambda v: v >= half)).cast("double").alias("high"),
            F.size(F.filter(pairs, lambda p: (p["a"] >= half) != (p["b"] >= half))).cast("double").alias("changes"),
            F.aggregate(pairs, F.lit(0.0), lambda a, p: a + (p["a"] - mean) * (p["b"] - mean)).alias("cross"),
            F.aggregate(s["at"], F.lit(0.0), lambda a, v: a + (v - mean) * (v - mean)).alias("spread"),
        )

    def tests(s):
        n, df = s["n"], s["k"] - 1
        # Wilson and Hilferty's cube root for chi-squared; the share of fuller cells than uniform use would give.
        z1 = (F.cbrt(s["chi2"] / df) - (1 - 2 / (9 * df))) / F.sqrt(2 / (9 * df))
        ties = 2 * s["high"] * (n - s["high"]) / n
        z2 = F.when(ties <= 1, F.lit(-9.0)).otherwise(-F.abs(s["changes"] - ties) / F.sqrt(ties * (ties - 1) / (n - 1)))
        z3 = F.when(s["spread"] <= 0, F.lit(-9.0)).otherwise(-F.abs(s["cross"] / s["spread"] + 1 / n) * F.sqrt(n))
        extra = s["k"] * s["even"] - 1
        zt = (s["chi2"] - df - n * extra) / F.sqrt(2 * df + 4 * n * extra)
        return F.struct(
            n.alias("n"), s["chi2"].alias("chi2"), df.alias("df"),
            F.least(F.lit(1.0), 3 * F.least(tail(-z1), 2 * tail(z2), 2 * tail(z3))).alias("wrong"),
            tail(zt).alias("text"),
        )

    return bound(bound(bound(start, counts), sums), tests)


def _first(cases: list[tuple[str, Column]], x: Column) -> Column:
    out = cases[-1][1]
    for pattern, value in reversed(cases[:-1]):
        out = F.when(x.rlike(pattern), value).otherwise(out)
    return out


def of_kind(rank: int):
    return lambda s: F.struct(s["start"].alias("start"), F.lit(rank).alias("kind"), s["end"].alias("end"))


def scan(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, base, runs): base spans in order, and the tested runs, of every document."""
    found = df.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("t"))
    empty = F.array().cast("array<string>")
    columns = ["doc_id"]
    for rank, (kind, pattern) in enumerate(zip(KINDS, (ASSIGN, ACCESS, HEX, RUN), strict=True)):
        all_ = F.regexp_extract_all("t", F.lit(pattern), F.lit(0))
        if kind == "access":
            all_ = F.when(F.contains(F.col("t"), F.lit("AKIA")), all_).otherwise(empty)
        columns.append(bound(all_, _found(rank, pattern)).alias(f"{kind}_span"))
    found = found.select(*columns)
    base = F.array_sort(F.concat("assign_span", "access_span", "hex_span"))
    return found.select("doc_id", base.alias("base"), F.col("random_span").alias("runs"))


def _found(rank: int, pattern: str):
    return lambda m: F.when(F.size(m) > 0, _kind(rank, m, pattern)).otherwise(F.array())


def _kind(rank: int, matches: Column, pattern: str) -> Column:
    """Spans of the matches of a kind, with the tests of random runs."""
    at, named = spans(matches, F.split(F.col("t"), pattern, -1)), of_kind(rank)
    if KINDS[rank] == "assign":
        value = F.regexp_extract_all("t", F.lit(pattern), F.lit(1))
        kept = lambda v: F.filter(F.transform(at, lambda s, i: F.when(F.length(F.get(v, i)) >= 8, named(s))), lambda s: s.isNotNull())
        return bound(value, kept)
    if KINDS[rank] == "random":
        return F.transform(at, lambda s, i: F.struct(s["start"].alias("start"), s["end"].alias("end"), battery(F.get(matches, i)).alias("test")))
    return F.transform(at, named)


def discovered(runs: DataFrame) -> DataFrame:
    """(class, least): for each class of length the least step of -10 log10 p that the step-up rule accepts."""
    seen = runs.select(F.explode("runs").alias("r")).where(F.col("r.test.wrong") >= WRONG)
    seen = seen.select(size_class(F.col("r.test.n")).alias("class"), step(F.col("r.test.text")).alias("step"))
    counts = seen.groupBy("class", "step").agg(F.count("*").alias("n"))  # at most CLASSES x (STEPS + 1) rows
    up = Window.partitionBy("class").orderBy(F.desc("step"))
    counts = counts.select("class", "step", F.sum("n").over(up).alias("beyond"), F.sum("n").over(Window.partitionBy("class")).alias("all"))
    fine = F.pow(F.lit(10.0), -F.col("step") / 10) * F.col("all") <= F.lit(FALSE_RATE) * F.col("beyond")
    return counts.where(fine).groupBy("class").agg(F.min("step").alias("least"))


def size_class(n: Column) -> Column:
    return F.least(F.lit(CLASSES - 1), F.floor(F.log2(n / 20) * 2)).cast("int")


def step(p: Column) -> Column:
    return F.least(F.lit(STEPS), F.floor(-10 * F.log10(F.greatest(p, F.lit(1e-300))))).cast("int")


def secrets(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, n_random, base_sha256, spans) of every document.

    A run that touches a base span is not added again.
    """
    found = staged(scan(df, key, text), "scan")
    least = discovered(found).agg(F.map_from_entries(F.collect_list(F.struct("class", "least"))).alias("least"))  # at most CLASSES entries
    found = found.crossJoin(F.broadcast(least))
    fresh = F.filter(
        "runs",
        lambda r: (r["test"]["wrong"] >= WRONG)
        & (step(r["test"]["text"]) >= F.coalesce(F.try_element_at("least", size_class(r["test"]["n"])), F.lit(STEPS + 1)))
        & ~F.exists("base", lambda b: (b["start"] < r["end"]) & (r["start"] < b["end"])),
    )
    fresh = F.transform(fresh, of_kind(3))
    names = F.array(*map(F.lit, KINDS))
    line = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("base", lambda b: b["kind"] == k)).cast("long")
    found = found.withColumn("fresh", fresh)
    return found.select(
        "doc_id", count(0).alias("n_assign"), count(1).alias("n_access"), count(2).alias("n_hex"), F.size("fresh").cast("long").alias("n_random"),
        F.sha2(line(F.col("base")).cast("binary"), 256).alias("base_sha256"), line(F.array_sort(F.concat("base", "fresh"))).alias("spans"),
    )
