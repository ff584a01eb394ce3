"""The pipeline's stages over the small tables, each judged on its own input."""

import random

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from relgraph.llm.common import staged, table
from tests.llm.test_operators import brute_components, check_places


@pytest.fixture(scope="module")
def steps(spark, small):
    docs, out = table(spark, small, "documents"), []
    for name, stage in corpus_pipeline.STAGES:
        after = staged(stage(spark, docs, small), "test")
        out.append((name, docs, after))
        docs = after
    return out


def test_columns_and_order(steps, spark, small):
    columns = table(spark, small, "documents").columns
    assert len(steps) == 5 and all(after.columns == columns for _, _, after in steps[:-1])
    assert all(after.count() > 0 for _, _, after in steps)
    assert steps[0][2].exceptAll(steps[0][1]).count() == 0


def test_line_dedup_keeps_documents(steps):
    _, before, after = steps[1]
    assert after.count() == before.count()
    assert after.where(F.col("n_chars") != F.length("text")).count() == 0


def test_mix_keeps_within_budget(steps):
    _, before, after = steps[3]
    size = lambda df: df.agg(F.sum(F.length("text") - F.length(F.translate("text", " \n", "")) + 1)).first()[0]
    whole = {r.doc_id: r.text for r in before.collect()}
    cut = [r for r in after.collect() if r.text != whole[r.doc_id]]
    assert all(whole[r.doc_id].startswith(r.text) and r.n_chars == len(r.text) for r in cut)
    assert size(after) <= size(before) * corpus_pipeline.MIX_SHARE


def test_places(steps):
    check_places(steps[4][2].collect())


def five(text):
    words = (text or "").translate({c: c + 32 for c in range(65, 91)}).split()
    return {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def test_near_dedup_links_from_similarity_08(spark, small):
    """Pairs of prose just above and just below 0.8; the copies differ in a run of words."""
    base = table(spark, small, "documents")
    docs, apart = [], 0
    for i in range(60):
        r = random.Random(i)
        words = [f"w{r.randrange(5000)}" for _ in range(200)]
        cut = 13 if i % 2 == 0 else 21
        other = words[:150] + [f"v{k}" for k in range(cut)] + words[150 + cut :]
        a, b = five(" ".join(words)), five(" ".join(other))
        close = len(a & b) / len(a | b) >= 0.8
        assert close == (i % 2 == 0)
        apart += 1 if close else 2
        docs += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(other))]
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    for c in base.columns:
        if c not in ("doc_id", "text"):
            frame = frame.withColumn(c, F.lit(None).cast(base.schema[c].dataType))
    found = corpus_pipeline.near_dedup(spark, frame.select(*base.columns), small).collect()
    assert len(found) == apart
    assert {r.doc_id for r in found} == {i for i in range(120) if i % 2 == 0 or i % 4 == 3}


def test_near_dedup_against_all_pairs(steps):
    """The stage over its own input of the run, by comparing every two texts."""
    _, before, after = steps[2]
    sets = {r.doc_id: five(r.text) for r in before.collect()}
    groups = brute_components(sorted(sets), lambda a, b: len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]))
    assert {r.doc_id for r in after.collect()} == set(groups.values()) and after.count() == len(set(groups.values()))


def test_near_dedup_with_null_and_repeated_ids(spark, small):
    """Only rows whose text has a near copy go; the same rows stay however the input is cut."""
    text = lambda k: " ".join(f"t{k}x{i}" for i in range(40))
    rows = [(1, text(1)), (1, text(2)), (1, text(2)), (2, text(1)), (3, text(3)), (None, text(3)), (None, text(4)), (None, text(4)), (None, text(5)), (None, None), (4, "")]
    base = table(spark, small, "documents")
    frame = spark.createDataFrame([(*r, "en", "a", 1) for r in rows], "doc_id long, text string, lang string, source string, n_chars long")
    expected = sorted([(1, text(1)), (1, text(2)), (3, text(3)), (-1, text(4)), (-1, text(5)), (4, "")])
    for parts in (1, 5):
        found = corpus_pipeline.near_dedup(spark, frame.select(*base.columns).repartition(parts), small).collect()
        assert sorted((-1 if r.doc_id is None else r.doc_id, r.text or "") for r in found) == expected


ODD = ["_doc", "_gone", "gone", "_tokens", "_partial", "_row", "_take", "row", "id", "score"]


@pytest.fixture(scope="module")
def odd(spark, small):
    """Null and repeated ids, null, empty and long texts, repeated rows, columns named like the operators' own."""
    text = lambda k, n=60: " ".join(f"wort{k} und{i} text" for i in range(n))
    rows = [(1, text(1)), (1, text(2)), (2, text(3)), (2, text(3)), (None, text(4)), (None, text(5)), (None, None), (3, None), (4, ""), (5, text(6, 60_000))]
    rows += [(10 + i, f"{text(20 + i)}\nThis very line stands in several documents.\n{text(40 + i)}") for i in range(4)]
    whole = [(*r, "en", None if i % 3 else "src1", 7, *range(len(ODD))) for i, r in enumerate(rows)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` long" for c in ODD)
    return spark.createDataFrame(whole, schema).repartition(3).cache()


def test_stages_take_odd_tables(spark, small, odd):
    key = lambda r: (r.doc_id is None, r.doc_id or 0, r.text or "")
    before = sorted(odd.collect(), key=key)
    names = dict(corpus_pipeline.STAGES)
    kept = names["quality classifier"](spark, odd, small)
    assert kept.columns == odd.columns and kept.exceptAll(odd).count() == 0
    lines = names["line dedup"](spark, odd, small)
    assert lines.columns == odd.columns and lines.count() == len(before)
    for a, b in zip(before, sorted(lines.collect(), key=key), strict=True):
        assert a[5:] == b[5:] and (a.text is None) == (b.text is None)
        assert (a.text != b.text) == (a.doc_id in (10, 11, 12)), (a.doc_id, b.text)
    near = sorted(names["SimHash near-dedup"](spark, odd, small).collect(), key=key)
    assert [(r.doc_id, r.text or "") for r in near] == sorted({(r.doc_id, r.text or "") for r in before if r.text or r.doc_id == 3}, key=lambda x: (x[0] is None, x[0] or 0, x[1]))
    assert all(r in before for r in near)
    mixed = names["mixing to target weights"](spark, odd, small)
    assert mixed.columns == odd.columns
    size = lambda t: 1 + (t or "").count(" ") + (t or "").count("\n")
    found = mixed.collect()
    assert sum(size(r.text) for r in found) <= int(sum(size(r.text) for r in before) * corpus_pipeline.MIX_SHARE)
    assert all(any(b[5:] == r[5:] and (b.text or "").startswith(r.text or "") for b in before) for r in found)
    packed = names["best-fit packing"](spark, odd, small).collect()
    check_places(packed)
    assert sum(r.piece == 0 for r in packed) == len(before)


def test_stages_take_empty_tables(spark, small, odd):
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, odd.limit(0), small).count() == 0, name
