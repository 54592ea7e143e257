"""Whole jobs where a part used to be left out, against brute force."""

import random

import pytest

from tripleschema.llm import html_layout, nearcopies, secrets


def words(rng, n):
    return ["".join(rng.choice("abcdefghij") for _ in range(rng.randrange(3, 9))) for _ in range(n)]


def grams(text):
    w = (text or "").lower().split()
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


@pytest.mark.parametrize(("small", "chunk"), [(32, 512), (3, 7), (2, 4)])
def test_near_copies_equal_brute_force(spark, small, chunk):
    rng = random.Random(8)
    line = words(rng, 12)
    texts = [None, "", "a b", "A  b", "a b c"]
    for n in (8, 25, 70, 150):
        for _ in range(3):
            base = words(rng, n)
            for edits in (0, 1, 1, 2, 3, 5, 8):
                t = list(base)
                for _ in range(edits):
                    t[rng.randrange(len(t))] = words(rng, 1)[0]
                texts.append(" ".join(t + (line if rng.random() < 0.3 else [])))
    up = list(range(len(texts)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    sets = [grams(t) for t in texts]
    for i in range(len(texts)):
        for j in range(i):
            if 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                up[max(a, b)] = min(a, b)
    docs = spark.createDataFrame([(t, i) for i, t in enumerate(texts)], "text string, doc_id long")
    kept = nearcopies.representatives(docs, small=small, chunk=chunk)
    assert kept.columns == ["text", "doc_id"]
    assert sorted(r.doc_id for r in kept.collect()) == [i for i in range(len(texts)) if root(i) == i]
    assert nearcopies.representatives(docs.limit(0)).count() == 0


def test_pipeline_stage_drops_near_copies(spark):
    import corpus_pipeline

    text = words(random.Random(1), 70)
    rows = [(1, " ".join(text)), (2, " ".join([*text[:30], "changed", *text[31:]])), (3, " ".join(words(random.Random(2), 70)))]
    kept = corpus_pipeline.near_dedup(spark, spark.createDataFrame(rows, "doc_id long, text string"), "")
    assert sorted(r.doc_id for r in kept.collect()) == [1, 3]


def test_secrets_of_two_owners_are_reported_and_masked(spark):
    key, wide = "ghp_" + "aB3" * 13, "sk_live_" + "cD4" * 7
    rows = [(1, f"x {key}", "o1"), (2, f"y {key}", "o2"), *((10 + k, f"z {wide}", f"o{k}") for k in range(3))]
    table = spark.createDataFrame(rows, "doc_id long, text string, source string")
    assert {r.doc_id: [s.verdict for s in r.spans] for r in secrets.scan(table).collect()} == {1: ["shared"], 2: ["shared"], 10: [], 11: [], 12: []}
    masked = {r.doc_id: r.text for r in secrets.redacted(table).collect()}
    assert masked == {1: "x [secret]", 2: "y [secret]"} | {10 + k: f"z {wide}" for k in range(3)}


@pytest.mark.parametrize(
    ("page", "text"),
    [
        ("<table><tbody><form><tr><td>x<td>y</tr></form></tbody></table>z", "x  y\n\nz"),
        ("<table><tbody><div>x</div><tr><td>y</table>", "x\ny"),
        ("a <math><mi>x</mi><mo>=</mo><mn>1</mn><annotation>tex</annotation></math> b", "a x=1 b"),
        ("a <svg><title>t</title><defs><text>no</text></defs><circle r=1 /><g><text>one</text></g></svg> b", "a one b"),
        ("a <select><option>x<option selected>y</select> b", "a y b"),
        ("a <select><option disabled>x<optgroup label=g><option>y</select>", "a y"),
        ("<select multiple><option>x<option>y</select>", "x\ny"),
    ],
)
def test_html_keeps_all_visible_text(page, text):
    assert html_layout.render(page) == text


def test_pipeline_stage_links_as_op7_does(spark):
    """Texts whose fingerprints are three bits apart go although they share under 0.8 of their five-word shingles."""
    import corpus_pipeline
    from tripleschema.llm import simhash

    rng = random.Random(3)
    base = words(rng, 400)
    for _ in range(4000):
        text = list(base)
        for i in range(25, 400, 30):
            text[i] = words(rng, 1)[0]
        a, b = " ".join(base), " ".join(text)
        apart = (simhash.fingerprint(a) ^ simhash.fingerprint(b)).bit_count()
        if apart <= simhash.RADIUS and not 5 * len(grams(a) & grams(b)) >= 4 * len(grams(a) | grams(b)):
            break
    else:
        pytest.fail("no such pair")
    rows = [(7, b), (3, a), (5, " ".join(words(rng, 70)))]
    kept = corpus_pipeline.near_dedup(spark, spark.createDataFrame(rows, "doc_id long, text string"), "")
    assert sorted(r.doc_id for r in kept.collect()) == [3, 5]


def test_what_earlier_tasks_used_goes_before_something_new():
    from functools import lru_cache

    from tripleschema.llm import common

    one, other = lru_cache(lambda: object()), lru_cache(lambda: object())
    for cached in (one, other):
        common._begin()
        common.used(cached)
        cached()
    assert one.cache_info().currsize == 0 and other.cache_info().currsize == 1
    common.used(one)
    one()
    assert other.cache_info().currsize == 1  # the same task uses both


def test_a_task_that_does_not_use_what_earlier_ones_did_drops_it():
    from functools import lru_cache

    from tripleschema.llm import common

    held = lru_cache(lambda: object())
    for _ in range(2):
        common.used(held)
        held()
        common._begin()
        assert held.cache_info().currsize == 1
    common._begin()
    assert held.cache_info().currsize == 0


def test_workers_get_rows_in_batches_of_few_bytes(spark):
    import pyarrow as pa

    from tripleschema.llm import common

    def sizes(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.num_rows]), pa.array([batch.nbytes])], ["n", "size"])

    common.prepare(spark)
    rows = spark.range(0, 4000, 1, 1).selectExpr("id", "repeat('abcdefgh ', 500) AS text").mapInArrow(sizes, "n long, size long").collect()
    assert sum(r.n for r in rows) == 4000
    assert max(r.size for r in rows) < 1.1 * common.BATCH_BYTES


def test_numbering_rows_starts_no_workers_of_its_own(spark, tmp_path, monkeypatch):
    from tripleschema.llm import common

    spark.range(0, 90, 1, 3).write.parquet(str(tmp_path / "t"))
    docs = spark.read.parquet(str(tmp_path / "t"))
    with monkeypatch.context() as m:
        m.setattr(type(spark.sparkContext), "parallelize", None)
        rows = common.numbered(docs.select("id"), docs, "numbered")
    assert sorted(r.id for r in rows.collect()) == list(range(90))
    assert rows.select("rid").distinct().count() == 90


def test_scored_texts_do_not_come_back_from_the_workers():
    import numpy as np
    import pyarrow as pa

    from tripleschema.llm import quality

    class Value:
        value = quality.fit([(1, 0, quality.grams("a bad text").astype("<u4").tobytes(), [0.0] * 6), (0, 1, b"", [1.0] * 6)])

    batch = pa.RecordBatch.from_arrays([pa.array([4, 5]), pa.array(["h", "h"]), pa.array(["p", "p"]), pa.array(["a bad text", None])], ["c0", "host", "path", "text"])
    (out,) = quality._score_batches(Value, 3)(iter([batch]))
    assert out.schema.names == ["c0", "host", "path", "__low", "__toxic"]
    assert np.allclose(out.column(3).to_numpy(), [Value.value.evidence(t)[0] for t in ("a bad text", "")])


def test_decontamination_holds_little_at_a_time():
    """A task's memory does not grow with what Spark hands over at once, and its finds are those of each text by itself."""
    import tracemalloc

    import pyarrow as pa

    from tripleschema.llm import decontam

    class Value:
        value = ((5, "the quick brown fox jumps over the lazy dog and runs away"),)

    rng = random.Random(4)
    text = [" ".join(words(rng, 300)) for _ in range(1900)]
    text[7::40] = [f"{t} {Value.value[0][1]}" for t in text[7::40]]
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(text))), pa.array(text)], ["doc_id", "text"])
    assert batch.nbytes > 3 << 20
    run = decontam._search(Value, decontam.Q, decontam.RATE, 1, False)
    next(run(iter([batch[:1]])))  # what is made once
    tracemalloc.start()
    kept = [i for part in run(iter([batch])) for i in part.column(0).to_pylist()]
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert kept == [i for i in range(len(text)) if i % 40 != 7]
    assert most < 60 << 20


def test_passages_leave_only_what_their_result_reads(spark, monkeypatch):
    """Tables of links and chains go when the next one is written; the result is read from the last."""
    from tripleschema.llm import common, passages

    monkeypatch.setattr(common, "_made", [])
    rng = random.Random(6)
    same = words(rng, 70)
    table = spark.createDataFrame([(i, " ".join(words(rng, 9) + same + words(rng, 9))) for i in range(4)], "doc_id long, text string")
    found = passages.shared_passages(table, few=2)
    there = lambda path: (p := spark._jvm.org.apache.hadoop.fs.Path(path)).getFileSystem(spark._jsc.hadoopConfiguration()).exists(p)
    left = sorted(p.rsplit("/", 1)[1].rsplit("-", 5)[0] for p in common._made if there(p))
    assert len(common._made) > 5 and left == ["aligned", "numbered"]
    assert {i for r in found.collect() for i in (r.doc_id, r.partner_id)} == {0, 1, 2, 3}
