"""Every operator on nulls, empty and very long texts, ties, repeated rows, empty tables and clashing column names."""

import collections
import hashlib
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

P = pytest.importorskip("public_tokenizers")

from tests.llm.test_operators import TEXTS, prose, words  # noqa: E402

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(None, "a b c d e", None, None, None), (None, "a b c d e", None, None, None), (1, None, "en", "s", 0), (1, None, "en", "s", 0), (2, "", "en", "s", 0), (3, " \n\t", "en", "s", 3), (4, "漢" * 40_000, "zh", "s", 40_000), (5, "x" * 90_000, "en", "t", 90_000), (6, "one", "en", "t", 3)]


@pytest.fixture(scope="module")
def odd(spark):
    clashing = ("block", "class", "size", "target", "source_size", "repeats", "taken", "extra", "part", "row", "plan", "mix", "order", "score", "label", "counts", "kind", "ids", "n_tokens", "held_out", "elements", "word", "n", "_text")
    df = spark.createDataFrame(ODD, DOCS).repartition(3)
    return df.withColumns({c: F.lit(7) for c in clashing}).cache()


def test_token_counts_and_bpe(spark, odd):
    from tokenizers import Tokenizer

    from devicelens.llm.byte_bpe import encode_ids, round_trip
    from devicelens.llm.token_counts import token_counts

    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    key = lambda r: (r[0] is None, r)
    library = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    want = sorted(((i, len((t or "").encode()), n := len(library.encode(t or "", add_special_tokens=False)), n > 2048) for i, t, *_ in ODD), key=key)
    assert sorted((tuple(r) for r in token_counts(odd, P.path("word_bpe_49k.json")).collect()), key=key) == want
    library = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    ids = {t: library.encode(t or "", add_special_tokens=False).ids for _, t, *_ in ODD}
    want = sorted(((i, len(ids[t]), sha(",".join(map(str, ids[t]))), sha(t or "")) for i, t, *_ in ODD), key=key)
    assert sorted((tuple(r) for r in round_trip(odd, P.path("byte_bpe_50k.json")).collect()), key=key) == want
    for operator, path in ((token_counts, "word_bpe_49k.json"), (round_trip, "byte_bpe_50k.json"), (encode_ids, "byte_bpe_50k.json")):
        assert operator(odd.filter("false"), P.path(path)).count() == 0


def test_frequent_words_are_those_that_fit(spark):
    from devicelens.llm.byte_bpe import frequent_words

    docs = spark.createDataFrame([(1, "a a a b b b c c d d e"), (2, "a b c"), (3, None), (4, "")], "doc_id long, text string")
    assert frequent_words(docs, 2) == ["a", "b"] and frequent_words(docs, 3) == ["a", "b", "c"] and frequent_words(docs, 9) == ["a", "b", "c", "d"]
    assert frequent_words(docs, 1) == []  # a and b occur as often, so both or neither


def test_repeats_jaccard_and_language_model(spark, odd):
    from devicelens.llm.jaccard import near_duplicates
    from devicelens.llm.lm import language_model_scores
    from devicelens.llm.repeats import remove_repeats

    got = collections.Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans) for r in remove_repeats(odd, wanted=["n_bytes", "n_removed", "n_spans"]).collect())
    long = {4: (120_000, 1), 5: (90_000, 1)}  # runs of one character repeat in themselves
    assert got == collections.Counter((i, len((t or "").encode()), *long.get(i, (0, 0))) for i, t, *_ in ODD)
    got = collections.Counter((r.doc_id, r.n_shingles, r.component_id) for r in near_duplicates(odd).collect())
    assert got == collections.Counter((i, {5: 2, 1: 1, 0: 0}[len(words(t))], i) for i, t, *_ in ODD)
    got = language_model_scores(odd).collect()
    assert collections.Counter((r.doc_id, r.held_out, r.n_tokens) for r in got) == collections.Counter((i, i is not None and zlib.crc32(str(i).encode()) % 10 == 0, len(words(t)) + 1) for i, t, *_ in ODD)
    assert all(np.isfinite(r.score) and r.score < 0 for r in got)
    empty = odd.filter("false")
    assert remove_repeats(empty).count() == near_duplicates(empty).count() == language_model_scores(empty).count() == 0


def test_mixing(spark, odd):
    from devicelens.llm.mixing import mix

    rows = mix(odd).collect()
    assert len(rows) == len(ODD) and {"size", "source_size", "target", "taken", "repeats", "plan", "block"} <= set(mix(odd).columns)
    size = lambda t: len(words(t))
    assert collections.Counter((r.doc_id, r["size"]) for r in rows) == collections.Counter((i, size(t)) for i, t, *_ in ODD)
    assert all(r.taken <= 3 * r["size"] and r.repeats == 7 for r in rows)
    assert {r.source: r.source_size for r in rows} == {None: 10, "s": 1, "t": 2}


def test_mixing_reaches_the_best_fit():
    import random

    from devicelens.llm.mixing import fill

    rng = random.Random(3)
    for _ in range(300):
        lengths = {n: rng.randint(1, 5) for n in rng.sample(range(1, 30), rng.randint(1, 6))}
        budget, reach = rng.randint(1, 140), {0}
        for n, c in lengths.items():
            reach = {x + n * k for x in reach for k in range(c + 1)}
        got = fill(budget, lengths)
        assert all(0 < c <= lengths[n] for n, c in got.items()) and sum(n * c for n, c in got.items()) == max(x for x in reach if x <= budget)


def test_warc(spark, tmp_path):
    from devicelens.llm.warc import archived

    html = "<p>" + "y" * 200
    rows = [(i, "u", html) for i in range(40, 0, -1)] + [(7, "u", html), (None, None, None), (50, None, "z" * 3_000_000), (51, "", "")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({c: F.lit("x") for c in ("digest", "payload", "salt", "refers_to", "last")}).repartition(3)
    got = sorted((tuple(r) for r in archived(pages, str(tmp_path / "a")).collect()), key=lambda r: (r[0] is None, r))
    sha = lambda h: hashlib.sha256((h or "").encode()).hexdigest()
    want = [(i, len(h or ""), sha(h), *(("revisit", 1) if h == html and i > 1 else ("response", None))) for i, _, h in rows]
    assert got == sorted(want, key=lambda r: (r[0] is None, r))
    assert archived(pages.filter("false"), str(tmp_path / "b")).count() == 0


def test_quality_model_is_made_by_a_task(spark, monkeypatch):
    from devicelens.llm import quality

    texts = [f"{'plain' if i % 2 else 'spam'} words {i} of a text {i * i}" for i in range(1, 41)]
    docs = spark.createDataFrame(list(enumerate(texts, 1)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(1, 41)], "doc_id long, quality int")
    rows = sorted((r.label, np.array(quality.trigram_counts(r.text.encode()), np.uint16).tobytes()) for r in quality.labelled_sample(docs, labels).collect())
    want = quality.VotingModel(np.array([np.frombuffer(x, np.uint16) for _, x in rows]), np.array([x for x, _ in rows], float))

    def refused(*_):
        raise AssertionError("the sample came to the driver")

    monkeypatch.setattr(quality, "leading_axes", refused)
    got = quality.fit(docs, labels)
    assert len(rows) > 20 and got.labels.tolist() == want.labels.tolist() and got.share == want.share
    assert np.array_equal(got.weight, want.weight) and np.allclose(got.vectors @ got.vectors.T, want.vectors @ want.vectors.T, atol=1e-5)


def test_quality_votes_by_brute_force(spark, odd):
    from devicelens.llm.quality import BINS, NEIGHBOURS, POWER, PRIOR, fit, quality_scores, trigram_counts

    docs = spark.createDataFrame([(i, t if i % 2 else (t or "").upper()) for i, t in TEXTS] + [(100 + i, prose(700 + i, 40)) for i in range(60)] + [(200 + i, "!!! " * (5 + i % 3)) for i in range(40)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 200)) for i in [*range(1, 18), *range(100, 160), *range(200, 240)]] + [(100, 0), (9_999, 1), (101, None)], "doc_id long, quality int")
    model = fit(docs, labels)
    taught = {i for i in [*range(1, 18), *range(100, 160), *range(200, 240)] if zlib.crc32(str(i).encode()) % 4 != 2}
    assert len(model.labels) == len(taught) and model.labels.sum() == sum(i < 200 for i in taught if i != 100)
    scores = {r.doc_id: r for r in quality_scores(docs, model).collect()}
    for i, t in {r.doc_id: r.text for r in docs.collect()}.items():
        counts = trigram_counts((t or "").encode())
        x = np.log1p(counts.astype(np.float32))
        x = (x / max(np.linalg.norm(x), 1e-12) * model.weight - model.centre) @ model.axes
        cosine = model.vectors @ (x / max(np.linalg.norm(x), 1e-12))
        near = sorted(range(len(cosine)), key=lambda k: (-cosine[k], k))[:NEIGHBOURS]
        votes = [max(float(cosine[k]), 0) ** POWER for k in near]
        want = (sum(v * model.labels[k] for v, k in zip(votes, near)) + PRIOR * model.share) / (sum(votes) + PRIOR) if counts.any() else model.share
        if i != 4:  # stands twice, with two texts of other letters
            assert scores[i].score == pytest.approx(want, abs=2e-3) and scores[i].predicted == int(scores[i].score >= 0.7)
    assert counts.shape == (BINS,)
    got = quality_scores(odd, model).collect()
    assert len(got) == len(ODD) and all(0 <= r.score <= 1 for r in got)
    nothing = fit(docs, labels.filter("false"))
    assert {r.score for r in quality_scores(odd, nothing).collect()} == {0.5}
    assert quality_scores(odd.filter("false"), model).count() == 0


def test_of_equal_neighbours_the_first_vote():
    from devicelens.llm.quality import nearest_columns

    cosine = np.array([[0.5, 0.9, 0.5, 0.5, 0.1], [0.2, 0.2, 0.2, 0.2, 0.2]], np.float32)
    assert nearest_columns(cosine, 3).tolist() == [[0, 1, 2], [0, 1, 2]]


def test_pipeline_on_odd_and_no_rows(spark, tmp_path):
    import corpus_pipeline as pipeline

    docs = spark.createDataFrame([*ODD, (8, prose(900, 4_000), "en", "s", 1), (9, prose(901, 80), "en", None, 1)], DOCS)
    labels = [(i, 1) for i in range(10)]
    for name, rows in (("some", docs), ("none", docs.filter("false"))):
        folder = tmp_path / name
        rows.write.parquet(str(folder / "documents.parquet"))
        spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(str(folder / "labels.parquet"))
        out = pipeline.run(spark, str(folder))
        assert out.columns == ["doc_id", "source", "ids", "n_tokens"]
        found = out.collect()
        assert all(len(r.ids) == r.n_tokens > 0 for r in found)
        assert bool(found) == (name == "some")
        if found:  # the words of 8 alone are more than its source's share of all
            assert {9, None} <= {r.doc_id for r in found} and 8 not in {r.doc_id for r in found}
    stages = [n for n, _ in pipeline.STAGES]
    assert stages == ["quality", "dedup", "repeats", "mix", "encode"]
