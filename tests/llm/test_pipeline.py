"""The pipeline's stages on rows with repeats, null ids and ids that several texts have."""

import collections

import pytest

pytest.importorskip("public_tokenizers")

import corpus_pipeline as pipeline  # noqa: E402
from tests.llm.test_operators import brute_components, prose, words  # noqa: E402

A, B, C, D, E, G = (prose(20 + k, 150) for k in range(6))
ROWS = [
    (1, A, "en", "s"), (1, A, "en", "s"), (1, A, "en", "s"),  # a row that stands three times
    (2, A + " tail", "en", "s"), (3, B, "en", "s"), (3, C, "en", "s"), (4, C, "en", "t"),  # two texts under an id, one of them copied
    (5, D, "en", "s"), (6, D, "en", "s"), (6, E, "en", "t"), (6, E + " tail", "en", "t"),  # E and its near copy have an id that D's copy has too
    (None, G, "en", None), (None, G, "en", None), (None, G + " tail", "en", "t"), (None, B + " tail", "de", "t"),
    (7, None, "en", "s"), (7, None, "en", "s"), (8, "", None, "s"), (None, " \n", "en", "t"), (9, "one two", "en", "s"), (None, "one two", "en", "s"),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*r, len(r[1] or "")) for r in ROWS], SCHEMA).repartition(3).cache()


def counted(df):
    return collections.Counter(tuple(r) for r in df.select(*pipeline.COLUMNS).collect())


def groups():
    sets = []
    for _, text, *_ in ROWS:
        w = words(text)
        sets.append({tuple(w[k : k + 4]) for k in range(max(1, len(w) - 3))} if w else set())
    found = collections.defaultdict(list)
    for root, row in zip(brute_components(sets), ROWS):
        found[root].append((*row, len(row[1] or "")))
    return list(found.values())


def test_dedup_keeps_one_row_of_each_group(spark, docs):
    got = counted(pipeline.dedup(spark, docs, ""))
    assert got == counted(pipeline.dedup(spark, docs.repartition(2), ""))
    for rows in groups():
        stay = [r for r in set(rows) for _ in range(got[r])]
        if words(rows[0][1]):
            order = lambda r: (r[0] is None, r[0] or 0)
            assert len(stay) == 1 and order(stay[0]) == min(map(order, rows))
        else:  # linked with nothing
            assert len(stay) == ROWS.count(rows[0][:4])
    assert sum(got.values()) == sum(1 if words(rows[0][1]) else len(rows) for rows in groups())


def test_repeated_row_survives_dedup_and_repeats(spark, docs):
    left = counted(pipeline.repeats(spark, pipeline.dedup(spark, docs, ""), ""))
    assert left[(1, A, "en", "s", len(A))] == 1
    assert sum(r[1] == A for r in left) == 1 and all(words(r[1]) for r in left)


def test_mix_and_encode_count_every_row(spark, docs):
    from tokenizers import Tokenizer

    from devicelens.llm.mixing import mix
    from devicelens.llm.queries import tokenizer

    want = collections.Counter()
    for r in mix(docs).collect():
        if r.taken:
            want[tuple(r[c] for c in pipeline.COLUMNS)] += r.taken // r.size
    assert counted(pipeline.mixed(spark, docs, "")) == want
    library = Tokenizer.from_file(tokenizer("byte_bpe_50k.json"))
    ids = collections.Counter((i, source, tuple(library.encode(text or "", add_special_tokens=False).ids)) for i, text, _, source in ROWS)
    assert collections.Counter((r.doc_id, r.source, tuple(r.ids)) for r in pipeline.encode(spark, docs, "").collect()) == ids


def test_quality_keeps_repeats_and_null_ids(spark, docs, tmp_path):
    from devicelens.llm.quality import fit, quality_scores

    spark.createDataFrame([(1, 1), (3, 1), (5, 0), (9, 0)], "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    model = fit(docs, spark.read.parquet(str(tmp_path / "labels.parquet")))
    good = {r.text for r in quality_scores(docs, model, keep=["text"]).collect() if r.predicted}
    assert counted(pipeline.quality(spark, docs, str(tmp_path))) == collections.Counter((*r, len(r[1] or "")) for r in ROWS if r[1] in good)
