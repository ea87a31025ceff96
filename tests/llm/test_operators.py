"""Every operator against a brute-force version on rows with nulls, empty, long, tied and repeated ones."""

import collections
import hashlib
import math
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

P = pytest.importorskip("public_tokenizers")


def prose(seed, n):
    rng = random.Random(seed)
    return " ".join("".join(rng.choice(["ka", "lo", "mi", "ne", "ru", "Sé"]) for _ in range(rng.randint(1, 4))) for _ in range(n))


A, B = prose(1, 300), prose(2, 120)
SHARED = prose(3, 60)
TEXTS = [
    (1, A), (2, A), (3, A.replace("ka", "KA", 3)), (4, B), (5, B + " tail"), (6, SHARED + " " + prose(4, 80)), (7, prose(5, 30) + " " + SHARED), (8, None), (9, ""), (10, "one two"), (11, "one two"),
    (12, " \n\t "), (13, "x" * 5000), (14, prose(6, 3000)), (15, "a<|endoftext|>b  c \n d"), (16, "Ünïcode ﬁ 漢字 'll 12345"), (17, "ab " * 200), (4, B),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, f"s{i % 3}" if i != 5 else None, i) for i, t in TEXTS]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, size int").repartition(3).cache()


def empty(docs):
    return docs.filter("false")


def words(text):
    return (text or "").encode().lower().split()


def test_token_counts(docs):
    from tokenizers import Tokenizer

    from devicelens.llm.token_counts import PieceEncoder, count_tokens, token_counts

    path = P.path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    want = sorted((i, len((t or "").encode()), len(library.encode(t or "", add_special_tokens=False))) for i, t in TEXTS)
    for chunk, overlap in ((32_768, 512), (120, 16)):  # the second splices and widens
        got = sorted((r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts(docs, path, chunk_chars=chunk, overlap_chars=overlap).collect())
        assert got == want
    assert token_counts(empty(docs), path).count() == 0
    text = prose(9, 500) + "y" * 400 + " " + prose(10, 50)
    assert count_tokens(text, PieceEncoder.of(path), 64, 4) == len(library.encode(text, add_special_tokens=False))


def test_byte_bpe_round_trip(docs):
    from tokenizers import Tokenizer

    from devicelens.llm.byte_bpe import decode_ids, encode_ids, round_trip

    path = P.path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = []
    for i, t in TEXTS:
        ids = library.encode(t or "", add_special_tokens=False).ids
        want.append((i, len(ids), sha(",".join(map(str, ids))), sha(library.decode(ids, skip_special_tokens=False))))
    assert sorted(tuple(r) for r in round_trip(docs, path).collect()) == sorted(want)
    back = decode_ids(encode_ids(docs, path), path)
    assert sorted(tuple(r) for r in back.collect()) == sorted((i, t or "") for i, t in TEXTS)


def test_lexicon_is_minimal_and_exact(tmp_path):
    from devicelens.llm.lexicon import Lexicon, compile_lexicon, minimal_automaton

    entries = {w.encode(): [i * 7] * (i % 3 + 1) for i, w in enumerate("a ab abs tabs taps tops stop stops".split())}
    path = tmp_path / "lexicon.bin"
    path.write_bytes(compile_lexicon(entries))
    lexicon = Lexicon(str(path))
    assert {w: lexicon.get(w) for w in entries} == entries
    words = [b"tab", b"", b"zzz", b"stops", b"stopss", b"\xff"]
    assert [p >= 0 for p in lexicon.find(words)] == [False, False, False, True, False, False] and lexicon.find([]) == []
    states, todo = set(), [minimal_automaton(sorted(entries))]
    while todo:
        s = todo.pop()
        if id(s) not in states:
            states.add(id(s))
            todo += s.arcs.values()
    assert len(states) < sum(map(len, entries)) // 2
    path.write_bytes(compile_lexicon({}))
    assert Lexicon(str(path)).find([b"a"]) == [-1]


@pytest.mark.parametrize("memory", [24 << 20, 0])
def test_byte_bpe_of_odd_texts(memory, tmp_path, monkeypatch):
    from tokenizers import Tokenizer

    from devicelens.llm import byte_bpe
    from devicelens.llm.lexicon import compile_lexicon

    monkeypatch.setattr(byte_bpe, "REMEMBERED_BYTES", memory)
    monkeypatch.setattr(byte_bpe, "STRETCH", 50)
    path = P.path("byte_bpe_50k.json")
    library, codec = Tokenizer.from_file(path), byte_bpe.BpeCodec(path)
    file = tmp_path / "lexicon.bin"
    file.write_bytes(compile_lexicon({(" " + w).encode(): np.frombuffer(codec.vocabulary.ids([" " + w])[0], np.int32).tolist() for w in ("the", "ka,", "Sé")}))
    codec = byte_bpe.BpeCodec(path, str(file))
    rng = random.Random(5)
    atoms = [" ", "  ", "\n", "\t ", "\u00a0", "\u3000", "the", "ka,", "Sé", "漢字", "12", "'ll", "<|endoftext|>", "e\u0301", "\x00", "🙂", "...", "abcdefgh" * 9, "zq" * 700, "Ω"]
    texts = ["".join(rng.choice(atoms) for _ in range(rng.randint(0, 40))) for _ in range(400)] + ["<|endoftext|> x" * 3_000, "漢字かな" * 20_000, " " * 5_000, "x" * 30_000]
    for t, encoded, (n, ids_sha, text_sha) in zip(texts, codec.encode(texts), codec.digests(texts)):
        ids = library.encode(t, add_special_tokens=False).ids
        assert encoded.tolist() == ids
        assert (n, ids_sha) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
        assert text_sha == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def backoff(counts, visits, plain, strengths):
    """The model's recursion, word for word: an arc where there is one, else the failure arc and the state below."""

    def weight(history, w):
        if not history:
            return plain(w)
        s, below = strengths[len(history) - 1], history[1:]
        if counts[(*history, w)]:
            return (counts[(*history, w)] + s * weight(below, w)) / (visits[history] + s)
        return s / (visits[history] + s) * weight(below, w)

    return weight


def lm_counts(texts):
    """Counts of runs of one to three tokens (a text begins with "^", which isn't counted itself) and visits of histories."""
    counts, visits = collections.Counter(), collections.Counter()
    for t in texts:
        run = ["^", *t]
        for i in range(1, len(run)):
            for n in range(0, min(i, 2) + 1):
                counts[tuple(run[i - n : i + 1])] += 1
                visits[tuple(run[i - n : i])] += 1
    return counts, visits


def test_language_model(docs):
    from devicelens.llm.lm import STRENGTHS, language_model_scores

    tokens = [(i, words(t) + [None]) for i, t in TEXTS]
    counts, visits = lm_counts([t for i, t in tokens if zlib.crc32(str(i).encode()) % 10])
    n, v = visits[()], sum(len(k) == 1 for k in counts)
    plain = lambda w: (counts[(w,)] + 0.1) / (n + 0.1 * (v + 1))
    weight = backoff(counts, visits, plain, STRENGTHS)
    score = lambda t: sum(math.log10(weight(tuple(["^", *t][max(0, i - 1) : i + 1]), w)) for i, w in enumerate(t))
    want = sorted((i, zlib.crc32(str(i).encode()) % 10 == 0, len(t), sum(counts[(w,)] > 0 for w in t), n, round(sum(math.log10(plain(w)) for w in t), 6), round(score(t), 6)) for i, t in tokens)
    got = sorted((*r[:5], round(r.base_score, 6), round(r.score, 6)) for r in language_model_scores(docs, block_bytes=9_000).collect())
    assert got == want
    assert language_model_scores(empty(docs)).count() == 0
    # all that leaves a state sums to 1: tokens of training, and one class of all others
    for history in [(), ("^",), *[h for h in visits if len(h) == 2][:20]]:
        assert sum(weight(history, k[0]) for k in [*(k for k in counts if len(k) == 1), ("unseen",)]) == pytest.approx(1.0)


def test_language_model_of_held_out_texts_beats_lower_orders(spark):
    from devicelens.llm.lm import language_model_scores

    rng = random.Random(8)
    follow = {a: [rng.choice("abcdefghij") for _ in range(3)] for a in (x + y for x in "abcdefghij" for y in "abcdefghij")}
    texts = []
    for i in range(300):
        t = [rng.choice("abcdefghij"), rng.choice("abcdefghij")]
        while len(t) < 60:
            t.append(rng.choice(follow[t[-2] + t[-1]]))
        texts.append((i, " ".join(t)))
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    total = lambda **kw: sum(r.score for r in language_model_scores(docs, **kw).filter("held_out").collect())
    base = sum(r.base_score for r in language_model_scores(docs).filter("held_out").collect())
    assert total() > 0.75 * total(strengths=(100.0, 1e12)) > base


def brute_components(sets, percent=85):
    parent = list(range(len(sets)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            inter = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * inter >= percent * (len(sets[i]) + len(sets[j]) - inter):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(sets))]


@pytest.mark.parametrize("bucket", [4_000, 2])
def test_ngram_jaccard(docs, bucket):
    from devicelens.llm.jaccard import near_duplicates

    sets = []
    for _, t in TEXTS:
        w = words(t)
        sets.append({tuple(w[k : k + 4]) for k in range(max(1, len(w) - 3))} if w else set())
    root = brute_components(sets)
    least = collections.defaultdict(lambda: 10**9)
    for r, (i, _) in zip(root, TEXTS):
        least[r] = min(least[r], i)
    want = sorted((i, len(s), least[r] if s else i) for (i, _), s, r in zip(TEXTS, sets, root))
    assert sorted(tuple(r) for r in near_duplicates(docs, bucket=bucket).collect()) == want
    if bucket > 2:
        assert near_duplicates(empty(docs)).count() == 0


@pytest.mark.parametrize("hot", [2_000, 0])
def test_repeats(docs, hot):
    from devicelens.llm.repeats import remove_repeats

    raw = [(t or "").encode() for _, t in TEXTS]
    seen = collections.Counter(b[i : i + 200] for b in raw for i in range(len(b) - 199))
    want = []
    for (d, _), b in zip(TEXTS, raw):
        gone = np.zeros(len(b) + 2, int)
        for i in range(len(b) - 199):
            if seen[b[i : i + 200]] > 1:
                gone[i + 1 : i + 201] = 1
        kept = bytes(x for x, g in zip(b, gone[1:]) if not g)
        want.append((d, len(b), int(gone.sum()), int((np.diff(gone) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    got = remove_repeats(docs, hot=hot, block_bytes=6_000).collect()
    assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in got) == sorted(want)
    if hot:
        assert remove_repeats(empty(docs)).count() == 0


def test_maximal_repeats():
    from devicelens.llm.suffixes import EnhancedSuffixArray

    array = EnhancedSuffixArray([b"xabcdy", b"zabcdw", b"abcq"])
    found = {(n, tuple(sorted(p.tolist()))) for n, p in array.maximal_repeats(3)}
    assert found == {(4, (1, 7)), (3, (1, 7, 12))}


def test_mixing(docs):
    from devicelens.llm.mixing import fill, mix

    rows = mix(docs).collect()
    again = mix(docs.repartition(2)).collect()
    key = lambda r: (r.doc_id, r.size, r.source_size, round(r.target, 6), r.taken)
    assert sorted(map(key, rows)) == sorted(map(key, again)) and len(rows) == len(TEXTS)
    total = sum(len(words(t)) for _, t in TEXTS)
    goals = {(r.source, r.source_size, r.target) for r in rows}
    assert sum(g[1] for g in goals) == total and abs(sum(g[2] for g in goals) - total) < 1e-6
    for source, size, target in goals:
        taken = sum(r.taken for r in rows if r.source == source)
        assert target <= 3 * size + 1e-9 and taken <= target + 1 and target - taken <= max(len(words(t)) for _, t in TEXTS)
    assert all(r.taken <= 3 * r.size and r.taken % max(1, r.size) == 0 for r in rows)
    assert mix(empty(docs)).count() == 0
    rng = random.Random(1)
    for _ in range(30):
        lengths = {n: rng.randint(1, 5) for n in rng.sample(range(1, 30), 5)}
        budget = rng.randint(1, 120)
        got = fill(budget, lengths)
        assert all(0 < c <= lengths[n] for n, c in got.items()) and sum(n * c for n, c in got.items()) <= budget


def vectors(spark):
    rng = np.random.default_rng(1)
    base = rng.standard_normal((300, 16))
    base[100:130] = base[0] + 0.02 * rng.standard_normal((30, 16))
    base[131] = base[130]
    rows = [(int(i), [float(np.float32(v)) for v in x], int(i % 3 == 0) if i < 100 or i > 131 else 5) for i, x in enumerate(base)]
    rows += [(900, None, 1), (901, [0.0] * 16, 1), (902, [float("nan")] * 16, 1), (903, [None] + [1.0] * 15, 1), (904, rows[0][1], None), (905, rows[131][1], 5), (905, rows[131][1], 5)]
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), rows


def test_nearest(spark):
    from devicelens.llm.ann import nearest

    df, rows = vectors(spark)
    good = [(i, np.array(v)) for i, v, _ in rows if i < 900 or i in (904, 905)]
    got = collections.defaultdict(list)
    for r in nearest(df, F.col("id") % 20 == 0, k=10).collect():
        got[r.query_id].append((r["rank"], r.vec_id, r.score))
    hit = total = 0
    assert set(got) == {i for i, _ in good if i % 20 == 0}
    for q, found in got.items():
        me = next(v for i, v in good if i == q)
        want = sorted(((-float(me @ v), i) for i, v in good if i != q))[:10]
        found.sort()
        assert [r for r, _, _ in found] == list(range(1, 11)) and [s for _, _, s in found] == sorted((s for _, _, s in found), reverse=True)
        hit += len({i for _, i in want} & {i for _, i, _ in found})
        total += len({i for _, i in want})
    assert hit >= 0.9 * total
    # several blocks, a group of few rows, another order of rows, and columns whose names the operator uses: the same
    again = nearest(df.orderBy("label").withColumn("id", F.lit(1)).withColumn("block", F.lit(2)).withColumn("rank", F.lit(3)), F.col("id") % 20 == 0, k=10, block_bytes=4 * 16 * 60, group_rows=16)
    few = collections.defaultdict(set)
    for r in again.collect():
        few[r.query_id].add(r.vec_id)
    assert sum(len(few[q] & {i for _, i, _ in found}) for q, found in got.items()) >= 0.85 * total
    assert nearest(df.filter("false"), F.col("id") % 20 == 0).count() == 0


@pytest.mark.parametrize("dims", [64, 384])
@pytest.mark.parametrize("sigma", [0.0, 0.5, 1.0])
def test_recall_by_collisions(dims, sigma):
    """Vectors without any structure, of like and of very unlike norms: recall, and how few are verified."""
    from devicelens.llm.ann import Block

    rng = np.random.default_rng(4)
    x = (rng.standard_normal((4_096, dims)) * np.exp(sigma * rng.standard_normal((4_096, 1)))).astype(np.float32)
    ids, chosen = np.arange(len(x)), np.arange(0, 4_096, 100)
    block = Block(x, ids, 1_024)
    hit = 0
    for q, (found, scores) in zip(chosen, block.search(x[chosen], ids[chosen], 20)):
        exact = x.astype(np.float64) @ x[q].astype(np.float64)
        assert np.array_equal(scores, np.sort(scores)[::-1]) and np.allclose(scores, exact[found], rtol=1e-12)
        exact[q] = -np.inf
        hit += len({*found.tolist()} & {*np.argsort(-exact)[:20].tolist()})
    assert hit >= 0.9 * 20 * len(chosen)
    assert sum(g.verified for g in block.groups) <= 0.3 * len(chosen) * len(x)
    backward = Block(x[::-1], ids[::-1], 1_024).search(x[chosen[::-1]], ids[chosen[::-1]], 20)[::-1]
    assert all(np.array_equal(a, b) for (a, _), (b, _) in zip(backward, block.search(x[chosen], ids[chosen], 20)))


def test_nearest_ties_and_repeated_queries(spark):
    from devicelens.llm.ann import nearest

    rows = [(i, [1.0, float(i % 2)]) for i in range(60)] + [(20, [1.0, 0.0]), (7, [1.0, 1.0])]
    got = sorted(tuple(r) for r in nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(3), F.col("id") % 20 == 0, k=5, block_bytes=8 * 60).collect())
    assert got == sorted((q, r, i, 1.0) for q in (0, 20, 40) for r, i in enumerate([x for x in range(6) if x != q][:5], 1))


def linked_by_brute_force(rows):
    """vec_id, links and component of (vec_id, vector, label) rows, all compared."""
    unit = [None if v is None or None in v or not np.isfinite(v).all() or not np.any(v) or l is None else np.array(v) / np.linalg.norm(v) for _, v, l in rows]
    n = len(rows)
    link = [[j for j in range(n) if i != j and unit[i] is not None and unit[j] is not None and rows[i][2] == rows[j][2] and float(unit[i] @ unit[j]) >= 0.98] for i in range(n)]
    root = list(range(n))
    while (new := [min([root[i], *(root[j] for j in link[i])]) for i in range(n)]) != root:
        root = new
    least = {r: min(rows[i][0] for i in range(n) if root[i] == r) for r in set(root)}
    return sorted((rows[i][0], len(link[i]), least[root[i]]) for i in range(n))


def test_near_duplicate_vectors(spark):
    from devicelens.llm.neighbour_graph import near_duplicate_vectors

    df, rows = vectors(spark)
    got = near_duplicate_vectors(df).collect()
    assert sorted((r.vec_id, r.n_links, r.component_id) for r in got) == linked_by_brute_force(rows)
    assert all(r.kept == (r.vec_id == r.component_id) for r in got)
    clashing = df.withColumn("class", F.lit("x")).withColumn("rows", F.lit(1)).withColumn("code", F.lit(2))
    assert sorted(map(tuple, near_duplicate_vectors(clashing).collect())) == sorted(map(tuple, got))
    assert near_duplicate_vectors(df.filter("false")).count() == 0


@pytest.mark.parametrize("cell_rows, part_rows", [(40, 6_000), (6_000, 50), (60, 30)])
def test_near_duplicate_vectors_in_cells_and_parts(spark, cell_rows, part_rows):
    from devicelens.llm.neighbour_graph import near_duplicate_vectors

    rng = np.random.default_rng(3)
    base = rng.standard_normal((40, 8))
    x = base[rng.integers(0, 40, 260)] + 0.07 * rng.standard_normal((260, 8))
    x[200:] = x[0] + 0.02 * rng.standard_normal((60, 8))  # one group fills cells of its own
    rows = [(i, [float(np.float32(v)) for v in y], 1) for i, y in enumerate(x)]
    got = near_duplicate_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"), cell_rows=cell_rows, part_rows=part_rows)
    assert sorted((r.vec_id, r.n_links, r.component_id) for r in got.collect()) == linked_by_brute_force(rows)


def test_a_cell_of_near_copies_keeps_no_pairs():
    import tracemalloc

    from devicelens.llm.neighbour_graph import find_links

    rng = np.random.default_rng(3)
    x = (rng.standard_normal(64) + 0.05 * rng.standard_normal((12_000, 64))).astype(np.float32)
    tracemalloc.start()
    links = find_links(x, np.ones(len(x), np.int64), lambda a, b: np.ones(np.broadcast_shapes(a.shape, b.shape), bool))
    assert tracemalloc.get_traced_memory()[1] < 300e6
    tracemalloc.stop()
    assert (links.total == len(x) - 1).all() and not links.root.any()


def test_warc(spark, tmp_path):
    from devicelens.llm.warc import read_archives, write_archives

    long = "<p>" + "é" * 80 + "</p>"
    rows = [(3, "http://a/ b\n", long), (1, None, long), (2, "http://c", "x"), (4, "http://c", "x"), (5, "u", None), (6, "u", long + "!"), (None, "n", long), (7, "r", "WARC/1.1\r\n\r\n" * 20)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    archives = write_archives(pages, str(tmp_path / "a"))
    got = sorted(((r.page_id or 0), r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in read_archives(archives).collect())
    body = lambda h: (h or "").encode()
    kind = {3: ("revisit", 1)}
    assert got == sorted(((i or 0), len(body(h)), hashlib.sha256(body(h)).hexdigest(), *kind.get(i, ("response", None))) for i, _, h in rows)


def test_quality_on_held_out_rows(spark):
    from devicelens.llm.quality import fit, quality_scores

    rng = random.Random(2)
    rows, labels = [], []
    for i in range(400):
        good = rng.random() < 0.7
        text = prose(1000 + i, 60)
        rows.append((i, text if good else text.replace(" ", "$$$ ").upper()))
        labels.append((i, int(good)))
    docs = spark.createDataFrame([*rows, (500, None), (501, "")], "doc_id long, text string")
    scores = {r.doc_id: r for r in quality_scores(docs, fit(docs, spark.createDataFrame(labels, "doc_id long, quality int"))).collect()}
    held = [(scores[i].predicted, y) for i, y in labels if zlib.crc32(str(i).encode()) % 4 == 2]
    assert sum(p == y for p, y in held) >= 0.95 * len(held)
    assert all(0 <= r.score <= 1 for r in scores.values()) and scores[500].score == scores[501].score


@pytest.mark.parametrize("at_once", [200_000, 3])
def test_components(spark, at_once):
    from devicelens.llm.components import components

    path = [(i, i + 1) for i in range(12)]
    star, odd = [(50, 50 + i) for i in range(1, 9)] + [(50, 51), (51, 50)], [(100, 101), (7, 7)]
    found = {(r.node, r.root) for r in components(spark.createDataFrame(path + star + odd, "a long, b long"), at_once).collect()}
    assert found == {(i, 0) for i in range(13)} | {(i, 50) for i in range(50, 59)} | {(100, 100), (101, 100)}
    assert components(spark.createDataFrame([], "a long, b long"), at_once).count() == 0


@pytest.mark.parametrize("n", range(1, 6))
def test_ngram_sets_of_few_words(n):
    from devicelens.llm.jaccard import ngram_sets

    text = " ".join("abcdefgh"[:n]).encode()
    alone, = ngram_sets([text])
    assert len(alone) == max(1, n - 3)
    among = ngram_sets([b"p q r s t " * 300_000, text, b"", text])  # the first fills a part of its own
    assert np.array_equal(among[1], alone) and np.array_equal(among[3], alone) and len(among[2]) == 0


def test_portions_keep_every_row():
    import pyarrow as pa

    from devicelens.llm.common import portions

    texts = ["a", None, "b" * 50, "", "c" * 5, "d" * 5, None]
    batches = [pa.RecordBatch.from_arrays([pa.array(range(len(texts))), pa.array(texts, pa.string())], ["i", "text"]), pa.RecordBatch.from_arrays([pa.array([], pa.int64()), pa.array([], pa.string())], ["i", "text"])]
    parts = list(portions(iter(batches), 1, at_most=10, rows=3))
    assert [x for p in parts for x in p.column(1).to_pylist()] == texts
    assert all(p.num_rows <= 3 and (p.num_rows == 1 or sum(len(t or "") for t in p.column(1).to_pylist()) <= 10) for p in parts)
