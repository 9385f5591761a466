"""Each operator against brute force or a public library, and on awkward tables."""

import hashlib
import random
import re
import sys
import time
import zlib
from collections import Counter
from pathlib import Path

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))
from conftest import SF, rows_of  # noqa: E402

from dpchangelog.llm import byte_bpe, embedding_dedup, line_dedup, lm_scoring, packing, piece_bpe, quality_classifier, quality_rules, record_files, simhash, token_counts  # noqa: E402
from dpchangelog.llm import queries as Q  # noqa: E402
from dpchangelog.llm.common import components, table  # noqa: E402

public_tokenizers = pytest.importorskip("public_tokenizers")
BYTES, PIECES = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("piece_bpe_32k.model")
WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, h long, row string, fp string, a int, n string, score double, idx int"


def fuzz(n=300, seed=1):
    r = random.Random(seed)
    parts = ["a", "b", "aaaa", "  ", " ", "\n", "\t", "'s", "é", "ü", "中文", "▁", "😀", "\x00", "　", "12", "<|endoftext|>", ".", ",", "<0x0A>", "\r\n", "word", " the", "ing"]
    return ["".join(r.choice(parts) for _ in range(r.randint(0, 30))) for _ in range(n)]


def rows(texts, lang="en", source="s"):
    return [(i, t, lang, source, 1, 1, "x", "y", 2, "z", 0.5, 3) for i, t in enumerate(texts)]


LONG = "one two three four five six seven eight nine ten " * 4000
AWKWARD = [None, "", "   \n \n", "same text here for all of us to see", "same text here for all of us to see", LONG, "x", "\n".join(["line one", "line two", "line three", "line one", "line two", "line three"])]


@pytest.fixture(scope="module")
def awkward(spark):
    """Nulls in any column, empty and very long texts, repeated rows, ties, and columns whose names clash."""
    data = rows(AWKWARD) + [rows(["same text here for all of us to see"])[0]] * 2 + [(None, "a text without an id", None, None, None, None, None, None, None, None, None, None)] * 2 + [(3, "another text of the id three", "en", None, 1, 1, None, None, 1, None, None, 1)]
    return spark.createDataFrame(data, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return table(spark, SF, "documents")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}


@pytest.fixture(scope="module")
def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(BYTES)


# 1
def test_records_round_trip(spark, docs, texts, tokenizer):
    out = {r.doc_id: r for r in Q.op1_token_records(spark, SF).collect()}
    at = 0
    for i in sorted(texts):
        ids = tokenizer.encode(texts[i] or "", add_special_tokens=False).ids + [2]
        assert (out[i].start, out[i].n_tokens, out[i].ids_crc32) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)
    assert len(out) == len(texts)


def test_records_awkward_and_shuffled_reads(spark, awkward, empty, tmp_path):
    where = f"file://{tmp_path}/records"
    record_files.write_records(awkward, where, BYTES)
    index = record_files.index_records(spark, where, f"file://{tmp_path}/index")
    assert index.count() == awkward.count()
    got = sorted(((r.doc_id, list(r.ids)) for r in record_files.read_records(spark, where).collect()), key=str)
    assert len(got) == awkward.count()
    for r in record_files.shuffled_order(index, 5).collect():
        name = next(tmp_path.glob(f"records/file={r.shard & 0xFFFFFF}/part-{r.shard >> 24:05d}-*.txt"))
        doc_id, ids = record_files.read_at(f"file://{name}", r.byte_offset, r.byte_length)
        assert doc_id == r.doc_id and len(ids) == r.n_tokens
    record_files.write_records(empty, f"file://{tmp_path}/none", BYTES)
    assert record_files.index_records(spark, f"file://{tmp_path}/none").count() == 0


def test_files_are_bounded_in_bytes(spark, docs, texts, tokenizer, monkeypatch, tmp_path):
    monkeypatch.setattr(record_files, "FILE_BYTES", 20_000)
    record_files.write_records(docs, f"file://{tmp_path}/records", BYTES)
    sizes = [f.stat().st_size for f in tmp_path.glob("records/file=*/part-*.txt")]
    index = record_files.index_records(spark, f"file://{tmp_path}/records").toPandas()
    alone = index.groupby("shard").size()[lambda n: n == 1].index
    assert len(sizes) > 10 and len(sizes) == index.shard.nunique()
    assert sum(s > 20_000 for s in sizes) <= len(alone)
    # Ids ascend over files in the order of their names, and each frame begins where the one before ends.
    index = index.sort_values(["shard", "seq"])
    assert index.doc_id.is_monotonic_increasing
    assert index.start.tolist() == [0, *index.n_tokens.cumsum().tolist()[:-1]]
    for _, own in index.groupby("shard"):
        assert own.byte_offset.tolist() == [0, *(own.byte_length + 1).cumsum().tolist()[:-1]]


def test_damage_is_found():
    good = record_files.record(7, 2, b"\x01\x00\x02\x00") + b"\n"
    assert [p for _, p in record_files.frames(good)]
    for k in (2, 9, 15, len(good) - 3):
        with pytest.raises(ValueError):
            list(record_files.frames(good[:k] + bytes([good[k] ^ 1]) + good[k + 1 :]))
    with pytest.raises(ValueError):
        list(record_files.frames(good[:-4]))


# 2 and 8, and the encoder of 1 and 7
def test_encoders_equal_the_libraries(texts, tokenizer):
    import sentencepiece

    sample = fuzz() + list(texts.values()) + ["", None, " " * 50, "a" * 500]
    want = [tokenizer.encode(t or "", add_special_tokens=False).ids for t in sample]
    assert token_counts.TokenCounter(BYTES).count(sample) == [len(w) for w in want]
    bpe = byte_bpe.ByteBpe(BYTES)
    assert [np.frombuffer(bpe.encode(t), bpe.kind).tolist() for t in sample] == want
    library, own = sentencepiece.SentencePieceProcessor(model_file=PIECES), piece_bpe.PieceBpe(PIECES)
    for t in sample:
        ids = library.encode(t or "")
        assert own.encode(t) == (",".join(map(str, ids)), len(ids), library.decode(ids))
    own.check_new()


def test_caches_that_overflow_change_nothing(texts, tokenizer, monkeypatch):
    monkeypatch.setattr(byte_bpe, "CACHE_WORDS", 50)
    monkeypatch.setattr(piece_bpe, "CACHE_WORDS", 50)
    monkeypatch.setattr(token_counts, "CACHE_WORDS", 50)
    sample = [t for t in texts.values()][:20]
    want = [tokenizer.encode(t, add_special_tokens=False).ids for t in sample]
    bpe = byte_bpe.ByteBpe(BYTES)
    assert [np.frombuffer(bpe.encode(t), bpe.kind).tolist() for t in sample] == want
    counter = token_counts.TokenCounter(BYTES)
    assert [n for t in sample for n in counter.count([t])] == [len(w) for w in want]
    own = piece_bpe.PieceBpe(PIECES)
    assert [own.encode(t) for t in sample] == [piece_bpe.PieceBpe(PIECES).encode(t) for t in sample]


def test_vocabularies_that_merge_otherwise_are_counted_by_the_library(tmp_path):
    import json

    from tokenizers import Tokenizer

    spec = json.loads(Path(BYTES).read_text())
    letters = {t: i for t, i in spec["model"]["vocab"].items() if len(t) == 1}
    n = max(letters.values()) + 1
    ab, bc, abc = "ab", "bc", "abc"
    for merges in ([["b", "c"], ["a", "b"], ["ab", "c"], ["a", "bc"]], [["ab", "c"], ["a", "b"]]):  # two ways to one token; a merge before its operand's
        spec["model"] |= {"vocab": letters | {ab: n, bc: n + 1, abc: n + 2}, "merges": merges}
        spec["added_tokens"] = []
        at = tmp_path / "v.json"
        at.write_text(json.dumps(spec))
        counter, library = token_counts.TokenCounter(str(at)), Tokenizer.from_file(str(at))
        sample = ["abc", "ababc abc", "aabcc", "", None]
        assert not counter.simultaneous
        assert counter.count(sample) == [len(library.encode(t or "", add_special_tokens=False).ids) for t in sample]
    assert token_counts.TokenCounter(BYTES).simultaneous


def test_pieces_that_differ_are_the_librarys(texts):
    import sentencepiece

    library, own = sentencepiece.SentencePieceProcessor(model_file=PIECES), piece_bpe.PieceBpe(PIECES)
    sample = [t for t in texts.values() if t][:40] + ["  two  spaces "]
    for piece in [t for t in own.agenda.cost if len(t) > 2][:2000]:
        del own.agenda.cost[piece]  # an agenda that is wrong
    for t in sample:
        own.encode(t)
    assert own.check_new() and own.bad
    for t in sample:
        ids = library.encode(t)
        assert own.encode(t) == (",".join(map(str, ids)), len(ids), library.decode(ids))
    assert own.replaced and not own.check_new()


def test_words_of_a_batch_are_encoded_side_by_side(texts, monkeypatch):
    own = piece_bpe.PieceBpe(PIECES)
    sample = fuzz() + list(texts.values()) + ["a" * 64 + " " + "ab" * 40 + "\nline", None, ""]
    words = sorted({m + w for t in sample if t for line in t.split("\n") for w in line.split(" ") for m in ("", piece_bpe.SPACE) if m + w})
    found = own.batch.encode(words)
    assert all(ids is None or ids == own.agenda.encode(w) for w, ids in zip(words, found, strict=True))
    strange = [w for w in words if not set(w) <= set(own.agenda.ids) or len(w) > 64]
    assert [w for w, ids in zip(words, found, strict=True) if ids is None] == strange and strange
    want = [own.encode(t) for t in sample]
    own, alone = piece_bpe.PieceBpe(PIECES), []
    monkeypatch.setattr(own.agenda, "encode", lambda w: alone.append(w) or piece_bpe.Agenda.encode(own.agenda, w))
    monkeypatch.setattr(piece_bpe.BatchAgenda, "WORDS", 100)
    own.learn(sample)
    assert [own.encode(t) for t in sample] == want and not own.check_new()
    plain = [t for t in texts.values() if t and not set(t) - set(own.agenda.ids) - set(" \n") and "  " not in t]
    alone.clear()
    own.marked.clear()
    own.learn(plain)
    assert [own.encode(t) for t in plain] and not [w for w in alone if len(w) <= 64]


def test_column_names_with_dots_and_spaces(spark, tmp_path):
    d = spark.createDataFrame([(1, "some words here", "en", "s"), (2, None, "en", "s")], "`a.id` long, `the text` string, `l.` string, `s` string")
    names = {"id_col": "a.id", "text_col": "the text"}
    record_files.write_records(d, f"file://{tmp_path}/records", BYTES, **names)
    assert record_files.index_records(spark, f"file://{tmp_path}/records").count() == 2
    out = [token_counts.count_tokens(d, BYTES, **names), piece_bpe.encode_decode(d, PIECES, **names), packing.pack_texts(d, BYTES, **names), line_dedup.dedup_lines(d, **names), simhash.groups(d, **names), simhash.similar_groups(d, **names)]
    out.append(quality_rules.quality_rules(d, lang_col="l.", source_col="s", **names))
    out.append(lm_scoring.score_documents(d, spark.createDataFrame([(1,)], "doc_id long"), **names))
    out.append(quality_classifier.scored(d, quality_classifier.train_classifier(d, spark.createDataFrame([(1, 1)], "`l.id` long, `the label` int"), label_col="the label", label_id_col="l.id", **names), **names))
    assert [x.count() for x in out] == [2] * len(out)
    assert simhash.near_duplicates_removed(d, **names).columns == d.columns


def test_overlapping_pairs_of_one_rank():
    ranks = token_counts.PairRanks(np.array([1, 2]), np.array([1, 2]), np.array([2, 3]), 4)
    symbols = np.array([1] * 3 + [1] * 4 + [1] + [1] * 7)
    assert token_counts.merge_all(symbols, np.array([3, 4, 1, 7]), ranks).tolist() == [2, 1, 1, 3]


def test_token_counts_and_pieces_awkward(spark, awkward, empty, tokenizer):
    out = token_counts.count_tokens(awkward, BYTES).collect()
    assert sorted(r.n_tokens for r in out) == sorted(len(tokenizer.encode(r.text or "", add_special_tokens=False).ids) for r in awkward.collect())
    assert sorted(r.n_bytes for r in out) == sorted(len((r.text or "").encode()) for r in awkward.collect())
    assert piece_bpe.encode_decode(awkward, PIECES).count() == awkward.count()
    for f in (lambda d: token_counts.count_tokens(d, BYTES), lambda d: piece_bpe.op8(spark, d, PIECES), lambda d: packing.pack_texts(d, BYTES)):
        assert f(empty).count() == 0


def test_piece_digests(spark, texts):
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    for r in Q.op8_piece_bpe(spark, SF).collect():
        ids = library.encode(texts[r.doc_id] or "")
        assert r.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest() and r.n_tokens == len(ids)
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids).encode()).hexdigest()


# 3
def dedup_by_hand(pairs):
    seen, out = set(), {}
    for i, t in sorted(pairs):
        lines = t.split("\n")
        gone = set()
        for k in range(len(lines) - 2):
            w = tuple(x.strip(" ") for x in lines[k : k + 3])
            if not any(w):
                continue
            if w in seen:
                gone |= {k, k + 1, k + 2}
            seen.add(w)
        out[i] = ("\n".join(x for k, x in enumerate(lines) if k not in gone), len(gone))
    return out


def test_line_dedup(spark, docs, texts, duck):
    got = {r.doc_id: (r.text, r.n_removed) for r in line_dedup.dedup_lines(docs).collect()}
    assert got == dedup_by_hand(texts.items())
    assert any(n for _, n in got.values())
    assert rows_of(Q.op3_line_dedup(spark, SF).toPandas()) == rows_of(duck.execute(line_dedup.SQL).df())


def test_line_dedup_awkward(spark, awkward, empty):
    out = line_dedup.dedup_lines(awkward)
    assert out.count() == awkward.count() and out.columns[: len(awkward.columns)] == awkward.columns
    last = [r for r in out.collect() if r.doc_id == 7][0]
    assert (last.text, last.n_removed, last.n_lines) == ("line one\nline two\nline three", 3, 6)
    assert line_dedup.dedup_lines(empty).count() == 0
    clash = line_dedup.dedup_lines(awkward.withColumns({"N_LINES": F.lit("mine"), "n_removed": F.lit("too")}))
    last = [r for r in clash.collect() if r.doc_id == 7][0]
    assert (last.N_LINES, last.n_removed, last.n_lines_, last.n_removed_) == ("mine", "too", 6, 3)


# 4
def statistics_by_hand(t):
    words = WORD.findall(t or "")
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    n, covered = Counter(windows), set()
    for i, w in enumerate(windows):
        if n[w] > 1:
            covered |= set(range(i, i + 8))
    lines = [x for x in (t or "").split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t or "")) if words else len(re.findall(r"[#*$%&|<>]", t or "")), len(lines) - len(set(lines)), len(covered)


def test_quality_rules(spark, docs, texts):
    out = {r.doc_id: r for r in Q.op4_quality_rules(spark, SF).collect()}
    labels = {r.doc_id: r.quality for r in table(spark, SF, "labels").collect()}
    for i, t in texts.items():
        s, r = statistics_by_hand(t), out[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == s
        assert r.base_failed == (s[0] < 20 or 100 * s[4] > 30 * s[0])
        assert not (r.base_failed and r.kept)
    good = [out[i] for i, q in labels.items() if q == 1 and i in out and not out[i].base_failed]
    assert sum(r.kept for r in good) >= 0.97 * len(good)
    kept = quality_rules.documents_kept(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {i for i, r in out.items() if r.kept}


def distances(x, e):
    centre = np.array([e[f"m{j}"] for j in range(5)])
    root = np.array([[e[f"i{i}{j}"] if j <= i else 0 for j in range(5)] for i in range(5)])
    return (((x - centre) @ root.T) ** 2).sum(1)


VECTORS = "lk string, sk string, x0 double, x1 double, x2 double, x3 double, x4 double"


def test_outliers_against_numpy(spark):
    r = np.random.default_rng(5)
    x = r.multivariate_normal([5, 1.7, 0, 0, 0], np.diag([0.4, 0.01, 1e-6, 1e-6, 1e-6]), 500)
    x[:25, 2] = 3.3
    data = spark.createDataFrame([("a", "b", *map(float, v)) for v in x], VECTORS)
    estimates = quality_rules.fit(data)
    (e,) = estimates.collect()
    assert (e.m0, e.m1) == pytest.approx((5, 1.7), abs=0.15) and e.m2 < 0.05
    judged = quality_rules.judge(data.withColumn("base_failed", F.lit(False)), estimates).collect()
    assert sum(not j.kept for j in judged) == (distances(x, e) > quality_rules.CUTOFF).sum() >= 25


@pytest.mark.parametrize("seed", range(4))
def test_estimates_against_all_subsets(spark, seed, monkeypatch):
    """The minimum covariance determinant by trying every subset of three quarters, floors and consistency factor alike."""
    from itertools import combinations

    monkeypatch.setattr(quality_rules, "SHRINK", 0)
    r = np.random.default_rng(seed)
    x = r.normal(size=(16, 5)) * [0.6, 0.1, 0.5, 0.5, 0.5] + [5, 1.7, 1, 0.5, 0.5]
    x[:3] += [4, 0, 5, 0, 3]
    floor = np.diag(np.square(quality_rules.FLOOR))

    def covariance(rows):
        return quality_rules.CONSISTENCY * np.cov(rows.T, bias=True) + floor

    best = min((x[list(s)] for s in combinations(range(16), 12)), key=lambda rows: np.linalg.det(covariance(rows)))
    d = x - best.mean(0)
    theirs = (d @ np.linalg.inv(covariance(best)) * d).sum(1)
    (e,) = quality_rules.fit(spark.createDataFrame([("a", "b", *map(float, v)) for v in x], VECTORS)).collect()
    own = distances(x, e)
    log_det = -2 * sum(np.log(e[f"i{j}{j}"]) for j in range(5))
    assert log_det <= np.log(np.linalg.det(covariance(best))) + 0.25  # as small a determinant, or nearly
    assert ((own > quality_rules.CUTOFF) == (theirs > quality_rules.CUTOFF)).all() and (own > quality_rules.CUTOFF)[:3].all()
    assert np.corrcoef(own, theirs)[0, 1] > 0.99


def test_every_group_has_an_estimate_of_its_own(spark):
    r = np.random.default_rng(8)
    sizes = {("a", "x"): 2000, ("a", "y"): 400, ("a", "z"): 5, ("b", "x"): 400, ("b", "y"): 1}
    centre = {("a", "x"): 4.0, ("a", "y"): 7.0, ("a", "z"): 4.0, ("b", "x"): 9.0, ("b", "y"): 9.0}
    rows = [(*g, *map(float, r.normal(size=5) * 0.05 + [centre[g], 1.7, 0.5, 0.1, 0.1])) for g, n in sizes.items() for _ in range(n)]
    data = spark.createDataFrame(rows, VECTORS)
    e = {(x.lk, x.sk): x for x in quality_rules.fit(data).collect()}
    assert set(e) == set(sizes)
    assert all(abs(e[g].m0 - centre[g]) < 0.6 for g in (("a", "x"), ("a", "y"), ("b", "x")))
    lang = (60 * 4.0 + 5 * 4.0) / 65  # a group of five is nearly its language
    assert abs(e["a", "z"].m0 - lang) < 1.0
    # A vector that is common in one group is an outlier in another of the same language.
    odd = spark.createDataFrame([("a", "x", 7.0, 1.7, 0.5, 0.1, 0.1), ("a", "y", 7.0, 1.7, 0.5, 0.1, 0.1)], VECTORS).withColumn("base_failed", F.lit(False))
    kept = {x.sk: x.kept for x in quality_rules.judge(odd, spark.createDataFrame([e["a", "x"], e["a", "y"]])).collect()}
    assert kept == {"x": False, "y": True}


def test_statistics_can_be_filtered(spark):
    """A filter on a statistic isn't pushed into the expressions, so it costs what the statistics cost."""
    began = time.time()
    d = table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "text")
    out = quality_rules.text_statistics(d, F.col("text")).where("not base_failed and n_repeat_words >= 0")
    assert 0 < out.select("doc_id", "n_words").count() < d.count() and time.time() - began < 60


def test_repeats_alone_reject_long_documents_only(spark):
    r = np.random.default_rng(3)
    words = lambda n: " ".join("".join(map(chr, r.integers(97, 123, 5))) for _ in range(n))
    lines = lambda n: [words(9) for _ in range(n)]
    texts = ["\n".join(lines(k)) for k in np.exp(r.uniform(1.6, 6, 150)).astype(int).tolist()]
    half = "\n".join(x for line in lines(200) for x in (line, "again and again"))  # every other line is one short line
    short = lines(8)
    texts += [half, "\n".join([*short, short[3]])]
    out = {x.doc_id: x for x in quality_rules.quality_rules(spark.createDataFrame(rows(texts), SCHEMA)).collect()}
    assert out[150].n_dup_lines == 199 and not out[150].base_failed and not out[150].kept
    assert out[151].n_dup_lines == 1 and not out[151].base_failed and out[151].kept
    assert all(out[i].kept for i in range(150))


def test_quality_rules_awkward(awkward, empty):
    assert quality_rules.quality_rules(awkward).count() == awkward.count()
    assert quality_rules.documents_kept(awkward).columns == awkward.columns
    assert quality_rules.quality_rules(empty).count() == 0


# 5
def test_classifier_holds_out(spark):
    d = "/root/testdata/sf0.01"
    out = Q.op5_quality_classifier(spark, d).join(table(spark, d, "labels"), "doc_id").where("held_out").toPandas()
    assert len(out) > 50 and out.score.between(0, 1).all()
    assert (out.predicted == out.quality).mean() > 0.9
    assert (out.predicted == (out.score >= 0.7)).all()


def test_gradients_are_those_of_the_loss():
    r = np.random.default_rng(2)
    sizes, y = np.array([3, 1, 5]), np.array([1.0, 0.0, 1.0])
    x = r.normal(size=(9, 6))
    m = quality_classifier.AttentionModel.fresh(np.zeros(6), np.ones(6), 4, 3)
    loss = lambda: -float(np.mean(y * np.log(m.score(x, sizes)) + (1 - y) * np.log(1 - m.score(x, sizes))))
    grads = m.gradients(x, sizes, y, 0.0)
    for k, g in grads.items():
        at = tuple(np.unravel_index(np.abs(g).argmax(), g.shape))
        keep = m.p[k][at]
        m.p[k][at] = keep + 1e-5
        up = loss()
        m.p[k][at] = keep - 1e-5
        assert g[at] == pytest.approx((up - loss()) / 2e-5, rel=1e-3, abs=1e-7)
        m.p[k][at] = keep
    assert np.add.reduceat(m.attention(x, sizes), [0, 3, 4]) == pytest.approx([1, 1, 1])


def test_what_is_learnt_from_is_bounded_in_bytes(spark, docs):
    labels = table(spark, SF, "labels")
    some = quality_classifier.train_classifier(docs, labels, sample_bytes=1 << 16)
    assert isinstance(some, quality_classifier.AttentionModel)
    assert isinstance(quality_classifier.train_classifier(docs, labels, sample_bytes=10), quality_classifier.Constant)
    twice = quality_classifier.train_classifier(docs.unionByName(docs), labels, sample_bytes=1 << 16)
    assert all(np.array_equal(some.p[k], twice.p[k]) for k in some.p)


def test_classifier_awkward(spark, awkward, empty):
    labels = spark.createDataFrame([(0, 1, 0), (1, 0, 0), (1, 1, 0), (None, 1, 0), (4, None, 0), (7, 1, 1)], "doc_id long, quality int, toxic int")
    none = labels.where("false")
    for lab in (labels, none, labels.where("quality = 1")):
        out = quality_classifier.op5(spark, awkward, lab)
        assert out.count() == awkward.count() and out.where("score is null or score < 0 or score > 1").count() == 0
    assert quality_classifier.documents_accepted(awkward, none).count() == awkward.count()
    assert quality_classifier.op5(spark, empty, labels).count() == 0


# 6
def links_by_hand(vectors, threshold=0.9):
    n = len(vectors)
    x = np.array([[np.nan if e is None else e for e in v] if v is not None and len(v) == 64 else [np.nan] * 64 for v in vectors], float)
    with np.errstate(all="ignore"):
        x = x / np.linalg.norm(x, axis=1, keepdims=True)
        s = x @ x.T >= threshold
    np.fill_diagonal(s, False)
    label = np.arange(n)
    for i in range(n):
        for j in np.flatnonzero(s[i]):
            a, b = label[i], label[j]
            if a != b:
                label[label == max(a, b)] = min(a, b)
    return s.sum(1), label


def test_embedding_links(spark):
    e = table(spark, SF, "embeddings").orderBy("vec_id").collect()
    out = {r.vec_id: r for r in Q.op6_embedding_dedup(spark, SF).collect()}
    n, label = links_by_hand([r.embedding for r in e])
    assert [out[r.vec_id].n_links for r in e] == n.tolist()
    assert [out[r.vec_id].component_id for r in e] == [e[k].vec_id for k in label]


def test_large_buckets_and_awkward_vectors(spark, monkeypatch):
    monkeypatch.setattr(embedding_dedup, "ROWS", 40)
    r = np.random.default_rng(4)
    centre = r.normal(size=64)
    vs = [(centre + r.normal(size=64) * s).tolist() for s in (0.02, 0.2, 0.35) for _ in range(70)] + [r.normal(size=64).tolist() for _ in range(100)]
    vs += [vs[0]] * 5 + [None, [], [0.0] * 64, [float("nan")] * 64, [None] * 64, [1.0] * 63, [1e200] * 64, [1e-200] * 64]
    data = spark.createDataFrame(list(enumerate(vs)), "vec_id long, embedding array<double>")
    out = sorted(embedding_dedup.near_vectors(data).collect())
    n, label = links_by_hand([[1.0] * 64 if v and max(map(lambda e: abs(e or 0), v)) in (1e200, 1e-200) else v for v in vs])
    found, all_ = sum(x.n_links for x in out), n.sum()
    assert 0.97 * all_ <= found <= all_
    assert [x.component_id for x in out] == label.tolist()
    assert embedding_dedup.near_vectors(data.where("false")).count() == 0


def test_vectors_with_awkward_ids_and_columns(spark):
    r = np.random.default_rng(14)
    a, b = r.normal(size=(2, 64))
    near = (a + 0.05 * r.normal(size=64)).tolist()
    rows_ = [(None, a.tolist()), (7, a.tolist()), (7, near), (7, b.tolist()), (None, None), (3, near), (None, (b + 0.01).tolist())]
    data = spark.createDataFrame([(i, v, 1, 2, 3, "x") for i, v in rows_], "vec_id long, embedding array<double>, n_links int, component_id int, rep int, vec string")
    out = embedding_dedup.near_vectors(data)
    assert out.columns == ["vec_id", "n_links", "component_id", "kept"]
    got = [(str(x.vec_id), x.n_links, x.component_id, x.kept) for x in out.collect()]
    # Four rows are near a, two near b, one can't link.
    want = [("None", 3, 3, False), ("7", 3, 3, False), ("7", 3, 3, False), ("3", 3, 3, True), ("7", 1, 7, True), ("None", 1, 7, False), ("None", 0, None, True)]
    assert sorted(map(str, got)) == sorted(map(str, want))


def test_recall_at_the_threshold():
    r = np.random.default_rng(6)
    x = r.normal(size=(2000, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    z = r.normal(size=x.shape)
    z -= (z * x).sum(1, keepdims=True) * x
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    y = 0.9 * x + np.sqrt(1 - 0.81) * z
    a, b = embedding_dedup.probe_codes(x), embedding_dedup.probe_codes(y)
    met = (a[:, :, :, None] == b[:, :, None, :]).any((1, 2, 3))
    assert met.mean() >= 0.95
    assert np.allclose(embedding_dedup.hadamard(embedding_dedup.hadamard(x)), x)


@pytest.mark.parametrize("n", [1, 10**6, 10**8])
def test_recall_holds_for_many_vectors(n):
    r = np.random.default_rng(16)
    axes = embedding_dedup.axes_for(n, 64)
    tables = embedding_dedup.tables_for(axes, 64, 0.9)
    x, z = r.normal(size=(2, 3000, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    z -= (z * x).sum(1, keepdims=True) * x
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    y = 0.9 * x + np.sqrt(1 - 0.81) * z
    a, b = (embedding_dedup.probe_codes(v, tables, axes=axes) for v in (x, y))
    met = (a[:, :, :, None] == b[:, :, None, :]).any((1, 2, 3))
    print(axes, tables, met.mean())
    assert met.mean() >= 0.997


# 7
def check_packed(out, texts, tokenizer, limits):
    ids = {i: np.array(tokenizer.encode(t or "", add_special_tokens=False).ids + [0], "<u4") for i, t in texts.items()}
    for i, own in out.groupby("doc_id"):
        own = own.sort_values("start")
        assert own.start.tolist() == np.r_[0, own.length.cumsum()[:-1]].tolist() and own.length.sum() == len(ids[i]) == own.doc_tokens.iloc[0]
        assert own.ids_crc32.tolist() == [zlib.crc32(ids[i][s : s + n].tobytes()) for s, n in zip(own.start, own.length, strict=True)]
    for _, seq in out.groupby("sequence_id"):
        seq = seq.sort_values("offset")
        assert seq.offset.tolist() == np.r_[0, seq.length.cumsum()[:-1]].tolist()
        assert seq.length.sum() <= limits.tokens and len(seq) <= limits.segments and seq.loss_tokens.sum() <= limits.loss


def test_packing(spark, texts, tokenizer):
    df = Q.op7_vector_packing(spark, SF)
    out = df.toPandas()
    assert set(out.doc_id) == set(texts)
    check_packed(out, texts, tokenizer, packing.Limits())
    assert packing.padding(df).first().padding == 0
    short = spark.createDataFrame([(i, "a b") for i in range(3000)], "doc_id long, text string")  # the segment limit closes these
    assert packing.padding(packing.pack_texts(short, BYTES)).first().padding == 0


def test_packing_under_three_limits(spark, docs, texts, tokenizer):
    limits = packing.Limits(512, 3, 200)
    pieces = packing.pack_texts(docs.withColumn("prompt", F.lit("Say this:")), BYTES, limits, prompt_col="prompt").toPandas()
    n = len(tokenizer.encode("Say this:", add_special_tokens=False).ids)
    assert pieces.loss_tokens.sum() == pieces.length.sum() - n * len(texts)
    seq = pieces.groupby("sequence_id").agg(tokens=("length", "sum"), loss=("loss_tokens", "sum"), segments=("length", "size"))
    assert seq.tokens.max() <= 512 and seq.loss.max() <= 200 and seq.segments.max() <= 3
    with pytest.raises(ValueError):
        packing.Limits(0)


def place_by_hand(examples, limits, slots=packing.WINDOW):
    """(key, start, length) of each sequence in order: an open sequence, slot by slot, always the largest dot product."""
    waiting, free, done = {}, list(range(slots)), []
    cap = (limits.tokens, limits.segments, limits.loss)

    def demand(p):
        key, start, n, prompt = p
        return n, 1, sum(1 for i in range(start, start + n) if i >= prompt)

    def longest(p, room):
        key, start, n, prompt = p
        while n and any(a > b for a, b in zip(demand((key, start, n, prompt)), room)):
            n -= 1
        return n

    def fill():
        room, pieces = list(cap), []
        while min(room) >= 1 and waiting:
            value = {s: sum(d / c * r / c for d, r, c in zip(demand(p), room, cap)) for s, p in waiting.items()}
            fitting = [s for s, p in waiting.items() if all(d <= r for d, r in zip(demand(p), room))]
            s = max(fitting or waiting, key=lambda s: (round(value[s], 12), -s))
            key, start, n, prompt = waiting[s]
            take = n if fitting else longest(waiting[s], room)
            if not take:
                break
            if take == n:
                del waiting[s]
                free.append(s)
            else:
                waiting[s] = (key, start + take, n - take, prompt)
            pieces.append((key, start, take, prompt))
            room = [r - d for r, d in zip(room, demand(pieces[-1]))]
        done.append([p[:3] for p in pieces])

    for key, length, prompt in examples:
        at = 0
        while at < length:
            n = longest((key, at, length - at, prompt), cap)
            if n == limits.tokens:
                done.append([(key, at, n)])
            else:
                if not free:
                    fill()
                waiting[free.pop()] = (key, at, n, prompt)
            at += n
    while waiting:
        fill()
    return done


def test_placement_is_that_of_the_heuristic(monkeypatch):
    monkeypatch.setattr(packing, "WINDOW", 12)
    r = random.Random(5)
    limits = packing.Limits(40, 4, 22)
    examples = [(k, r.randint(1, 60), r.randint(0, 30)) for k in range(150)]
    packer = packing.Packer(limits)
    for key, length, prompt in examples:
        packer.add(key, length, prompt)
    packer.finish()
    by = {}
    for key, start, n, sequence, offset in packer.placed():
        by.setdefault(sequence, []).append((offset, key, start, n))
    rows_ = [(k, s, n) for q in sorted(by) for _, k, s, n in sorted(by[q])]
    # A sequence that is not full is cut into powers of two afterwards, which may cut a piece, but keeps their order.
    whole = []
    for k, s, n in rows_:
        if whole and whole[-1][0] == k and whole[-1][1] + whole[-1][2] == s:
            whole[-1] = (k, whole[-1][1], whole[-1][2] + n)
        else:
            whole.append((k, s, n))
    want = []
    for k, s, n in (p for seq in place_by_hand(examples, limits, 12) for p in seq):
        if want and want[-1][0] == k and want[-1][1] + want[-1][2] == s:
            want[-1] = (k, want[-1][1], want[-1][2] + n)
        else:
            want.append((k, s, n))
    assert whole == want
    lengths = [sum(n for _, _, _, n in by[q]) for q in by]
    assert all(n == 40 or n & (n - 1) == 0 for n in lengths)


def test_instruction_data_meets_all_three_limits(spark, tokenizer):
    turns = table(spark, SF, "conversations")
    examples = packing.instruction_examples(turns)
    limits = packing.Limits(256, 6, 120)
    out = packing.pack_texts(examples, BYTES, limits, prompt_col="prompt").toPandas()
    said = {(r.conv_id, r.turn): r for r in turns.collect()}
    want = {r.doc_id: (r.prompt, r.text) for r in examples.collect()}
    assert len(want) == sum(r.role == "assistant" for r in said.values())
    for r in examples.collect():
        before = said.get((r.conv_id, r.turn - 1))
        assert r.text == said[r.conv_id, r.turn].text and (before is None or r.prompt == before.text)
    size = lambda t: len(tokenizer.encode(t or "", add_special_tokens=False).ids)
    for i, own in out.groupby("doc_id"):
        prompt, text = want[i]
        assert own.length.sum() == own.doc_tokens.iloc[0] == size(prompt) + size(text) + 1 and own.loss_tokens.sum() == size(text) + 1
    seq = out.groupby("sequence_id").agg(tokens=("length", "sum"), loss=("loss_tokens", "sum"), segments=("length", "size"))
    assert (seq.tokens.max(), seq.segments.max(), seq.loss.max()) <= (256, 6, 120) and (seq.tokens <= 256).all() and (seq.loss <= 120).all() and (seq.segments <= 6).all()

    def bins(limits):
        packer = packing.Packer(limits)
        for k, (prompt, text) in enumerate(sorted(want.values(), key=str)):
            packer.add(k, size(prompt) + size(text) + 1, size(prompt))
        packer.finish()
        return packer.bins

    # Each limit binds: without it fewer bins are needed.
    base, free = (256, 2, 150), 10**6
    assert all(bins(packing.Limits(*[free if i == k else x for i, x in enumerate(base)])) < bins(packing.Limits(*base)) for k in range(3))


def test_packing_awkward(awkward):
    out = packing.pack_texts(awkward, BYTES).toPandas()
    assert (out.length > 0).all() and out[out.start == 0].shape[0] == awkward.count()


# 9
def test_lm_scores_by_hand(spark, docs, texts):
    good = {r.doc_id for r in table(spark, SF, "labels").where("quality = 1").collect()}
    words, pairs = np.zeros((2, lm_scoring.WORDS)), np.zeros((2, lm_scoring.PAIRS))
    for i, t in texts.items():
        w, _, p = lm_scoring.slots(lm_scoring.codes(t))
        np.add.at(words[int(i in good)], w, 1)
        np.add.at(pairs[int(i in good)], p, 1)
    m = lm_scoring.Models(words, pairs)
    out = {r.doc_id: r for r in Q.op9_lm_scoring(spark, SF).collect()}
    for i, t in list(texts.items())[:60]:
        c = lm_scoring.codes(t)
        a, b = m.losses(c, int(i in good))
        assert out[i].score == pytest.approx((a - b) / max(len(c), 1)) and out[i].is_target == (i in good)


def test_lm_awkward(spark, awkward, empty):
    good = spark.createDataFrame([(3,), (None,), (3,)], "doc_id long")
    out = lm_scoring.score_documents(awkward, good)
    assert out.count() == awkward.count() and out.where("score is null or isnan(score)").count() == 0
    assert lm_scoring.score_documents(awkward, good.where("false")).where("isnan(score)").count() == 0
    assert lm_scoring.score_documents(empty, good).count() == 0


def test_lm_counts_every_word_and_pair(spark, monkeypatch):
    """Against models of dictionaries without hashing, on more different words and pairs than 2^18."""
    monkeypatch.setattr(lm_scoring, "CHUNK_BYTES", 300_000, raising=False)
    monkeypatch.setattr(lm_scoring, "SHARD_BYTES", 600_000, raising=False)
    r = np.random.default_rng(7)
    texts = [" ".join(f"w{x}" for x in np.r_[np.arange(700) + 700 * i, r.integers(0, 3000, 300), r.zipf(1.5, 200) % 90].tolist()) + ("" if i % 3 else " end w1 end") for i in range(420)]
    data = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = {x.doc_id: x for x in lm_scoring.score_documents(data, data.where("doc_id % 4 = 0").select("doc_id")).collect()}
    words, pairs = [Counter(), Counter()], [Counter(), Counter()]
    for i, t in enumerate(texts):
        w = t.split()
        words[i % 4 == 0].update(w)
        pairs[i % 4 == 0].update(zip(w, w[1:]))
    total, size = [c.total() for c in words], len(words[0] | words[1])
    assert size > 1 << 18 and len(out) == len(texts)
    for i in range(0, len(texts), 7):
        w, loss = texts[i].split(), []
        own_w, own_p = Counter(w), Counter(zip(w, w[1:]))
        for m in (1, 0):
            mine, s, x = m == (i % 4 == 0), 1 if m else total[1] / total[0], 0.0
            for k, word in enumerate(w):
                one = (s * (words[m][word] - mine * own_w[word]) + 0.1) / (s * (total[m] - mine * len(w)) + 0.1 * size)
                pair, b = (w[k - 1], word), w[k - 1]
                x -= np.log((s * (pairs[m][pair] - mine * own_p[pair]) + 16 * one) / (s * (words[m][b] - mine * own_w[b]) + 16) if k else one)
            loss.append(x / len(w))
        assert (out[i].target_loss, out[i].background_loss) == pytest.approx(tuple(loss), rel=1e-9)


# 10
def fingerprint_by_hand(t):
    import xxhash

    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    if not words:
        return 0
    hs = [xxhash.xxh64_intdigest(" ".join(words[i : i + 4]).encode(), 42) for i in range(max(1, len(words) - 3))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def groups_by_hand(fps, radius=4):
    a, label = np.array(fps, np.uint64), np.arange(len(fps))
    for i in range(len(a)):
        for j in np.flatnonzero(np.bitwise_count(a ^ a[i]) <= radius):
            x, y = label[i], label[j]
            if x != y:
                label[label == max(x, y)] = min(x, y)
    return label


def test_simhash(spark, texts):
    ids = sorted(texts)
    fps = [fingerprint_by_hand(texts[i]) for i in ids]
    out = {r.doc_id: r for r in Q.op10_simhash(spark, SF).collect()}
    assert [out[i].fingerprint for i in ids] == [f"{f:016x}" for f in fps]
    assert [out[i].component_id for i in ids] == [ids[k] for k in groups_by_hand(fps)]


def test_bit_slices_equal_distances():
    r = np.random.default_rng(8)
    base = r.integers(0, 2**63, 5, dtype=np.uint64)
    fps = np.array([b ^ np.bitwise_or.reduce(np.uint64(1) << r.integers(0, 64, k).astype(np.uint64)) if k else b for b in base for k in r.integers(0, 9, 60)], np.uint64)
    for radius in (0, 1, 3, 4, 7):
        q, k = simhash.within(simhash.planes_of(fps), len(fps), fps, radius)
        want = np.argwhere(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= radius)
        assert sorted(zip(q.tolist(), k.tolist(), strict=True)) == sorted(map(tuple, want.tolist()))


@pytest.mark.parametrize("n", [100, 10**7, 10**10, 10**12])
def test_every_scheme_finds_every_link(spark, n, monkeypatch):
    monkeypatch.setattr(simhash, "ROWS", 30)
    r = np.random.default_rng(9)
    base = r.integers(0, 2**63, 4, dtype=np.uint64)
    fps = np.unique(np.array([b ^ np.bitwise_xor.reduce(np.uint64(1) << r.integers(0, 64, k).astype(np.uint64)) for b in base for k in r.integers(1, 8, 40)], np.uint64))
    df = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    found = {r.node: r.component for r in components(simhash.fingerprint_links(df, n, 4)).collect()}
    label = groups_by_hand(fps)
    mine = [found.get(int(x), int(x)) for x in fps.view(np.int64)]
    assert len(set(mine)) == len(set(label)) == len(set(zip(mine, label.tolist(), strict=True)))


def test_simhash_awkward(spark, awkward, empty):
    assert simhash.groups(awkward).count() == awkward.count()
    kept = simhash.near_duplicates_removed(awkward).collect()
    ids = [r.doc_id for r in kept]
    # Id 0 has two texts, which stand for two groups.
    assert ids.count(None) == 1 and ids.count(0) == 2 and 4 not in ids and ids.count(3) == 1
    assert simhash.near_duplicates_removed(empty).count() == simhash.groups(empty).count() == 0


def test_components(spark):
    r = random.Random(3)
    edges = [(i, i + 1) for i in range(300) if i % 50 != 49] + [(5, 5), (400, 7), (None, 3)]
    r.shuffle(edges)
    got = {x.node: x.component for x in components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert all(got[i] == i // 50 * 50 for i in range(300)) and got[400] == 0
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0


# The pipeline
def test_pipeline(spark, docs, texts, tokenizer, tmp_path):
    import corpus_pipeline as c

    stages = dict(c.STAGES)
    labels = table(spark, SF, "labels")
    one = stages["quality_classifier"](spark, docs, SF)
    one.write.parquet(f"{tmp_path}/1")
    one = spark.read.parquet(f"{tmp_path}/1")
    good = {r.doc_id for r in labels.where("quality = 1").collect()}
    kept = {r.doc_id for r in one.collect()}
    assert len(good & kept) >= 0.95 * len(good & set(texts))
    two = stages["quality_rules"](spark, one, SF)
    assert two.columns == docs.columns
    two.write.parquet(f"{tmp_path}/2")
    two = spark.read.parquet(f"{tmp_path}/2")
    three = stages["line_dedup"](spark, two, SF)
    want = dedup_by_hand((r.doc_id, r.text) for r in two.collect())
    assert {r.doc_id: r.text for r in three.collect()} == {i: t for i, (t, _) in want.items()} and three.columns == docs.columns
    assert three.where("n_chars <> length(text)").count() == 0
    three.write.parquet(f"{tmp_path}/3")
    three = spark.read.parquet(f"{tmp_path}/3")
    four = stages["simhash_near_dedup"](spark, three, SF)
    own = {r.doc_id: r.text for r in three.collect()}
    left = {r.doc_id: r.text for r in four.collect()}
    assert left == {i: own[i] for i in similar_by_hand(own)} and four.columns == docs.columns
    check_packed(stages["packing"](spark, four, SF).toPandas(), left, tokenizer, packing.Limits())


def similar_by_hand(texts):
    """Smallest id of each group that pairs of a similarity of 0.8 or more make up, shingles being five words."""
    words = {i: WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or "")) for i, t in texts.items()}
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set() for i, w in words.items()}
    label, by = {i: i for i in texts}, {}
    for i in sorted(texts):
        for s in sets[i] or {None}:
            by.setdefault(s, []).append(i)
    for pair in {(a, b) for ids in by.values() for k, a in enumerate(ids) for b in ids[k + 1 :]}:
        a, b = (sets[x] for x in pair)
        x, y = (label[i] for i in pair)
        if x != y and len(a & b) >= 0.8 * len(a | b):
            label = {i: min(x, y) if v in (x, y) else v for i, v in label.items()}
    return set(label.values())


@pytest.mark.parametrize("n", [1, 10**7, 10**11])
def test_wide_fingerprints_meet(n):
    """At the very similarity: within the radius, and in a bucket of some table."""
    r = np.random.default_rng(31)
    axes, tables = simhash.bucket_plan(n, 0.8)
    sums = []
    for k in range(300):
        m = 5 * int(r.integers(2, 80))  # of 10 parts 8 are common, and each has one of its own
        x = r.integers(0, 2**64, 10 * m, dtype=np.uint64)
        sums.append((simhash.wide_sums(x[: 9 * m]), simhash.wide_sums(np.r_[x[: 8 * m], x[9 * m :]])))
    near = [int(np.bitwise_count(simhash.wide_fingerprint(a) ^ simhash.wide_fingerprint(b)).sum()) <= simhash.radius_for(0.8) for a, b in sums]
    codes = [simhash.probe_codes(np.array([simhash.rounded(s[k]) for s in sums], float), tables, simhash.PROBES, axes) for k in (0, 1)]
    met = (codes[0][:, :, :, None] == codes[1][:, :, None, :]).any((1, 2, 3))
    assert sum(near) >= 297 and met.mean() >= 0.96
    assert tables * simhash.PROBES <= 100  # buckets of a text, for any corpus


@pytest.mark.parametrize("size", [20, 4000])
def test_near_copies_of_similarity_08(spark, monkeypatch, size):
    import corpus_pipeline as c

    monkeypatch.setattr(simhash, "ROWS", size)
    monkeypatch.setattr(simhash, "SETS", size)
    r = np.random.default_rng(12)
    texts = []
    for _ in range(25):
        base = r.integers(0, 10**6, 300)
        texts.append(base)
        for n in (1, 3, 5, 12):  # words that are changed
            x = base.copy()
            x[r.choice(300, n, replace=False)] = r.integers(10**6, 2 * 10**6, n)
            texts.append(x)
    base = r.integers(0, 10**6, 300)
    texts += [np.r_[base[:-1], k] for k in range(60)]
    texts = [" ".join(f"w{x}" for x in t.tolist()) for t in texts]
    left = {x.doc_id for x in dict(c.STAGES)["simhash_near_dedup"](spark, spark.createDataFrame(rows(texts), SCHEMA), SF).collect()}
    assert left == similar_by_hand(dict(enumerate(texts))) and 26 < len(left) < 80


def test_pipeline_stages_awkward(spark, awkward, empty):
    import corpus_pipeline as c

    for name, stage in c.STAGES:
        out = stage(spark, awkward, SF)
        out.count()
        if name != "packing":
            assert out.columns == awkward.columns
        assert stage(spark, empty, SF).count() == 0
