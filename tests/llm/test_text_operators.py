"""Text operators against brute force, exact round trips and held-out accuracy, with nulls, empty and long texts, ties, repeats and empty tables."""

import hashlib
import re
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from retro.llm.bpe import ByteBpe, WordBpe, runs
from retro.llm.jaccard_join import COARSE, FINE, JaccardJoin, Sketches
from retro.llm.language_id import LanguageId
from retro.llm.packing import VectorBestFit
from retro.llm.quality import Quality
from retro.llm.runtime import components, fold
from retro.llm.token_codec import decoded, encoded, round_trip_digest
from retro.llm.token_files import Segment, TokenFiles, pack, segment, unpack
from retro.llm.toxicity import Toxicity

SF = "/root/testdata/sf0.001"
WORDS, BYTES = (public_tokenizers.path(n) for n in ("word_bpe_49k.json", "byte_bpe_50k.json"))
ODD = [None, "", " ", "\n\t ", "a", "it's I'LL don't 's", "ΣΑΣ İ é ﬁ ½ 漢字 😀", "<|endoftext|> x", "\x1cab\x1d \x00", "  two  spaces \n\nlines\n", "aaaa " * 400, "x" * 5000, "1234567 !!??--", "tail "]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, score double, ids string"


def table(spark, texts, schema=SCHEMA):
    """A documents table with columns whose names clash with those that operators make."""
    return spark.createDataFrame([(k, t, None, None, None, None, None) for k, t in enumerate(texts)], schema)


# ---- tokens ----------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def coders():
    out = []
    for kind, path in ((WordBpe, WORDS), (ByteBpe, BYTES)):
        source = open(path, encoding="utf-8").read()
        for speculate in (True, False):
            coder = kind(source)
            coder.speculate = speculate
            out.append((coder, Tokenizer.from_str(source)))
    return out


def thue_morse(n):
    """The 0/1 Thue-Morse word of n letters, in letters a and b, and its complement."""
    bits = [k.bit_count() % 2 for k in range(n)]
    return "".join("ab"[b] for b in bits), "".join("ba"[b] for b in bits)


def same(coders, texts):
    for coder, library in coders:
        got = [x for a, b in runs(texts, 50) for x in coder.encode(texts[a:b])]
        assert got == [np.array(e.ids, "<u4").tobytes() for e in library.encode_batch(texts, add_special_tokens=False)]
        assert coder.encode([]) == []


def test_encoding_equals_the_library(coders):
    same(coders, [t or "" for t in ODD])


def test_encoding_of_regular_words_equals_the_library(coders):
    """Words whose polynomial hashes meet, words of repeated blocks, and pieces that a full memory has forgotten."""
    texts = [*(w for n in (1024, 2048, 4096, 8192) for w in thue_morse(n)), *("ab" * n + "ba" * n for n in (512, 1024)), *("ba" * n + "ab" * n for n in (512, 1024))]
    same(coders, texts)
    for coder, _ in coders:
        coder.remember = 4
    same(coders, [*texts, *texts[::-1]])
    for coder, _ in coders:
        del coder.remember
        assert coder.remember == type(coder).remember


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet=st.sampled_from(list("ab cd'stlleréñ\n\t!?.,12ΣσB́ 日")), max_size=60), max_size=8))
def test_encoding_equals_the_library_on_random_texts(coders, texts):
    same(coders, texts)


def test_round_trip_digest(spark):
    docs = table(spark, ODD)
    library = Tokenizer.from_file(WORDS)
    for r in round_trip_digest(docs, WORDS).collect():
        ids = library.encode(ODD[r.doc_id] or "", add_special_tokens=False).ids
        assert (r.n_tokens, r.ids_sha256) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
        assert r.decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    back = {r.doc_id: r.text for r in decoded(encoded(docs, WORDS), WORDS).collect()}
    assert back[0] == "" and len(back) == len(ODD)
    assert round_trip_digest(docs.limit(0), WORDS).count() == 0


@given(st.integers(1, 20), st.lists(st.integers(0, 1 << 20), max_size=300))
def test_bit_packing_round_trip(bits, values):
    ids = np.array([v % (1 << bits) for v in values], dtype=np.uint32)
    assert unpack(pack(ids, bits), bits, len(ids)).tolist() == ids.tolist()


def test_segment_random_access():
    ids = np.arange(10_000, dtype=np.uint32) % 1500
    s = Segment(segment(np.array([5, 9]), np.array([4000, 6000]), ids, 11, 3))
    assert (s.bits, s.position, s.doc_ids.tolist()) == (11, 3, [5, 9])
    for a, b in ((0, 10_000), (4095, 4097), (9999, 10_000), (7, 7)):
        assert s.ids(a, b).tolist() == ids[a:b].tolist()


def test_token_files(spark):
    docs = table(spark, ODD).unionByName(spark.createDataFrame([(None, "no id", None, None, None, None, None)], SCHEMA))
    files = TokenFiles(WORDS, end_id=1, segment_ids=200, file_bytes=3000)
    library, start = Tokenizer.from_file(WORDS), 0
    rows = {r.doc_id: r for r in files.digest(docs).collect()}
    assert len(rows) == len(ODD)
    for k, t in enumerate(ODD):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 1]
        assert (rows[k].start, rows[k].n_tokens, rows[k].ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert files.digest(docs.limit(0)).count() == 0


# ---- packing ---------------------------------------------------------------------------------------------------------


@settings(max_examples=80, deadline=None)
@given(st.lists(st.integers(1, 40), min_size=1, max_size=80), st.sampled_from(["norm", "dot"]), st.sampled_from([None, 3]), st.sampled_from([None, 600]))
def test_best_fit_respects_every_constraint(lengths, score, documents, attention):
    if attention and max(lengths) ** 2 > attention:
        lengths = [min(x, 24) for x in lengths]
    histogram = {x: lengths.count(x) for x in set(lengths)}
    bins: dict[int, list[tuple[int, int]]] = {}
    for length, a, b, first, each, offset in VectorBestFit(40, documents, attention, score).runs(histogram):
        for r in range(a, b):
            bins.setdefault(first + (r - a) // each, []).append((offset + length * ((r - a) % each), length))
    assert sorted(x for b in bins.values() for _, x in b) == sorted(lengths)
    for b in bins.values():
        at = 0
        for offset, length in sorted(b):
            assert offset == at
            at += length
        assert at <= 40 and len(b) <= (documents or 40) and (not attention or sum(x * x for _, x in b) <= attention)
    if not documents and not attention and score == "norm":
        # at most what best fit decreasing, one piece at a time, takes
        plain: list[int] = []
        for x in sorted(lengths, reverse=True):
            fit = [k for k, left in enumerate(plain) if left >= x]
            k = min(fit, key=lambda j: plain[j]) if fit else len(plain)
            plain[k : k + 1] = [(plain[k] if fit else 40) - x]
        assert len(bins) <= len(plain)


def test_packing_of_documents(spark):
    texts = [*ODD, "one two three " * 900, *["copy of a text"] * 30]
    library = Tokenizer.from_file(BYTES)
    rows = VectorBestFit(capacity=256).pack(table(spark, texts).repartition(5), BYTES, 2).collect()
    by_doc, by_bin = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_bin.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for k, t in enumerate(texts):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 2]
        pieces = sorted(by_doc[k], key=lambda r: r.piece)
        assert [p.piece for p in pieces] == list(range(len(pieces))) and sum(p.length for p in pieces) == len(ids)
        assert all(p.length == 256 for p in pieces[1:])
        for p in pieces:
            assert p.ids_crc32 == zlib.crc32(np.array(ids[p.start : p.start + p.length], "<u4").tobytes())
    for b in by_bin.values():
        ends = [o + n for o, n in sorted(b)]
        assert [o for o, _ in sorted(b)] == [0, *ends[:-1]] and ends[-1] <= 256
    assert VectorBestFit().pack(table(spark, []), BYTES, 2).count() == 0


# ---- near duplicates -------------------------------------------------------------------------------------------------


def brute_components(texts):
    sets = {}
    for k, t in enumerate(texts):
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate({i: i + 32 for i in range(65, 91)}))
        sets[k] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in sets:
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {k: (len(s), find(k)) for k, s in sets.items()}


def near_copies(seed=3):
    """Groups whose pairs lie about the threshold, chains, tiny texts, exact copies in other cases, shared passages."""
    rng = np.random.default_rng(seed)
    words = [f"w{k}" for k in range(4000)]
    draw = lambda n: [words[k] for k in rng.integers(0, len(words), n)]
    out = [None, "", " \t", "One", "one", "a b c d", "A B c d", "a b c d e", "a b c d e f"]
    passage = draw(60)
    for _ in range(8):
        base = draw(int(rng.integers(5, 150)))
        for _ in range(int(rng.integers(2, 9))):
            copy = list(base)
            for _ in range(int(rng.integers(0, 1 + len(base) // 25))):
                copy[int(rng.integers(0, len(copy)))] = words[int(rng.integers(0, len(words)))]
            out.append(" ".join(copy if rng.random() < 0.7 else [w.upper() for w in copy]))
    for _ in range(14):
        out.append(" ".join(passage + draw(int(rng.integers(8, 80)))))
    return out


@pytest.mark.parametrize("options", [{}, {"work": 0, "pivots": 2, "members": 3}, {"crowd": 3, "work": 30, "broadcast_rows": 0}, {"effort": 1, "entries": 50}])
def test_jaccard_join_equals_brute_force(spark, options):
    texts = near_copies()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in JaccardJoin(**options).join(table(spark, texts).repartition(4)).collect()}
    assert got == brute_components(texts)


def test_jaccard_join_edges(spark):
    join = JaccardJoin()
    assert join.join(table(spark, [])).count() == 0
    assert {tuple(r) for r in join.join(table(spark, [None, ""])).collect()} == {(0, 0, 0), (1, 0, 1)}
    twice = table(spark, ["a b c d e f g", "a b c d e f g"]).unionByName(table(spark, ["a b c d e f g"]))
    assert sorted(tuple(r) for r in join.join(twice).collect()) == [(0, 3, 0), (0, 3, 0), (1, 3, 0)]


def test_jaccard_pivots_and_windows_take_documents():
    """Pivots take what may link with them; that and what is in the window of a live pivot stays; a spent effort leaves the untaken."""
    join, base = JaccardJoin(), np.arange(1000, dtype=np.uint64)
    # near the base; in its window only; unrelated; near the unrelated one
    sets = [base, base[:950], base[:690], base + np.uint64(10**6), base[:960] + np.uint64(10**6)]
    held = Sketches()
    for k, s in enumerate(sets):
        held.add(np.array([k], np.uint64), np.array([len(s)]), join.sketch(s))
    held.finished()
    one = np.zeros(5, np.int64)
    a, p, stay = join.taken(one, np.arange(5), held)
    assert set(zip(p.tolist(), a.tolist(), strict=True)) == {(0, 1), (3, 4)} and stay.tolist() == [False, True, True, False, True]
    _, _, stay = JaccardJoin(effort=5).taken(one, np.arange(5), held)
    assert stay[3] and stay[4]


def test_first_level_names_pivots_on_the_given_tables(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    join = JaccardJoin()
    classes = join.sizes(docs).where("n_shingles > 0").groupBy("f1", "n_shingles").agg(F.first("sketch").alias("sketch"))
    got = join.regions(docs, classes, 8)
    assert got.where("pivot is not null").count() > 0 and got.where("pivot is null").count() > 0


def test_words_of_equal_polynomial_hashes_stay_apart(spark):
    """Thue-Morse words and their complements meet under any polynomial modulo a power of two."""
    texts = [" ".join((*"wxyz", w)) for n in (1024, 2048, 8192) for w in thue_morse(n)]
    got = JaccardJoin().join(table(spark, texts)).collect()
    assert {r.component_id for r in got} == set(range(len(texts)))


def test_every_linked_pair_shares_a_region():
    """In any order by counts, and a region whose befores differ; the sketches' bound never exceeds the difference."""
    rng, join = np.random.default_rng(5), JaccardJoin()
    for _ in range(300):
        n = int(rng.integers(1, 400))
        base = rng.integers(0, 1 << 62, n, dtype=np.uint64)
        gone = int(rng.integers(0, n // 9 + 2))
        other = np.concatenate([base[gone:], rng.integers(0, 1 << 62, int(rng.integers(0, n // 9 + 2)), dtype=np.uint64)])
        a, b = np.unique(base), np.unique(other)
        if not len(b):
            continue
        shared = np.intersect1d(a, b)
        if join.linked(len(shared), len(a) + len(b) - len(shared)):
            # what both hold is shared; so is some of what only one holds, with other documents
            extra = [np.setdiff1d(x, shared) for x in (a, b)]
            extra = [x[rng.random(len(x)) < 0.5] for x in extra]
            own = [np.union1d(shared, x) for x in extra]
            region, owner = np.concatenate(own), np.repeat([0, 1], [len(x) for x in own])
            count = np.searchsorted(np.unique(region), region) % 7 + 2
            keep, before, order = join.prefix(owner, region, count, np.array([len(a), len(b)]), np.array([1, 2], np.uint64))
            region, owner, before = region[order][keep], owner[order][keep], before[keep]
            common, i, j = np.intersect1d(region[owner == 0], region[owner == 1], return_indices=True)
            assert len(common) and (before[owner == 0][i] != before[owner == 1][j]).any()
            for density in (COARSE, FINE):
                held = Sketches(density)
                for k, s in enumerate((a, b)):
                    held.add(np.array([k], np.uint64), np.array([len(s)]), join.sketch(s, density))
                held.finished()
                assert held.least(np.array([0]), np.array([1]))[0] <= len(a) + len(b) - 2 * len(shared)


@pytest.mark.parametrize("alone", [0, 1000])
def test_components(spark, alone):
    edges = [(1, 2), (3, 2), (10, 11), (11, 12), (12, 13), (13, 14), (20, 20), (5, 9), (9, 5)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long"), alone).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 10: 10, 11: 10, 12: 10, 13: 10, 14: 10, 5: 5, 9: 5}


# ---- classifiers -----------------------------------------------------------------------------------------------------


def test_language_on_held_out_rows_and_odd_texts(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").withColumn("score", F.lit("clash"))
    model = LanguageId(per_language=200).fit(docs, fold("doc_id", 3) != 1)
    out = model.predict(docs).join(docs.select("doc_id", "lang"), "doc_id").where(fold("doc_id", 3) == 1).collect()
    assert np.mean([r.lang == r.lang_pred for r in out]) >= 0.9 and all(0 <= r.score <= 1 for r in out)
    rows = {r.doc_id: r for r in model.predict(table(spark, ODD)).collect()}
    assert len(rows) == len(ODD) and all(rows[k].lang_pred == "und" and rows[k].rejected and rows[k].score == 0 for k in (0, 1, 2, 3, 12))
    assert model.accepted(docs).count() >= 0.97 * docs.count() and model.accepted(docs).columns == docs.columns
    none = LanguageId().fit(table(spark, []), F.lit(True))
    assert {r.lang_pred for r in none.predict(table(spark, ODD)).collect()} == {"und"}


@pytest.mark.parametrize("junk", [[], ["", "123 -- 456", None], ["ξψχω " * 30], ["", "ξψχω " * 30]])
def test_junk_among_learning_texts_does_not_lift_the_limit(spark, junk):
    rng = np.random.default_rng(3)
    pools = {"aa": ["house", "river", "stone", "under", "bright", "morning", "walked", "slowly"], "bb": ["maison", "fleuve", "pierre", "sous", "clair", "matin", "marchait", "doucement"]}
    rows = [(100 * i + k, " ".join(rng.choice(pool, 30)), lang) for i, (lang, pool) in enumerate(pools.items()) for k in range(60)]
    rows += [(900 + k, text, "aa") for k, text in enumerate(junk)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = LanguageId().fit(docs, F.lit(True))
    assert (model.limit < 0.9).all()
    asked = spark.createDataFrame([(1, "ξψχω " * 20), (2, "漢字仮名" * 30), *((3 + i, " ".join(rng.choice(pool, 20))) for i, pool in enumerate(pools.values()))], "doc_id long, text string")
    assert {r.doc_id: r.rejected for r in model.predict(asked).collect()} == {1: True, 2: True, 3: False, 4: False}


def toxic_texts(spark, n=400):
    rng = np.random.default_rng(1)
    words = [f"w{k}" for k in range(300)]
    texts = [" ".join(words[k] for k in rng.integers(0, 300, 40)) for _ in range(n)]
    labels = [(k, int(k % 5 == 0)) for k in range(n)]
    texts = [t + (" you scum loser" if k % 5 == 0 else "") for k, t in enumerate(texts)]
    return table(spark, texts), spark.createDataFrame([*labels, (3, None), (None, 1), (7, 9)], "doc_id long, label int")


def test_toxicity(spark):
    docs, labels = toxic_texts(spark)
    model = Toxicity().fit(docs, labels, fold("doc_id", 3) != 1)
    out = {r.doc_id: r for r in model.predict(docs).collect()}
    held = [k for k in out if zlib.crc32(str(k).encode()) % 3 == 1]
    assert all(out[k].predicted == int(k % 5 == 0) for k in held) and len(model.at) < 2000
    assert {r.doc_id for r in model.accepted(docs).collect()} == {k for k in out if not out[k].predicted}
    odd = model.predict(table(spark, ODD)).collect()
    assert len(odd) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in odd)
    one = Toxicity().fit(docs, labels.where("label = 0"), F.lit(True))
    assert all(r.score < 1e-6 for r in one.predict(docs).collect())
    assert Toxicity().fit(docs, labels.limit(0), F.lit(True)).predict(docs).where("predicted = 1").count() == 0


def test_quality(spark):
    rng = np.random.default_rng(2)
    good = [" ".join(f"{'abcdefghij'[k % 10] * (1 + k % 7)}{k}" for k in rng.integers(0, 900, 60)) + ".\nEnd." for _ in range(150)]
    junk = [("BUY NOW!! " * int(rng.integers(20, 60))) for _ in range(60)]
    docs = table(spark, good + junk)
    labels = spark.createDataFrame([(k, int(k < 150)) for k in range(210)] + [(1, None)], "doc_id long, label int")
    model, scores = Quality().fit_predict(docs, labels, fold("doc_id", 4) != 2)
    out = {r.doc_id: r for r in scores.collect()}
    held = [k for k in out if zlib.crc32(str(k).encode()) % 4 == 2]
    assert np.mean([out[k].predicted == int(k < 150) for k in held]) >= 0.95
    odd = model.predict(Quality().statistics(table(spark, ODD))).collect()
    assert len(odd) == len(ODD) and all(0 <= r.score <= 1 for r in odd)
    # moments summed over partitions give the same model as all rows at once
    x = {r.doc_id: np.array(r.x, float) for r in Quality().statistics(docs).collect()}
    learn = [k for k in x if zlib.crc32(str(k).encode()) % 4 != 2 and k >= 150]
    assert np.allclose(model.mean[0], np.mean([x[k] for k in learn], axis=0))
    assert Quality().fit_predict(docs, labels.limit(0), F.lit(True))[1].where("predicted = 1").count() == 0


# ---- classifiers against their plain formulas --------------------------------------------------------------------------


def labelled(spark, column):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text", "lang")
    labels = spark.read.parquet(f"{SF}/labels.parquet").select("doc_id", F.col(column).alias("label"))
    return docs, labels


def test_quadratic_scores_equal_the_plain_formula(spark):
    docs, labels = labelled(spark, "quality")
    x = Quality().statistics(docs)
    model = Quality().fit(x, labels, F.lit(True))
    rows = {r.doc_id: np.array(r.x, dtype=float) for r in x.collect()}
    known = {r.doc_id: r.label for r in labels.collect() if r.doc_id in rows}
    own = [np.stack([rows[k] for k, v in known.items() if v == c]) for c in (0, 1)]
    cov, n, d = [np.cov(o.T, bias=True) for o in own], [len(o) for o in own], len(next(iter(rows.values())))
    pooled = (cov[0] * n[0] + cov[1] * n[1]) / sum(n)

    def density(v, c):
        share = max(0.1, min(1.0, d / n[c]))
        s = (1 - share) * cov[c] + share * pooled
        s = 0.95 * s + 0.05 * np.diag(np.diag(s)) + 1e-4 * np.eye(d)
        gap = v - own[c].mean(axis=0)
        return -0.5 * (gap @ np.linalg.solve(s, gap) + np.linalg.slogdet(s)[1])

    for r in model.predict(x).collect():
        odds = np.log(n[1] / n[0]) + density(rows[r.doc_id], 1) - density(rows[r.doc_id], 0)
        assert abs(r.score - 1 / (1 + np.exp(-np.clip(odds, -30, 30)))) < 1e-4


def test_ftrl_weights_equal_the_scalar_algorithm(spark):
    from retro.llm.toxicity import features_of
    from retro.llm.vector_text import mix64, utf8_view

    docs, labels = labelled(spark, "toxic")
    model = Toxicity(bits=12, passes=2, l1=0.5).fit(docs, labels, F.lit(True))
    known = {r.doc_id: r.label for r in labels.collect()}
    texts = {r.doc_id: r.text or "" for r in docs.collect() if r.doc_id in known}
    ids = np.array(sorted(texts))
    order = ids[np.argsort(mix64(ids.astype(np.uint64)), kind="stable")].tolist()
    z, n, z0, n0 = {}, {}, 0.0, 0.0
    many = {v: sum(known[k] == v for k in texts) for v in (0, 1)}
    total = {v: sum(x == v for x in known.values()) for v in (0, 1)}
    part = {v: total[v] / sum(total.values()) * len(texts) / many[v] for v in (0, 1)}
    weight = lambda k: 0.0 if abs(z.get(k, 0.0)) <= 0.5 else -(z[k] - np.sign(z[k]) * 0.5) / (1 + np.sqrt(n[k]) + 0.01)
    for turn in (0, 1):
        for doc in order if turn == 0 else order[::-1]:
            data, offsets = utf8_view(pa.array([texts[doc]]))
            at = sorted(set(features_of(data, offsets, 12)[1].tolist()))
            w = {k: weight(k) for k in at}
            w0 = -z0 / (1 + np.sqrt(n0))
            g = (1 / (1 + np.exp(-np.clip(w0 + sum(w.values()), -30, 30))) - known[doc]) * part[known[doc]]
            for k in at:
                z[k] = z.get(k, 0.0) + g - (np.sqrt(n.get(k, 0.0) + g * g) - np.sqrt(n.get(k, 0.0))) * w[k]
                n[k] = n.get(k, 0.0) + g * g
            z0 += g - (np.sqrt(n0 + g * g) - np.sqrt(n0)) * w0
            n0 += g * g
    want = {k: weight(k) for k in z if weight(k)}
    assert set(model.at.tolist()) == set(want) and all(abs(want[k] - w) < 1e-6 for k, w in zip(model.at.tolist(), model.weight.tolist(), strict=True))


def test_language_scores_equal_naive_cosines(spark):
    docs, _ = labelled(spark, "quality")
    model = LanguageId(dimensions=512).fit(docs, F.lit(True))
    texts = {r.doc_id: (r.text or "") for r in docs.collect()}
    got = {r.doc_id: r for r in model.predict(docs).collect()}
    for doc, text in sorted(texts.items(), key=lambda x: len(x[1]))[:120]:
        data, count = bytes(b + 32 if 65 <= b <= 90 else b for b in text.encode()), np.zeros(512)
        for i in range(len(data)):
            gram = 0
            for width, b in enumerate(data[i : i + 3], 1):
                gram = (gram * 0x01000193 + b + width) % 2**32
                count[(gram * 0x9E3779B1 % 2**32 >> 12) % 512] += 1
        v = np.log1p(count) * model.idf
        cosine = model.centre @ (v / max(np.linalg.norm(v), 1e-12))
        best = int(np.argmax(cosine))
        if got[doc].lang_pred != "und":
            assert abs(got[doc].score - min(1, max(0, cosine[best]))) < 1e-4
            assert got[doc].lang_pred == model.names[model.owner[best]] or np.sort(cosine)[-1] - np.sort(cosine)[-2] < 1e-5
