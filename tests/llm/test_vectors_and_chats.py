"""Vector search and near-duplicate vectors against brute force; quotation linking on a fixture; the pipeline and the registered queries."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from retro.llm import quotation
from retro.llm.embedding_dedup import EmbeddingDedup
from retro.llm.vector_search import PrefixForest

SCHEMA = "vec_id long, embedding array<float>, label int, score double, size int, rank int, codes int"


def vectors(spark, rows):
    return spark.createDataFrame([(k, e, lab, None, None, None, None) for k, e, lab in rows], SCHEMA)


ODD = [(900, None, 1), (901, [0.0] * 8, 1), (902, [1.0, None] + [0.0] * 6, 1), (903, [float("nan")] * 8, 1), (904, [float("inf")] + [0.0] * 7, 1), (905, [], 1), (906, [1.0, 2.0], 1), (None, [1.0] * 8, 1)]


def sample(n=300, dim=8, seed=0):
    rng = np.random.default_rng(seed)
    return [(k, rng.standard_normal(dim).astype(np.float32).tolist(), int(k % 3)) for k in range(n)]


def test_search_returns_all_candidates_exactly_when_they_are_few(spark):
    rows = sample()
    rows[7] = (7, rows[3][1], 0)  # a tie
    out = PrefixForest().search(vectors(spark, rows + ODD), F.col("vec_id") % 20 == 0, 5).collect()
    x = np.array([r[1] for r in rows])
    for q in range(0, 300, 20):
        score = x @ x[q]
        want = sorted((k for k in range(300) if k != q), key=lambda k: (-score[k], k))[:5]
        got = sorted((r for r in out if r.query_id == q), key=lambda r: r.rank)
        assert [r.vec_id for r in got] == want and [r.rank for r in got] == [1, 2, 3, 4, 5]
        assert np.allclose([r.score for r in got], score[want])
    assert {r.query_id for r in out} == set(range(0, 300, 20))


def test_forest_recall_and_longest_prefixes():
    rng = np.random.default_rng(4)
    forest = PrefixForest(trees=12, share=0.5, least=100)
    centre = rng.standard_normal((40, 24))
    x = centre[rng.integers(0, 40, 3000)] + 0.15 * rng.standard_normal((3000, 24))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    items = forest.codes(x)
    score = x[:60] @ x.T
    hits = []
    for q, found in forest.candidates(items, items[:60]):
        top = np.argsort(-score[q])[:20]
        hits.append(np.isin(top, found).mean())
        assert q in found and len(found) < 3000
    assert np.mean(hits) >= 0.9


@pytest.mark.parametrize("kind", ["random", "copied", "near copies", "unequal norms", "norms in a band"])
def test_recall_of_the_defaults(spark, kind):
    rng = np.random.default_rng(11)
    n, dim, k = 10_256, 64, 20
    x = rng.standard_normal((n, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    group = rng.random(n) < (1 / 3 if kind in ("copied", "near copies") else 0)
    x[group] = x[np.argmax(group)]
    if kind == "near copies":
        x[group] += 0.02 * rng.standard_normal((group.sum(), dim))
    if kind == "unequal norms":
        x *= np.exp(0.5 * rng.standard_normal(n))[:, None]
    if kind == "norms in a band":
        x *= rng.uniform(0.75, 1.0, n)[:, None]
    rows = spark.createDataFrame(pa.table({"vec_id": pa.array(range(n)), "embedding": pa.array(list(x), pa.list_(pa.float64()))}))
    found = {}
    for r in PrefixForest().search(rows, F.col("vec_id") % 40 == 0, k).collect():
        found.setdefault(r.query_id, set()).add(r.vec_id)
    hits = []
    for q in range(0, n, 40):
        score = x @ x[q]
        score[q] = -np.inf
        if not group[q]:
            hits.append(len(found[q] & set(np.argsort(-score, kind="stable")[:k].tolist())) / k)
        assert len(found[q]) == k
    assert np.mean(hits) >= 0.95 and np.mean(sorted(hits)[: len(hits) // 10]) >= 0.85


def test_search_edges(spark):
    none = vectors(spark, [])
    assert PrefixForest().search(none, F.lit(True), 3).count() == 0
    one = vectors(spark, sample(1))
    assert PrefixForest().search(one, F.lit(True), 3).count() == 0
    few = PrefixForest(shard=2, query_block=2).search(vectors(spark, sample(7) + sample(7)), F.lit(True), 20)
    assert few.count() == 7 * 6


def brute(rows, least):
    ok = {k: np.array(e, float) for k, e, lab in rows if k is not None and e and lab is not None and None not in e and np.isfinite(np.array(e, float)).all() and np.any(e)}
    lab = {r[0]: r[2] for r in rows}
    links, root = {r[0]: 0 for r in rows if r[0] is not None}, {r[0]: r[0] for r in rows if r[0] is not None}
    ids = sorted(ok)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if lab[a] == lab[b] and len(ok[a]) == len(ok[b]) and ok[a] @ ok[b] / np.linalg.norm(ok[a]) / np.linalg.norm(ok[b]) >= least:
                links[a] += 1
                links[b] += 1
                x, y = sorted((root[a], root[b]))
                root = {k: x if v == y else v for k, v in root.items()}
    return {k: (links[k], root[k], root[k] == k) for k in root}


@pytest.mark.parametrize("block", [2048, 3])
def test_embedding_dedup(spark, block):
    rng = np.random.default_rng(9)
    rows = sample(80) + [(100, [1.0] * 8, None)]
    for g in range(8):
        base = rng.standard_normal(8)
        for k in range(10):
            noise = 0.06 * rng.standard_normal(8) if k % 3 else 0
            rows.append((200 + 10 * g + k, (base + noise).astype(np.float32).tolist(), g % 2))
    rows += ODD
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in EmbeddingDedup(block=block).dedup(vectors(spark, rows)).collect()}
    assert got == brute(rows, 0.98)
    assert EmbeddingDedup().dedup(vectors(spark, [])).count() == 0


CHAT = [
    (1, 0, "user", "How do I sort a list?\nIn place, please."),
    (1, 1, "assistant", "Use list.sort().\n\nIt returns None."),
    (1, 2, "user", "> Use   list.SORT().\nThanks!\n>> In place, please.\n> It returns None.\nWhy?"),
    (1, 3, "user", "> How do I sort a list?\n> In place, please.\nAnother thought on this."),
    (2, 0, "user", "> It returns None.\nQuoted from elsewhere"),
    (2, 1, "assistant", None),
    (2, 2, "user", ">"),
    (3, 5, "user", "> never said by anyone"),
]


def test_quotation_linking(spark):
    rows = spark.createDataFrame([*[(*r, 0) for r in CHAT], (*CHAT[0], 0), (None, 1, "user", "x", 0), (4, None, "user", "x", 0)], "conv_id long, turn long, role string, text string, depth int")
    found = {(r.conv_id, r.turn, r.place): (r.level, r.to_conv, r.to_turn) for r in quotation.links(quotation.messages(rows)).collect()}
    assert found[1, 2, 0] == (1, 1, 1) and found[1, 2, 1] == (2, 1, 0) and found[1, 2, 2] == (1, 1, 1)
    assert found[1, 3, 0] == (1, 1, 0) and found[2, 0, 0] == (1, 1, 1) and found[3, 5, 0] == (1, None, None)
    out = {(r.conv_id, r.turn): r for r in quotation.reply_ordered(rows).collect()}
    assert len(out) == len(CHAT)
    assert out[1, 3].reply_to == 0 and out[1, 2].reply_to == 1 and out[1, 0].reply_to is None and out[2, 1].reply_to == 0
    assert out[1, 2].content == "Thanks!\nWhy?" and out[2, 2].content == "" and out[2, 1].content == ""
    assert [t for t in sorted(range(4), key=lambda t: out[1, t].position)] == [0, 1, 3, 2] and out[1, 2].depth == 2
    assert (out[1, 2].n_quotes, out[1, 2].n_linked) == (3, 3) and (out[3, 5].n_quotes, out[3, 5].n_linked) == (1, 0)
    chat = {r.conv_id: r for r in quotation.chats(rows).collect()}
    assert chat[1].n_messages == 4 and [m.role for m in chat[1].messages] == ["user", "assistant", "user", "user"]
    assert quotation.reply_ordered(rows.limit(0)).count() == 0


def threads(seed, conversations=30):
    """Messages that quote earlier ones whole, by paragraph or line, with the quotes inside them one level deeper; some texts are said more than once."""
    rng, said = np.random.default_rng(seed), []
    for conv in range(conversations):
        own = []
        for turn in range(int(rng.integers(1, 9))):
            lines = []
            for _ in range(int(rng.integers(0, 3)) if own else 0):
                other = own[int(rng.integers(0, len(own)))] if rng.random() < 0.8 or not said else said[int(rng.integers(0, len(said)))][3]
                part = other.split("\n") if rng.random() < 0.6 else [x for x in [other.split("\n")[-1]] if x.strip()] or ["never said"]
                lines += [("> " if rng.random() < 0.5 else ">") + x for x in part]
                lines += ["thanks" if rng.random() < 0.5 else f"comment {conv} {turn} {len(lines)}"]
            lines += [f"line {conv}.{turn}.{k}" if rng.random() < 0.9 else "me too" for k in range(int(rng.integers(1, 4)))]
            own.append("\n".join(lines))
            said.append((conv, turn, "user" if turn % 2 == 0 else "assistant", own[-1]))
    return said


def plain_links(said):
    """The same by loops over all messages: {(conv, turn): (reply_to, n_quotes, n_linked, content)}."""
    norm = lambda t: " ".join(t.split()).lower()
    parsed = {}
    for conv, turn, _, text in said:
        own, runs, last = [], [], 0
        for line in text.split("\n"):
            rest, level = line, 0
            while rest[:1] == ">":
                level, rest = level + 1, rest[1:]
                rest = rest[1:] if rest[:1] == " " else rest
            if level and level == last:
                runs[-1][1].append(rest)
            elif level:
                runs.append((level, [rest]))
            else:
                own.append(line)
            last = level
        body = "\n".join(own).strip()
        parsed[conv, turn] = body, [(n, norm("\n".join(r))) for n, r in runs if norm("\n".join(r))], {norm(body), *map(norm, body.split("\n"))} - {""}
    out = {}
    for (conv, turn), (body, quotes, _) in parsed.items():
        linked, answers = 0, []
        for level, text in quotes:
            here = [t for (c, t), p in parsed.items() if c == conv and text in p[2]]
            to = (conv, min(here)) if here and min(here) < turn else min([k for k, p in parsed.items() if k[0] != conv and text in p[2]], default=None)
            linked += to is not None
            if to and to[0] == conv and level == 1:
                answers.append(to[1])
        out[conv, turn] = max(answers) if answers else turn - 1 if turn else None, len(quotes), linked, body
    return out


@pytest.mark.parametrize("seed", [1, 2])
def test_reply_order_equals_brute_force(spark, seed):
    said = threads(seed)
    want = plain_links(said)
    got = {(r.conv_id, r.turn): r for r in quotation.reply_ordered(spark.createDataFrame(said, "conv_id long, turn long, role string, text string")).collect()}
    # a passage of several lines, of which no message is the whole, may be linked by its sentences; the plain loops know wholes alone
    wholes = {k for k, w in want.items() if got[k].n_linked == w[2]}
    assert len(wholes) > 0.8 * len(want) and sum(w[2] for w in want.values()) > 30
    for k in wholes:
        assert (got[k].reply_to, got[k].n_quotes, got[k].content) == (want[k][0], want[k][1], want[k][3])
    assert all(got[k].n_linked >= w[2] for k, w in want.items())
    for conv in {c for c, _ in want}:
        turns = [t for c, t in want if c == conv]
        depth, root = {}, {}
        for t in turns:
            up = got[conv, t].reply_to
            depth[t], root[t] = (0, t) if up is None else (depth[up] + 1, root[up])
            assert (got[conv, t].depth, got[conv, t].thread) == (depth[t], root[t])
        assert sorted(turns, key=lambda t: got[conv, t].position) == sorted(turns, key=lambda t: (root[t], depth[t], t))


LONG = "First line of it\nsecond line here\nthird line there\n\nA paragraph of its own.\n\nOne sentence. Another sentence! A last one?"


@pytest.mark.parametrize(
    "quote",
    [
        "> second line here\n> third line there",
        "> A paragraph of its own.\n>\n> One sentence. Another sentence! A last one?",
        "> another  SENTENCE!",
        "> One sentence. Another sentence!",
        "> First line of it\n> second line here\n> words that nobody wrote",
    ],
)
def test_quotes_of_a_part(spark, quote):
    chat = [(1, 0, "user", "Nothing here"), (1, 1, "user", LONG), (1, 2, "assistant", "second line here"), (1, 3, "assistant", "third line there\nOne sentence."), (1, 4, "user", f"{quote}\nMine"), (2, 0, "user", LONG), (2, 1, "user", "Hm"), (2, 2, "user", "> Nothing here\n> that was said\n> by anyone")]
    out = {(r.conv_id, r.turn): r for r in quotation.reply_ordered(spark.createDataFrame(chat, "conv_id long, turn long, role string, text string")).collect()}
    assert (out[1, 4].n_quotes, out[1, 4].n_linked, out[1, 4].reply_to, out[1, 4].content) == (1, 1, 1, "Mine")
    assert (out[2, 2].n_quotes, out[2, 2].n_linked, out[2, 2].reply_to) == (1, 0, 1)


def test_nested_levels():
    body, quotes, _ = quotation.parsed("> > deep\n> a\n> b\nown\n>c")
    assert body == "own" and [q[0] for q in quotes] == [2, 1, 1]
    assert quotes[1][1] == quotation.code_of("A  b")


def test_pipeline_on_the_smallest_tables(spark):
    import corpus_pipeline as p

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in p.STAGES] == ["language", "toxicity", "near_duplicates", "packing"]
    kept = docs
    for _, stage in p.STAGES[:-1]:
        now = stage(spark, kept, sf)
        assert now.columns == docs.columns
        assert now.join(kept.select("doc_id"), "doc_id", "left_anti").count() == 0 and now.count() >= 0.7 * kept.count()
        kept = now
    out = p.run(spark, sf)
    assert {r.doc_id for r in out.select("doc_id").collect()} == {r.doc_id for r in kept.select("doc_id").collect()}
    empty = docs.limit(0)
    for _, stage in p.STAGES:
        empty = stage(spark, empty, sf)
        assert empty.count() == 0


def test_near_duplicate_stage_keeps_one_row_of_each_document(spark):
    import corpus_pipeline as p

    long = " ".join(f"w{k}" for k in range(60))
    rows = [(1, long), (1, long), (2, long + " end"), (3, None), (4, ""), (4, ""), (5, "other words here"), (None, long)]
    docs = spark.createDataFrame([(i, t, "en", "s", None) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in dict(p.STAGES)["near_duplicates"](spark, docs, "").collect()) == [1, 3, 4, 5]


def test_registered_queries():
    import __spark_entry__ as e

    names = list(e.queries())
    assert [n.split("_")[0] for n in names if n.startswith("op")] == [f"op{k}" for k in range(1, 11)] and "pipeline" in names
    assert set(e.oracle_sql()) <= set(names)
