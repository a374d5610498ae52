"""Each corpus operator against brute force, a library or an exact round trip, with nulls, empties, ties and empty tables."""

import base64
import hashlib
import json
import random
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from rastertopo.llm import exact_dedup, html_text, line_dedup, mixing, near_dedup, pieces, tool_calls, toxicity, warc, winnowing

DOCS = "doc_id long, text string, lang string, source string, n_chars long, digest string"
LONG = " ".join(f"w{i}" for i in range(3000))


@pytest.fixture(scope="module")
def docs(spark):
    """Nulls in every column, empty and long texts, ties, repeated rows, a column whose name operators use themselves."""
    rows = [
        (1, "alpha beta gamma", "en", "a", 16, "x"), (2, "alpha beta gamma", "en", "b", 16, None), (3, None, None, None, None, None), (4, "", "en", "a", 0, "y"),
        (5, LONG, "en", "a", len(LONG), "z"), (6, LONG, "en", None, len(LONG), "z"), (6, LONG, "en", None, len(LONG), "z"), (7, "é ü\tß\n漢字 😀", "de", "b", 9, "q"),
        (8, "alpha", "en", "c", 5, "q"), (None, "alpha beta gamma", "en", "a", 16, "q"), (9, " ".join(LONG.split()[:2900] + ["new"] * 60), "en", "b", 1, "q"),
    ]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


# ---- 1: exact dedup ----


@pytest.mark.parametrize("keep,digest_bytes", [("largest", 32), ("smallest", 32), ("largest", 0), ("smallest", 1)])
def test_exact_dedup(docs, keep, digest_bytes):
    """A short digest makes different texts meet, so the bytes must tell them apart."""
    groups = defaultdict(list)
    for r in docs.collect():
        groups[r.text or ""].append(r.doc_id)
    got = sorted(exact_dedup.exact_duplicates(docs, keep=keep, digest_bytes=digest_bytes).collect(), key=str)
    want = []
    for text, ids in groups.items():
        known = [i for i in ids if i is not None]
        first = (max if keep == "largest" else min)(known)
        # Of rows equal in id and text one stays.
        want += [(i, first, len(ids), i == first and n == ids.index(first), hashlib.sha256(text.encode()).hexdigest()) for n, i in enumerate(ids)]
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, want))


def test_one_of_equal_rows_stays(spark):
    df = spark.createDataFrame([(5, "same"), (5, "same"), (4, "same"), (None, "none"), (None, "none")], "doc_id long, text string")
    for digest_bytes in (32, 0):
        got = exact_dedup.exact_duplicates(df, digest_bytes=digest_bytes)
        assert sorted(map(str, got.filter("kept").select("doc_id", "group_size").collect())) == ["Row(doc_id=5, group_size=3)", "Row(doc_id=None, group_size=2)"]


def test_index_grows_by_levels(spark):
    texts = [f"t{i % 7}" for i in range(20)]
    index = exact_dedup.DigestIndex(spark, fanout=2)
    for start in range(0, 20, 4):
        index.flush(spark.createDataFrame([(i, texts[i]) for i in range(start, start + 4)], "doc_id long, text string"))
    # Five flushes at two a level: one run of four flushes, one flush left.
    assert [len(level) for level in index.levels] == [1, 0, 1]
    digest = hashlib.sha256(b"t3").digest()
    assert tuple(index.find(digest).first()) == (digest, 3, 3) and index.find(hashlib.sha256(b"no").digest()).isEmpty()
    level = index.compact()
    assert level.count() == 7 and level.agg(F.sum("group_size")).first()[0] == 20 and tuple(index.find(digest).first()) == (digest, 3, 3)
    index.flush(spark.createDataFrame([(99, "t3")], "doc_id long, text string"))
    assert index.compact().filter(F.col("digest") == F.lit(bytearray(digest))).select("keep_id", "group_size").first()[:] == (3, 4)


# ---- 2: toxicity ----


def labelled_texts(n=400, seed=1):
    rng = random.Random(seed)
    plain = ["".join(rng.choice("bcdfgklmn") + rng.choice("aeiou") for _ in range(3)) for _ in range(200)]
    texts, labels = [], []
    for i in range(n):
        words = [rng.choice(plain) for _ in range(rng.randint(10, 80))]
        if i % 5 == 0:
            for _ in range(1 + len(words) // 25):
                words.insert(rng.randrange(len(words)), rng.choice(["wretched", "scoundrel", "vermin"]))
        texts.append(" ".join(words))
        labels.append(int(i % 5 == 0))
    return texts, labels


def test_toxicity_held_out_accuracy():
    model = toxicity.fit(*labelled_texts())
    scorer = toxicity.Scorer(*model)
    texts, labels = labelled_texts(seed=2)
    found = [scorer.score(t) >= 0.5 for t in texts]
    assert np.mean(np.array(found) == labels) > 0.97
    # Misspellings were never seen; they share subwords.
    assert scorer["scoundrell"] > 0 and scorer["wretchedd"] > 0 and abs(scorer["zzzz"]) < scorer["vermin"] / 10


def test_toxicity_without_two_classes():
    assert toxicity.Scorer(*toxicity.fit([], [])).score("x") < 1e-6
    assert toxicity.Scorer(*toxicity.fit(["a b"], [1])).score(None) > 0.999
    assert toxicity.Scorer(*toxicity.fit(["a b", "c"], [0, 1])).score("") == pytest.approx(0.5, abs=0.5)


def test_toxicity_rows(spark, docs, none):
    labels = spark.createDataFrame([(i, i % 2, None if i == 4 else i % 2) for i in range(12)] + [(None, 1, 1), (1, 0, 1)], "doc_id long, quality int, toxic int")
    got = toxicity.scores(docs, labels)
    assert got.count() == docs.count() and got.filter("score IS NULL OR score < 0 OR score > 1 OR predicted <> int(score >= 0.5)").isEmpty()
    assert toxicity.scores(none, labels).isEmpty() and toxicity.scores(docs, labels.limit(0)).count() == docs.count()


# ---- 3: chat formatting ----

SCHEMAS = {"find": {"type": "object", "properties": {"q": {"type": "string"}, "n": {"type": "integer", "minimum": 1}}, "required": ["q"], "additionalProperties": False}}


def test_calls_are_linked_ordered_and_validated(spark):
    j = json.dumps
    rows = [
        (1, 0, "user", "hi {"),
        (1, 1, "assistant", j({"content": "c", "tool_calls": [{"id": "a", "name": "find", "arguments": {"q": "x", "n": 1.0}}, {"id": "b", "name": "find", "arguments": {"q": "$a"}}, {"id": "z", "name": "no", "arguments": {}}]})),
        (1, 2, "tool", j({"tool_call_id": "b", "content": 1.5})), (1, 3, "tool", j({"tool_call_id": "a", "content": {"z": 1, "a": [1, 2]}})), (1, 4, "tool", j({"tool_call_id": "q"})),
        (2, 0, "assistant", j({"tool_calls": [{"id": "a", "name": "find", "arguments": {}, "after": ["b"]}, {"id": "b", "name": "find", "arguments": '{"q":"1"}', "after": ["a"]}]})),
        (2, 1, "tool", j({"tool_call_id": "a"})), (2, 2, "tool", j({"tool_call_id": "b"})), (None, None, None, None), (3, 0, "assistant", "{broken"),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = [r.asDict() for r in tool_calls.format_chats(df, SCHEMAS).orderBy("conv_id", "order_turn", "order_depth", "turn", "part").collect()]
    one = [(r["kind"], json.loads(r["record"]).get("id"), r["linked_turn"], r["valid"]) for r in got if r["conv_id"] == 1]
    assert one == [("message", None, None, None), ("message", None, None, None), ("call", "a", 3, True), ("call", "z", None, False), ("result", "a", 1, None), ("call", "b", 2, True), ("result", "b", 1, None), ("result", "q", None, None)]
    assert {r["cyclic"] for r in got if r["conv_id"] == 2 and r["kind"] != "message"} == {True}
    assert next(r for r in got if r["conv_id"] == 3)["record"] == '{"content":"{broken","conv_id":3,"kind":"message","role":"assistant","turn":0}'
    assert any(r["conv_id"] is None for r in got)
    assert tool_calls.format_chats(df.limit(0), SCHEMAS).isEmpty()


@pytest.mark.parametrize(
    "arguments", ['{"n": 1e999}', '{"n": NaN}', '{"q": "\\ud800"}', '{"q": ' + "[" * 3000 + "]" * 3000 + "}", '{"q": "$\\udfff"}'], ids=["infinite", "nan", "half", "deep", "half-reference"]
)
def test_odd_calls_stay(arguments):
    """Numbers that aren't finite, halves of surrogate pairs and deep nesting don't stop a job."""
    for name in ('"find"', "[]", "null"):
        text = '{"tool_calls": [{"id": "a\\ud801", "name": ' + name + ', "arguments": ' + arguments + "}]}"
        rows = tool_calls.parse(1, 2, "assistant", text, SCHEMAS)
        assert rows[0][1] == "message" and all(x is None or isinstance(x, (int, bool, list)) or x.encode() for row in rows for x in row)
        assert len(rows) == (1 if len(arguments) > 1000 else 2) and (len(rows) == 1 or rows[1][4] is (name == '"find"' and arguments.startswith('{"q"')))


def test_chat_rows_of_odd_tables(spark):
    rows = [(1, 0, "user", "x"), (1, 0, "user", "x"), (1, 1, "assistant", "y" * 200_000), (1, 1, "assistant", None), (2, 0, "user", None), (2, 1, "assistant", ""), (None, None, None, None)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("kind", F.lit("mine")).withColumn("id", F.lit(1)).withColumn("part", F.lit(None).cast("int"))
    got = tool_calls.format_chats(tool_calls.derived(df), {"search": {"type": "object", "required": ["query"]}}).collect()
    assert sorted(r["kind"] for r in got) == ["call"] * 3 + ["message"] * 10 + ["result"] * 3
    assert sorted(r["linked_turn"] for r in got if r["kind"] == "call") == [1, 1, 1] and sum(r["valid"] is True for r in got) == 2


def test_canonical_json():
    assert tool_calls.canonical({"b": 1.0, "a": [True, None, "é\n", 1e21, 0.1]}) == '{"a":[true,null,"é\\n",1e+21,0.1],"b":1}'


def test_schema_problems():
    ok = {"q": "x", "n": 2}
    assert tool_calls.problems(ok, SCHEMAS["find"]) == []
    for bad in ({}, {"q": 1}, {"q": "x", "n": 0}, {"q": "x", "n": 1.5}, {"q": "x", "o": 1}, {"q": "x", "n": True}, []):
        assert tool_calls.problems(bad, SCHEMAS["find"])


# ---- 4: fingerprints ----


def brute_fingerprint(spark, text, k, w):
    """Windows over all grams: the entries of window size 1 are all grams in order."""
    df = spark.createDataFrame([(1, text)], "doc_id long, text string")
    grams = [(e["hash"], e["position"]) for e in winnowing.fingerprints(df, k=k, w=1).first()["entries"]]
    out = []
    for i in range(max(len(grams) - w + 1, 1)):
        best = min(grams[i : i + w], key=lambda g: (g[0], -g[1]))
        if best not in out:
            out.append(best)
    return out


@pytest.mark.parametrize("text", ["", "one", "a b c d e f", "x " * 40, " ".join(random.Random(3).choices("abc", k=120))])
def test_winnowing_windows(spark, text):
    got = winnowing.fingerprints(spark.createDataFrame([(1, text)], "doc_id long, text string"), k=3, w=4).first()["entries"]
    assert [(e["hash"], e["position"]) for e in got] == brute_fingerprint(spark, text, 3, 4)


def test_winnowing_guarantee(spark):
    """Texts that share k + w - 1 words share an entry."""
    rng = random.Random(5)
    shared = " ".join(f"s{i}" for i in range(winnowing.GRAM + winnowing.WINDOW - 1))
    rows = [(i, " ".join(f"r{rng.random()}" for _ in range(rng.randint(0, 30))) + " " + shared + " " + " ".join(f"t{rng.random()}" for _ in range(rng.randint(0, 30)))) for i in range(20)]
    found = [{e["hash"] for e in r["entries"]} for r in winnowing.fingerprints(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert all(a & b for a in found for b in found)


def test_short_texts_share_characters(spark):
    """15 successive characters in common are found, in texts of few words or none apart, and beyond the basic plane."""
    shared = ["three short words", "漢字" * 8, "😀é" * 8, "unbroken" * 3]
    rows = [(2 * i + j, text) for i, s in enumerate(shared) for j, text in enumerate((f"{s} ab", f"x😀 {s}"))]
    got = {r.doc_id: r.entries for r in winnowing.fingerprints(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i in range(len(shared)):
        assert {e["hash"] for e in got[2 * i]} & {e["hash"] for e in got[2 * i + 1]}
    # Positions count code points, and there is a gram for each but the last seven.
    grams = winnowing.fingerprints(spark.createDataFrame([(1, "😀bcdefghij")], "doc_id long, text string"), w=1).first()["entries"]
    assert [e["position"] for e in grams] == [0, 1, 2]


@pytest.mark.parametrize("stretch", [500, 2])
def test_edited_texts(docs, none, monkeypatch, stretch):
    monkeypatch.setattr(winnowing, "STRETCH_ROWS", stretch)
    rows = sorted(docs.collect(), key=lambda r: (-(r.doc_id if r.doc_id is not None else -(1 << 63)), r.text or ""))
    texts = [r.text or "" for r in rows]
    want = []
    for i, t in enumerate(texts):
        cut = len(t) // 2
        edited = t[: len(t) - cut] + texts[(i + 1) % len(texts)][:cut]
        want.append((rows[i].doc_id, len(t), hashlib.sha256(edited.encode()).hexdigest()))
    got = winnowing.edited_fingerprints(docs).collect()
    assert sorted(map(str, [(r.doc_id, r.n_chars, r.edited_sha256) for r in got])) == sorted(map(str, want))
    by_text = defaultdict(set)
    for r in got:
        by_text[r.n_chars, r.doc_id in (1, 2, None)].add(r.fingerprint)
        assert 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    assert len(by_text[16, True]) == 1
    assert winnowing.edited_fingerprints(none).isEmpty()


# ---- 5: pieces ----


@pytest.fixture(scope="module")
def model():
    return pieces.PieceModel(pieces.read_model())


ODD = ["", "a", " ", "  ", "   x", "a  b", "\n\n x\ny", " " * 17, " " * 40, "x" + " " * 35 + "y", "日本語 テキスト😀", "<s> <unk> </s>", "a\x00b", "aaaaaaaaaaaaaaaaaaa", "=====----====", "\t\tif (x==1) {\n\t\t\treturn;\n}", "1234567890 3.14"]


def test_pieces_match_the_library(model):
    library = pytest.importorskip("sentencepiece").SentencePieceProcessor(model_file=pieces.MODEL)
    rng = random.Random(1)
    texts = ODD + ["".join(rng.choice("ab el o\nthin. ,é=-_(){}") for _ in range(rng.randint(1, 60))) for _ in range(1500)]
    for text in texts:
        ids = model.encode(text)
        assert ids == library.encode(text)
        assert model.decode(ids) == library.decode(ids) == text


def test_unigram_path_is_the_cheapest():
    unigram = pieces.PieceModel(pieces.read_model(), kind=pieces.UNIGRAM)

    def brute(text):
        if not text:
            return 0.0
        options = [-unigram.scores[unigram.ids[text[:k]]] + brute(text[k:]) for k in range(1, len(text) + 1) if text[:k] in unigram.ids]
        return min(options, default=float("inf"))

    for word in ("the", "letters", "in the", "abcabc"):
        ids = unigram.encode(word)
        assert sum(-unigram.scores[i] for i in ids) == pytest.approx(brute(unigram.normalise(word)))
        assert unigram.decode(ids) == word


def test_pieces_rows(docs, none):
    got = pieces.tokens(docs)
    assert got.count() == docs.count() and got.filter("NOT exact").isEmpty()
    assert got.filter("doc_id IN (3, 4) AND n_tokens <> 0").isEmpty()
    assert pieces.tokens(none).isEmpty()
    kept = pieces.decode(pieces.encode(docs)).filter("NOT (decoded <=> coalesce(text, ''))")
    assert kept.isEmpty() and "digest" in pieces.encode(docs).columns


def test_normaliser_rules():
    n = pieces.Normaliser(strip=True, rules={"ﬁ": "fi", "ab": "x", "abc": "y"})
    assert n("  abc  ab ﬁ ") == "▁y▁x▁fi" and n(" ") == ""


# ---- 6: near dedup ----


def plain_distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_banded_alignment():
    r = random.Random(3)
    for _ in range(3000):
        a = [r.choice("abcd") for _ in range(r.randint(0, 24))]
        b = list(a)
        for _ in range(r.randint(0, 8)):
            kind = r.random()
            if kind < 0.33 and b:
                del b[r.randrange(len(b))]
            elif kind < 0.66:
                b.insert(r.randint(0, len(b)), r.choice("abcd"))
            elif b:
                b[r.randrange(len(b))] = r.choice("abcd")
        most = r.randint(0, 12)
        assert near_dedup.edit_distance(a, b, most) == min(plain_distance(a, b), most + 1)


def test_order_matters_and_occurrences_count():
    words = np.random.default_rng(1).integers(0, 1 << 62, 200, dtype=np.uint64)
    twice = near_dedup.labelled_shingles(np.concatenate([words, words]))
    assert len(np.unique(twice)) == len(twice)
    m = near_dedup._multipliers(64, 11)
    same = lambda a, b: (near_dedup.order_minhash(a, m) == near_dedup.order_minhash(b, m)).mean()
    straight = near_dedup.labelled_shingles(words)
    # The first occurrences hash alike whether or not the text repeats something.
    assert np.isin(straight[:190], twice).all()
    swapped = near_dedup.labelled_shingles(np.concatenate([words[100:], words[:100]]))
    assert same(straight, straight) == 1 and same(straight, swapped) < 0.6


@pytest.mark.parametrize("share", [0.08, 0.1, 0.15, 0.2])
def test_links_are_candidates(share):
    """Texts with scattered edits up to the threshold share a bucket."""
    rng = random.Random(8)
    m = near_dedup._multipliers(near_dedup.SKETCHES, 11)
    met = []
    for _ in range(100):
        a = [rng.getrandbits(62) for _ in range(rng.randint(20, 300))]
        b = list(a)
        for i in rng.sample(range(len(a)), near_dedup.limit_of(len(a), 1 - share)):
            b[i] = rng.getrandbits(62)
        x, y = (near_dedup.text_buckets(np.array(t, np.uint64), m) for t in (a, b))
        met.append(bool(len(np.intersect1d(x, y))))
    assert np.mean(met) >= 0.95


def test_blocks_join_what_all_pairs_join():
    """Two blocks of a large bucket give links that join the same texts as all links do."""
    rng = random.Random(5)
    passage = [f"p{i}" for i in range(40)]
    texts = [" ".join(passage + [f"w{rng.randrange(12)}" for _ in range(rng.randint(2, 24))]) for _ in range(60)]
    words = [t.split() for t in texts]
    nodes, own = np.arange(60) * 7, np.array([i % 2 for i in range(60)])
    labels = nodes.copy()
    labels[:10] = 0

    def classes(links):
        root = {int(n): int(c) for n, c in zip(nodes, labels)}
        for a, b in links:
            x, y = root[a], root[b]
            root = {n: (x if c == y else c) for n, c in root.items()}
        return {frozenset(n for n in root if root[n] == c) for c in root.values()}

    every = []
    for i in range(60):
        for j in range(i):
            limit = near_dedup.limit_of(max(len(words[i]), len(words[j])), 0.8)
            if near_dedup.edit_distance(words[i], words[j], limit) <= limit:
                every.append((int(nodes[j]), int(nodes[i])))
    found = []
    for i, j in ((0, 0), (0, 1), (1, 1)):
        at = np.flatnonzero((own == i) | (own == j))
        found += near_dedup.linked_nodes(1, 0, own[at] == i, own[at] == j, nodes[at], labels[at], [[1]] * len(at), [texts[k] for k in at], 0.8)
    assert classes(found) == classes(every)
    assert 1 < len(classes(every)) < 51 and len(found) < len(every)


def test_links_of_short_texts_share_a_key():
    rng = random.Random(9)
    for _ in range(3000):
        a = [rng.randrange(1 << 40) for _ in range(rng.randint(1, 14))]
        b = list(a)
        for _ in range(rng.randint(0, 2)):
            i = rng.randrange(len(b) + 1)
            b[i : i + rng.randint(0, 1)] = [rng.randrange(1 << 40)] * rng.randint(0, 1)
        longer = max(len(a), len(b))
        limit = near_dedup.limit_of(longer, 0.8)
        if b and longer <= 14 and plain_distance(a, b) <= limit:
            x, y = (set(near_dedup.deletion_keys(np.array(t, np.uint64)).tolist()) for t in (a, b))
            assert x & y
    assert len(near_dedup.deletion_keys(np.arange(15, dtype=np.uint64))) == 0


def test_short_texts_are_linked(spark):
    base = [f"w{i}" for i in range(9)]
    rows = [(1, " ".join(base)), (2, " ".join(base[:8])), (3, " ".join(f"v{i}" for i in range(5))), (4, "v0 v1 x v3 v4"), (5, "v0  v1 x v3 v4"), (6, "solo"), (7, "other"), (8, "v0 v1 v3 q"), (9, "u1 u2 u3 u4"), (10, "u1 u2 u3 x")]
    got = {r.doc_id: r.class_id for r in near_dedup.near_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 1, 3: 3, 4: 3, 5: 3, 6: 6, 7: 7, 8: 8, 9: 9, 10: 10}


def near_rows(n=30, seed=4):
    rng = random.Random(seed)
    rows, k = [], 0
    for g in range(n):
        base = [f"w{rng.randrange(5000)}" for _ in range(rng.randint(40, 160))]
        for _ in range(rng.choice((1, 1, 2, 5))):
            words = list(base)
            for _ in range(rng.randint(0, max(1, len(words) // 60))):
                words[rng.randrange(len(words))] = f"x{rng.randrange(10**6)}"
            rows.append((k, " ".join(words)))
            k += 1
    return rows + [(k, None), (k + 1, ""), (k + 2, rows[0][1]), (k + 2, rows[0][1]), (None, rows[3][1])]


def test_near_classes_match_brute_force(spark):
    rows = near_rows()
    df = spark.createDataFrame(rows, "doc_id long, text string")
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    words = [(t or "").split() for _, t in rows]
    for i in range(len(rows)):
        for j in range(i):
            limit = near_dedup.limit_of(max(len(words[i]), len(words[j])), 0.8)
            if bool(words[i]) == bool(words[j]) and near_dedup.edit_distance(words[i], words[j], limit) <= limit:
                parent[find(i)] = find(j)
    classes = defaultdict(list)
    for i, (doc, _) in enumerate(rows):
        classes[find(i)].append(doc)
    want = sorted(str((d, min(x for x in ids if x is not None), len(ids))) for ids in classes.values() for d in ids)
    got = near_dedup.near_classes(df)
    assert sorted(str((r.doc_id, r.class_id, r.class_size)) for r in got.collect()) == want
    assert near_dedup.keep_one(df.filter("doc_id < 20")).count() <= 20
    assert near_dedup.near_classes(df.limit(0)).isEmpty() and near_dedup.keep_one(df.limit(0)).isEmpty()


# ---- 7: mixing ----


def brute_targets(sizes, weights, epochs=3):
    total, free = sum(sizes.values()), set(sizes)
    while True:
        rest = total - sum(epochs * sizes[s] for s in sizes if s not in free)
        share = {s: rest * weights[s] / sum(weights[x] for x in free) for s in free}
        over = {s for s in free if share[s] > epochs * sizes[s]}
        if not over:
            return {s: share.get(s, float(epochs * sizes[s])) for s in sizes}
        free -= over


def test_water_filling(spark):
    rng = random.Random(2)
    for _ in range(5):
        sizes = {f"s{i}": rng.choice((0, 1, 10, 1000)) for i in range(8)} | {"t": 500}
        weights = {s: rng.choice((1.0, 2.0, 7.5)) for s in sizes}
        df = spark.createDataFrame([(s, sizes[s], weights[s]) for s in sizes], "source string, source_size long, weight double")
        got = {r.source: r.target for r in mixing.water_fill(df).collect()}
        assert got == pytest.approx(brute_targets(sizes, weights))
        assert sum(got.values()) == pytest.approx(sum(sizes.values()))


def test_mix(docs, none):
    rows = mixing.mix(docs).collect()
    assert len(rows) == docs.count() and all(0 <= r.taken <= 3 * r.size for r in rows)
    sums, targets = Counter(), {}
    for r in rows:
        sums[r.source] += r.taken
        targets[r.source] = r.target
    assert all(abs(sums[s] - targets[s]) <= 1 for s in targets)
    assert sorted(map(str, mixing.mix(docs.repartition(3)).collect())) == sorted(map(str, rows))
    assert mixing.mix(none).isEmpty()


# ---- 8: WARC ----

PAGES = "page_id long, url string, html string, payload string"


@pytest.fixture(scope="module")
def pages(spark):
    rows = [(1, "u", "abc", "p"), (2, "v", "abc", None), (3, None, None, "p"), (4, "w\r\nx", "", "p"), (5, "x", "é" * 5000, "p"), (6, "y", "é" * 5000, "p"), (7, "z", "solo", "p"), (7, "z", "solo", "p"), (8, "t", "a\r\n\r\nb", "p")]
    return spark.createDataFrame(rows, PAGES)


@pytest.mark.parametrize("least,chunk", [(0, 100), (4, 7), (0, 1 << 20)])
def test_warc_round_trip(pages, least, chunk):
    held = defaultdict(list)
    rows = pages.collect()
    for r in rows:
        held[r.html or ""].append(r.page_id)
    want = []
    for r in rows:
        body = (r.html or "").encode()
        first = max(held[r.html or ""]) if len(body) >= least else r.page_id
        revisit = r.page_id != first
        want.append((r.page_id, len(body), base64.b32encode(hashlib.sha1(body).digest()).decode(), "revisit" if revisit else "response", first if revisit else None))
    assert sorted(map(str, map(tuple, warc.round_trip(pages, least, chunk).collect()))) == sorted(map(str, want))


def test_warc_files_and_damage(spark, pages, tmp_path):
    path = str(tmp_path / "chunks")
    warc.write_archive(pages, path, chunk_bytes=100)
    files = warc.export_files(spark, path, f"file://{tmp_path}/files").collect()
    data = b"".join(open(f.file, "rb").read() for f in files)
    assert data.count(b"WARC/1.1\r\n") == pages.count() and sum(f.n_bytes for f in files) == len(data)
    broken = str(tmp_path / "broken")
    spark.read.parquet(path).withColumn("block", F.when(F.col("chunk_no") == 3, F.encode(F.lit("?"), "UTF-8")).otherwise(F.col("block"))).write.parquet(broken)
    with pytest.raises(Exception, match="digest"):
        warc.read_archive(spark, broken).collect()
    assert warc.round_trip(pages.limit(0)).isEmpty()


# ---- 9: HTML ----

PARAGRAPH = "Sentence of plain words that an article holds. " * 6


@pytest.mark.parametrize("page,want", [
    (None, ""), ("", ""), ("plain &amp; text", "plain & text"), ("<p>a<p>b", "a b"), ("<p>un<b>bold</b>ed &lt;x&gt; <!-- c -->z", "unbolded <x> z"),
    (f"<nav><ul><li><a href=x>Home</a></ul></nav><article><h1>T</h1><p><b>{PARAGRAPH}<br><p>two</article><footer>foot</footer>", f"T {PARAGRAPH.strip()} two"),
    (f"<body><script>var a='<p>no</p>'</script><div class=ad>{PARAGRAPH}</div><main><p>{PARAGRAPH}</p><form><input>f</form><aside>s</aside></main>", PARAGRAPH.strip()),
    (f"<div id=content><h1>T</h1><section><p>{PARAGRAPH}</p><p>{PARAGRAPH}</p></section></div><div class='side-bar sidebar'><p>{PARAGRAPH}</div><div id=comments><p>{PARAGRAPH}</div><div class=cookie-notice>{PARAGRAPH}</div>", f"{PARAGRAPH.strip()} {PARAGRAPH.strip()}"),
    ("<p>a&nbsp;b\n\n c</p><style>x", "a b c"), ("<div " * 3, ""),
])
def test_main_text(page, want):
    assert html_text.main_text(page).endswith(want) if want.startswith(PARAGRAPH.strip() + " S") else html_text.main_text(page) == want


def test_deep_and_long_pages(pages):
    assert html_text.main_text("<div>" * 20000 + "x") == "x"
    assert html_text.main_text("<p>word " * 20000).count("word") == 20000
    got = html_text.extract(pages)
    assert got.count() == pages.count() and got.filter("n_chars <> length(text)").isEmpty() and html_text.extract(pages.limit(0)).isEmpty()


LINE = "lorem ipsum dolor sit amet consectetur " * 12


@pytest.mark.parametrize(
    "page,there,gone",
    [
        (f"<article><p>{LINE}one</p><p>{LINE}</p></article><article><p>{LINE}two</p><p>{LINE}</p></article>", ["one", "two"], []),
        (f"<div id=post><h2>Story</h2><p>{LINE}one</p><p>{LINE}</p></div><article class='comment'><p>{LINE}mine</p></article>", ["Story", "one"], ["mine"]),
        (f"<article><p>{LINE}one</p><div class='share-price'>9.99</div><div class='share-buttons'>tell</div><article class='comment'>mine</article></article>", ["one", "9.99"], ["tell", "mine"]),
        (f"<main><h1>Head</h1><article><p>{LINE}</p><p>short.</p></article><section class='related-posts'><a href=x>{LINE}more</a></section></main>", ["short."], ["more"]),
        (f"<div><h1>Title</h1><p>{LINE}</p><p>x.</p><p>{LINE}</p></div><ul><li><a href=1>uno</a><li><a href=2>dos</a></ul>", ["Title", "x."], ["uno", "dos"]),
    ],
)
def test_article_by_density(page, there, gone):
    text = html_text.main_text(f"<html><body><nav><a href=a>menu</a></nav>{page}</body></html>")
    assert all(x in text for x in there) and not any(x in text for x in [*gone, "menu"])


def test_pages_with_clashing_columns(spark):
    df = spark.createDataFrame([(1, None, None, "t", 3), (1, None, None, "t", 3), (None, "u", "", None, None)], "page_id long, url string, html string, text string, n_chars int")
    assert sorted(map(str, html_text.extract(df).select("text", "n_chars").collect())) == ["Row(text='', n_chars=0)"] * 3


# ---- 10: line dedup ----


@pytest.mark.parametrize("digest_bytes", [16, 1])
def test_line_dedup(spark, digest_bytes):
    rng = random.Random(6)
    line = lambda n: " ".join(f"l{rng.randrange(10**6)}" for _ in range(n))
    heavy, passage = line(60), "\n".join(line(14) for _ in range(6))
    rows = [(i, "\n".join([line(12), heavy if i % 2 else line(8), line(9), passage if i % 3 == 0 else line(5), line(11)]), f"k{i}") for i in range(12)]
    rows += [(12, None, "n"), (13, "", "e"), (14, rows[3][1], "copy"), (14, rows[3][1], "copy"), (None, heavy, "h"), (15, "\n\n\n", "blank"), (16, heavy + "\n" + heavy, "own")]
    df = spark.createDataFrame(rows, "doc_id long, text string, removed_by string")
    order = sorted(range(len(rows)), key=lambda i: (rows[i][0] is not None, rows[i][0] or 0))
    seen, want = {}, []
    for i in order:
        doc, text, extra = rows[i]
        if text is None:
            want.append((doc, text, extra))
            continue
        kept, lines = [], text.split("\n")
        for a, b, n in line_dedup.chunk_spans(text):
            part = "\n".join(lines[a:b])
            if line_dedup.eligible(a, b, n) and seen.setdefault(part, (doc, text, a)) != (doc, text, a):
                continue
            kept += lines[a:b]
        want.append((doc, "\n".join(kept), extra))
    got = line_dedup.drop_repeated(df, digest_bytes)
    assert sorted(map(str, [(r.doc_id, r.text, r.removed_by) for r in got.collect()])) == sorted(map(str, want))
    assert got.filter("text LIKE '%" + heavy + "%'").count() == 1
    assert line_dedup.line_deduplicated(df.limit(0)).isEmpty()


def test_chunks_resist_shifts():
    rng = random.Random(7)
    passage = [" ".join(f"p{rng.randrange(10**6)}" for _ in range(10)) for _ in range(40)]
    cuts = lambda lines: {"\n".join(lines[a:b]) for a, b, _ in line_dedup.chunk_spans("\n".join(lines))}
    a, b = cuts(passage), cuts(["something", "else", "before"] + passage)
    assert len(a & b) >= len(a) - 2


def brute_passages(rows):
    """What is left of (doc, text) rows: a line goes if a run of lines around it that is long enough occurs earlier."""
    seen, out = set(), []
    for _, text in rows:
        lines = text.split("\n")
        gone = set()
        for a in range(len(lines)):
            for b in range(a + 1, len(lines) + 1):
                part = tuple(lines[a:b])
                if line_dedup.eligible(a, b, sum(len(x.split()) for x in part)):
                    if part in seen:
                        gone.update(range(a, b))
                    seen.add(part)
        out.append("\n".join(x for i, x in enumerate(lines) if i not in gone))
    return out


@pytest.mark.parametrize("digest_bytes", [16, 1])
def test_repeated_passages_go_whole(spark, digest_bytes):
    """Passages of ordinary lines, each planted in two contexts, and random texts of few lines against brute force."""
    rng = random.Random(11)
    line = lambda n: " ".join(f"q{rng.randrange(10**6)}" for _ in range(n))
    passages = [[line(w) for _ in range(n)] for n, w in ((2, 30), (3, 20), (4, 15), (6, 10), (10, 10), (20, 8))]
    rows = [(k, "\n".join([line(9), *p, line(12)])) for k, p in enumerate(passages + passages)]
    some = [line(n) for n in (2, 4, 6, 12, 60)] + [""]
    rows += [(100 + k, "\n".join(rng.choice(some) for _ in range(rng.randint(1, 9)))) for k in range(40)]
    got = line_dedup.drop_passages(spark.createDataFrame(rows, "doc_id long, text string"), digest_bytes).orderBy("doc_id").collect()
    assert [r.text for r in got] == brute_passages(rows)
    assert [len(r.text.split("\n")) for r in got[6:12]] == [2] * 6
    for r, (_, text) in zip(got, rows):
        gone = [i for s in r.removed or [] for i in range(s["first"], s["after"])]
        assert len(gone) == len(set(gone)) and all(i < len(text.split("\n")) for i in gone)


def test_spliced_entries_are_those_of_the_whole_text(spark):
    rng = random.Random(3)
    rows = []
    for i in range(300):
        a, b = ("".join(rng.choice("ab c" if i % 2 else "abcdefgh é😀") for _ in range(rng.choice((0, 5, 14, 15, 16, 29, 31, 80, 200)))) for _ in "ab")
        rows.append((i, a, b, len(a) - len(a) // 2, min(len(a) // 2, len(b))))
    df = spark.createDataFrame(rows, "doc_id long, a string, b string, kept int, taken int").withColumn("ea", winnowing.chosen(F.col("a"))).withColumn("eb", winnowing.chosen(F.col("b")))
    got = winnowing.spliced(F.col("a"), F.col("ea"), F.col("kept"), F.col("b"), F.col("eb"), F.col("taken"))
    whole = winnowing.chosen(F.concat(F.expr("substr(a, 1, kept)"), F.expr("substr(b, 1, taken)")))
    assert df.filter(~got.eqNullSafe(whole)).isEmpty() and not df.filter("kept > 14 AND taken > 14").isEmpty()


def test_block_of_texts_takes_a_number_a_word():
    import tracemalloc

    texts = [" ".join(f"long{i}word{k}" for k in range(40)) * 50 for i in range(40)]
    n = len(texts)
    tracemalloc.start()
    both = np.ones(n, bool)
    near_dedup.linked_nodes(1, -1, both, both, np.arange(n), np.arange(n), [[1]] * n, texts, 0.8)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    # A string for each word took some 60 bytes.
    assert peak < 30 * sum(len(t.split()) for t in texts)


def test_nodes_meet_in_tasks_of_two_blocks_copied_once_less(spark):
    rows = spark.createDataFrame([(o, b) for b in range(1, 6) for o in range(b)], "own int, blocks int")
    tasks = {}
    for r in rows.select("own", "blocks", near_dedup.met_by("own", "blocks").alias("others")).collect():
        assert len(r.others) == max(r.blocks - 1, 1)
        for o in r.others:
            tasks.setdefault((r.blocks, min(r.own, o), max(r.own, o)), set()).add(r.own)
    for b in range(1, 6):
        met = [(i, j) for n, i, j in tasks if n == b]
        assert sorted(met) == ([(0, 0)] if b == 1 else [(i, j) for i in range(b) for j in range(i + 1, b)])
        alone = sorted(k for i, j in met for k, other in ((i, j), (j, i)) if i != j and (k + 1) % b == other)
        assert b == 1 or alone == list(range(b))


def test_two_blocks_meet_within_one_task():
    texts = [" ".join(f"a{k}b{w}" for w in range(20)) for k in (1, 2)] * 2
    texts = [t + f" end{i}" for i, t in enumerate(texts)]
    left = np.array([True, False, True, False])
    found = near_dedup.linked_nodes(1, -1, left, ~left, np.arange(4), np.arange(4), [[1]] * 4, texts, 0.8, [left, ~left])
    assert sorted(found) == [(0, 2), (1, 3)]


def passage_texts(n, seed):
    """Texts of a passage and some words of their own, a few of them edited."""
    rng = random.Random(seed)
    passage = [f"p{i}" for i in range(30)]
    texts = [" ".join(passage + [f"w{rng.randrange(40)}" for _ in range(rng.randint(2, 30))]) for _ in range(n)]
    for _ in range(n // 3):
        words = rng.choice(texts).split()
        for _ in range(rng.randint(1, 9)):
            at = rng.randrange(len(words))
            words[at : at + rng.randint(0, 1)] = [f"w{rng.randrange(40)}"] * rng.randint(0, 1)
        texts.append(" ".join(words))
    return sorted(set(texts))


def all_links(texts):
    words = [t.split() for t in texts]
    limits = {(i, j): near_dedup.limit_of(max(len(words[i]), len(words[j])), 0.8) for j in range(len(words)) for i in range(j)}
    return {(i, j) for (i, j), most in limits.items() if near_dedup.edit_distance(words[i], words[j], most) <= most}


def test_linked_texts_meet_by_a_rare_word():
    texts, known = passage_texts(90, 6), near_dedup._Words()
    hashes = [near_dedup.word_hashes(t.split(), known) for t in texts]
    words = [near_dedup.labelled_shingles(h, 1) for h in hashes]
    counts = np.bincount((np.concatenate(words) % np.uint64(256)).astype(np.int64), minlength=256)
    rare = [near_dedup.rarest(w, counts, 0.8)[0] for w in words]
    label = np.arange(len(texts)) // 2
    owner, sizes, bins = np.repeat(np.arange(len(texts)), [len(w) for w in rare]), np.array([len(w) for w in words]), np.stack([near_dedup.in_bins(h) for h in hashes])
    linked = {(i, j) for i, j in all_links(texts) if label[i] != label[j]}
    found = np.concatenate(list(near_dedup.rare_pairs(owner, np.concatenate(rare).view(np.int64), label, sizes, bins, 0.8)))
    found = {(min(x, y), max(x, y)) for x, y in found.tolist()}
    assert len(linked) > 50 and linked <= found and all(label[i] != label[j] for i, j in found)
    assert list(near_dedup.rare_pairs(np.zeros(0, np.int64), np.zeros(0, np.int64), label, sizes, bins, 0.8)) == []


def test_nodes_of_large_buckets_meet_once_for_all_buckets(spark, monkeypatch):
    """Rare and frequent words give what brute force gives, in few pairs and with no text for each bucket."""
    texts = passage_texts(60, 8)
    heavy = spark.createDataFrame([(i, i, t) for i, t in enumerate(texts)], "node long, label long, text string")
    root = list(range(len(texts)))
    linked = all_links(texts)
    for i, j in linked:
        root = [root[i] if c == root[j] else c for c in root]
    for frequent in (1 << 14, 8):
        monkeypatch.setattr(near_dedup, "FREQUENT", frequent)
        monkeypatch.setattr(near_dedup, "PART_WORDS", 200)
        words = near_dedup.rare_words(heavy, 0.8).cache()
        assert (words.filter("part < 0").count() > 0) == (frequent == 8) and words.filter("part >= 0").select("part").distinct().count() > 2
        given = [(r.a, r.b) for r in near_dedup.pairs_of_rare(words.filter("part >= 0"), 0.8).collect()]
        found = set(given)
        # Also pairs with words of several tasks in common come from one.
        assert len(found) == len(given)
        seen = near_dedup.mixed_buckets(words.filter("part < 0").selectExpr("explode(words) AS bucket", "node"), heavy.select("node", "label"))
        links = {(r.a, r.b) for r in near_dedup.links_of_frequent(seen, heavy.select("node", "text"), 0.8).collect()}
        assert links <= linked and (frequent == 8 or linked <= found)
        of = list(range(len(texts)))
        for i, j in links | (linked & found):
            of = [of[i] if c == of[j] else c for c in of]
        assert [of.index(c) for c in of] == [root.index(c) for c in root]
    # Texts of which a passage is three fifths: the square of their number were compared.
    own = [" ".join([f"p{k}" for k in range(30)] + [f"t{i}w{k}" for k in range(20)]) for i in range(600)]
    heavy = spark.createDataFrame([(i, i, t) for i, t in enumerate(own)], "node long, label long, text string")
    words = near_dedup.rare_words(heavy, 0.8)
    assert words is None or near_dedup.pairs_of_rare(words, 0.8).count() < 600 and words.count() < 600
    assert near_dedup.rare_words(heavy.limit(0), 0.8) is None


def test_texts_of_a_repeated_sentence_give_few_pairs(spark):
    """The sentence is three quarters of each text and fills its bins; what else they share is too little for a link."""
    rng = random.Random(12)
    texts = [" ".join([f"v{rng.randrange(2000)}" for _ in range(100)] + ["is", "onhe"] * 150) for _ in range(100)]
    for text in texts[:10]:
        words = text.split()
        for at in rng.sample(range(100), 40) + rng.sample(range(100, 400), 10):
            words[at] = f"v{rng.randrange(2000)}"
        texts.append(" ".join(words))
    heavy = spark.createDataFrame([(i, i, t) for i, t in enumerate(texts)], "node long, label long, text string")
    given = [(r.a, r.b) for r in near_dedup.pairs_of_rare(near_dedup.rare_words(heavy, 0.8), 0.8).collect()]
    linked = all_links(texts)
    assert {(i, 100 + i) for i in range(10)} <= linked <= set(given)
    # All but a few of the 5,995 pairs were given.
    assert len(given) < 300


def test_little_goes_with_each_rare_word(spark, monkeypatch):
    """What is known of a node went to each task of its words, and all words of earlier tasks: more for each task there was."""
    texts = passage_texts(40, 8)
    heavy = spark.createDataFrame([(i, i, t) for i, t in enumerate(texts)], "node long, label long, text string")
    monkeypatch.setattr(near_dedup, "PART_WORDS", 50)
    monkeypatch.setattr(near_dedup, "PART_CHECKED", 20)
    words = near_dedup.rare_words(heavy, 0.8)
    rows = words.collect()
    assert len(rows) > 4 * len(texts)
    assert sorted(r.node for r in rows if r.about) == sorted({r.node for r in rows})
    assert all(len(r.brief) == near_dedup.BRIEF_BINS // 2 and len(r.before) <= near_dedup.BEFORE for r in rows)
    given = [(r.a, r.b) for r in near_dedup.pairs_of_rare(words, 0.8).collect()]
    assert len(given) > 40 and len(set(given)) == len(given) and all_links(texts) <= set(given)


def test_brief_bins_bound_no_closer_than_all():
    rng = np.random.default_rng(3)
    hashes = [rng.integers(0, 1 << 63, n, dtype=np.uint64) for n in (0, 1, 40, 300, 3000)] + [np.full(500, 77, np.uint64)]
    bins = np.stack([near_dedup.in_bins(h) for h in hashes]).astype(np.int64)
    brief = near_dedup.from_brief(np.frombuffer(b"".join(near_dedup.in_brief(b) for b in bins.astype(np.int8)), np.uint8).reshape(len(bins), -1)).astype(np.int64)
    for h, got in zip(hashes, brief):
        counted = np.bincount((h % np.uint64(near_dedup.BRIEF_BINS)).astype(np.int64), minlength=near_dedup.BRIEF_BINS)
        assert got.tolist() == np.minimum(counted, near_dedup.BRIEF_MOST).tolist()
    assert all(np.abs(brief[i] - brief[j]).sum() <= np.abs(bins[i] - bins[j]).sum() for i in range(len(bins)) for j in range(i))


def test_classes_of_large_buckets_match_brute_force(spark, monkeypatch):
    texts = passage_texts(60, 10)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    plain = {r.doc_id: r.class_id for r in near_dedup.near_classes(docs).collect()}
    for frequent in (1 << 14, 8):
        monkeypatch.setattr(near_dedup, "LIGHT", 2)
        monkeypatch.setattr(near_dedup, "FREQUENT", frequent)
        got = {r.doc_id: r.class_id for r in near_dedup.near_classes(docs).collect()}
        for i, j in all_links(texts):
            assert got[i] == got[j]
        assert len(set(got.values())) <= len(set(plain.values()))
