"""Each operator against brute force on small tables, with nulls, empty and long texts, ties, repeated rows and extra columns."""

import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from caseloom.llm import components, decontam, fingerprints, jaccard, language, licenses, packing, secrets, sentences, suffixes, toxicity
from caseloom.llm import kernels as K

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, hash string, n long, key string, _id int, p int"


def frame(spark, texts):
    """Documents with columns whose names clash with those inside the operators."""
    rows = [(i, t, "en" if t else None, None, len(t or ""), "h", 1, "k", 7, 8) for i, t in texts]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def texts():
    r = random.Random(4)
    vocab = ["".join(r.choices("abcdeé", k=r.randint(2, 7))) for _ in range(150)]
    say = lambda n: " ".join(r.choice(vocab) + r.choice(["", "", "", ".", ","]) for _ in range(n))
    base, passage = say(120), ". ".join(say(12) for _ in range(6)) + "."
    docs = [say(r.randint(1, 90)) for _ in range(25)]
    docs += [base, base, base.replace(vocab[0], "changed"), base[:-8], "", None, "   \n\t", "one", "two words", say(9) + " " + passage + " " + say(9), say(5) + ". " + passage, "x" * 5000, "ab " * 3000, say(4000)]
    return list(enumerate(docs)) + [(25, base), (None, base), (None, say(30))]


def by_id(df, *keys):
    return sorted((tuple(r) for r in df.select(*keys).collect()), key=str)


def test_words_and_hashes():
    s = next(K.slices(pa.array(["Ab c", None, "", "é ab"])))
    w = K.words(s, K.ALNUM)
    h = w.hashes()
    assert w.doc.tolist() == [0, 2, 2, 2, 4] and h[0] == h[3] and len(set(h.tolist())) == 3


def test_components(spark):
    edges = spark.createDataFrame([(5, 4), (4, 3), (3, 2), (9, 8), (7, 7), (8, 9)], "x long, y long")
    assert by_id(components.components(edges), "node", "root") == [(2, 2), (3, 2), (4, 2), (5, 2), (8, 8), (9, 8)]
    assert components.components(edges.limit(0)).count() == 0


def word_sets(docs, k=4):
    fold = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for _, t in docs:
        w = [x for x in re.split("[\x20\x09-\x0d]+", (t or "").translate(fold)) if x]
        yield {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def test_only_rows_in_question_pass_the_filter(spark):
    """All members pass, null ids too, and nearly no other row, so few texts are dealt out."""
    members = spark.createDataFrame([(i * 3,) for i in range(2000)] + [(None,)], "doc_id long")
    rows = spark.range(0, 60000).select(F.col("id").alias("doc_id")).unionByName(members)
    got = [r["doc_id"] for r in rows.where(jaccard.maybe(members, "doc_id")("doc_id")).collect()]
    assert set(got) >= {r["doc_id"] for r in members.collect()} and got.count(None) == 1 and 4001 <= len(got) < 6000
    assert rows.where(jaccard.maybe(members.limit(0), "doc_id")("doc_id")).count() == 0


@pytest.mark.parametrize("common", [0, 1])
def test_jaccard(spark, texts, monkeypatch, common):
    if common:
        monkeypatch.setattr(jaccard, "COMMON_LEAST", 2)
        monkeypatch.setattr(jaccard, "LOCAL_LEAST", 2)
        monkeypatch.setattr(jaccard, "FEW", 2)
        monkeypatch.setattr(jaccard, "BLOCK_DOCS", 2)
    sets = list(word_sets(texts))
    root = list(range(len(texts)))
    links = [0] * len(texts)

    def top(i):
        return i if root[i] == i else top(root[i])

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                links[i] += 1
                links[j] += 1
                root[max(top(i), top(j))] = min(top(i), top(j))
    least = {}
    for i, (d, _) in enumerate(texts):
        if d is not None:
            least[top(i)] = min(least.get(top(i), d), d)
    want = sorted(((d, len(sets[i]), least.get(top(i)) if sets[i] else d, links[i]) for i, (d, _) in enumerate(texts)), key=str)
    assert by_id(jaccard.link(frame(spark, texts).repartition(3)), "doc_id", "n_shingles", "component_id", "n_links") == want
    assert jaccard.link(frame(spark, [])).count() == 0


def test_jaccard_where_pairs_share_frequent_tokens(spark):
    """Linked pairs whose common tokens are mostly frequent ones share only half of their rare ones."""
    r = random.Random(6)
    say = lambda n: " ".join("".join(r.choices("abcdefgh", k=8)) for _ in range(n))
    docs = []
    for n, rare, common, k in ((600, 92, 48, 4), (1000, 160, 82, 4)):
        boiler = say(n - rare + 3)
        docs += [f"{boiler} {say(n)}" for _ in range(24)]
        for _ in range(k):
            start = f"{boiler} {say(common)} "
            docs += [start + say(rare - common), start + say(rare - common)]
    sets = list(word_sets(list(enumerate(docs))))
    want = [sum(100 * len(a & b) >= 85 * len(a | b) for b in sets) - 1 for a in sets]
    assert sum(want) == 16
    assert by_id(jaccard.link(frame(spark, list(enumerate(docs))).coalesce(1)), "doc_id", "n_links") == sorted(enumerate(want), key=str)
    rng = np.random.default_rng(0)
    for _ in range(3000):
        n, m = rng.integers(1, 60, 2)
        least = -(-85 * (n + m) // 185)
        x = rng.permutation(200)
        inter = int(min(n, m, least + rng.integers(0, 3)))
        if 100 * inter < 85 * (n + m - inter):
            continue
        a, b = np.sort(x[:n]), np.sort(np.append(x[:inter], x[n : n + m - inter]))
        prefix = [t[: len(t) - -(-85 * len(t) // 100) + 1] for t in (a, b)]
        assert len(np.intersect1d(*prefix)) >= jaccard.needed(np.array([n]), np.array([m]), 85)[0]


@pytest.mark.parametrize(("length", "gram"), [(100, 40), (20, 6)])
def test_suffixes(spark, texts, length, gram):
    docs = sorted(((d, t or "") for d, t in texts if d is not None and (d, t) != (25, texts[25][1])), key=lambda x: x[0])
    seen, want = set(), []
    for d, t in docs:
        b = t.encode()
        cover = np.zeros(len(b), bool)
        for p in range(len(b) - length + 1):
            w = b[p : p + length]
            if w in seen:
                cover[p : p + length] = True
            seen.add(w)
        kept = bytes(np.frombuffer(b, np.uint8)[~cover])
        want.append((d, len(b), int(cover.sum()), int((np.diff(cover.astype(int), prepend=0) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    got = suffixes.dedup(frame(spark, docs).repartition(3), length, gram)
    assert by_id(got, "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == sorted(want, key=str)
    assert suffixes.dedup(frame(spark, [])).count() == 0


def test_sentences(spark, texts):
    got = {r["doc_id"]: r for r in sentences.dedup(frame(spark, [x for x in texts if x[0] is not None][:-1]).repartition(3)).collect()}
    assert got[25]["n_removed"] == 0 and got[26]["text"] == ""
    assert got[35]["n_removed"] > 3 and got[34]["n_removed"] == 0 and got[30]["n_sentences"] == 0
    rows = [(1, "A b c d e f g h i. J k l m n o p q r."), (2, "Zz. A b c d e f g h i. J k l m n o p q r. Y y."), (None, "A b c d e f g h i. J k l m n o p q r."), (1, "A b c d e f g h i. J k l m n o p q r.")]
    assert sorted((str(r["doc_id"]), r["n_removed"]) for r in sentences.dedup(frame(spark, rows)).collect()) == [("1", 0), ("1", 0), ("2", 2), ("None", 2)]
    assert sentences.dedup(frame(spark, [])).count() == 0


def test_long_sentences_at_any_offset(spark):
    r = random.Random(12)
    say = lambda n: " ".join("".join(r.choices("abcdefgh", k=7)) for _ in range(n))
    passages = [say(52) for _ in range(20)]
    rows = [(i, f"{say(20)} {p} {say(20)}") for i, p in enumerate(passages)] + [(100 + i, f"{say(21 + i % 15)} {p} {say(20)}") for i, p in enumerate(passages)]
    got = {x["doc_id"]: x for x in sentences.dedup(frame(spark, rows).repartition(3)).collect()}
    for i, p in enumerate(passages):
        assert got[i]["n_removed"] == 0
        assert 16 <= len(rows[20 + i][1].split()) - len(got[100 + i]["text"].split()) <= len(p.split())


def test_spans_do_not_depend_on_the_slice():
    text = "A b c. D e f. " * 3
    alone, among = (sentences.runs(next(K.slices(pa.array(x)))) for x in ([text], [text, "g h. " * 20]))
    assert len(alone[2]) == (among[1][among[2]] == 0).sum()


def test_simhash(spark, texts):
    docs = [(i * 700, t) for i, t in texts if i is not None][:-1]
    got = {r["doc_id"]: r for r in fingerprints.edited_likeness(frame(spark, docs)).collect()}
    assert len(got) == len(docs)
    for k, (d, t) in enumerate(docs):
        t, after = t or "", docs[(k + 1) % len(docs)][1] or ""
        m = len(t) // 4
        assert got[d]["n_chars"] == len(t)
        assert got[d]["edited_sha256"] == hashlib.sha256((t[: len(t) - m] + after[:m]).encode()).hexdigest()
    assert got[25 * 700]["fingerprint"] == got[26 * 700]["fingerprint"] and got[25 * 700]["near_next"] == 1.0
    one = fingerprints.edited_likeness(frame(spark, [(None, "a b c d e f g h")])).collect()
    assert len(one) == 1 and one[0]["near_next"] == 1.0
    assert fingerprints.edited_likeness(frame(spark, [])).count() == 0


def brute_print(spark, text):
    """The fingerprint of a text, voted bit by bit."""
    w = re.split("[ \t\n\x0b\f\r]+", text)
    pairs = [(a, b) for a, b in zip(w, [*w[1:], None], strict=True)]
    rows = spark.createDataFrame(pairs, "a string, b string").select(F.xxhash64("a", "b"), F.xxhash64("b", "a", F.lit(7)), F.length("a"), F.coalesce(F.length("b"), F.lit(0))).collect()
    out = []
    for k in range(2):
        bits = 0
        for i in range(64):
            vote = sum((1 if r[k] >> i & 1 else -1) * min(r[2] + r[3], 24) for r in rows)
            bits |= (vote > 0) << i
        out.append(bits)
    return out


def test_fingerprints_by_brute_force(spark, texts):
    docs = [(i * 50, t) for i, t in texts if i is not None][:-1]
    docs += [(5000, docs[2][1] + " tail"), (5001, docs[2][1] + " tail"), (5002, "zz " + docs[2][1])]
    got = {r["doc_id"]: r for r in fingerprints.edited_likeness(frame(spark, docs).repartition(3)).collect()}
    prints = {}
    for k, (d, t) in enumerate(docs):
        t, after = t or "", docs[(k + 1) % len(docs)][1] or ""
        m = len(t) // 4
        own, edit = brute_print(spark, t), brute_print(spark, t[: len(t) - m] + after[:m])
        prints[d] = (own, edit)
        assert got[d]["fingerprint"] == "%016x%016x" % tuple(own) and got[d]["edited_fingerprint"] == "%016x%016x" % tuple(edit)
    apart = lambda a, b: sum((x ^ y).bit_count() for x, y in zip(a, b, strict=True))
    like = lambda n: max(0.0, np.cos(np.pi * n / 128))
    for k, (d, _) in enumerate(docs):
        own, edit = prints[d]
        assert got[d]["near_edited"] == pytest.approx(like(apart(own, edit)), abs=1e-8)
        assert got[d]["near_next"] == pytest.approx(like(apart(own, prints[docs[(k + 1) % len(docs)][0]][0])), abs=1e-8)
        near = [x for x in prints if apart(own, prints[x][0]) <= fingerprints.RADIUS]
        assert (got[d]["n_near"], got[d]["near_id"]) == ((len(near) - 1, min(near)) if d % 100 == 0 else (None, None))


@pytest.mark.parametrize(("radius", "spare"), [(3, 2), (6, 2), (2, 1)])
def test_permuted_tables(spark, radius, spare):
    r = random.Random(1)
    base = [(r.getrandbits(64), r.getrandbits(64)) for _ in range(30)]
    for a, b in base[:20]:
        for n in range(1, radius + 2):
            x = a | b << 64
            for bit in r.sample(range(128), n):
                x ^= 1 << bit
            base.append((x & (2**64 - 1), x >> 64))
    signed = lambda x: x - 2**64 if x >= 2**63 else x
    df = spark.createDataFrame([(signed(a), signed(b)) for a, b in base], "f0 long, f1 long")
    want = sorted((signed(a), signed(b), signed(c), signed(d)) for a, b in base for c, d in base if (a ^ c).bit_count() + (b ^ d).bit_count() <= radius)
    assert by_id(fingerprints.within(df, df, radius, spare), "f0", "f1", "q0", "q1") == sorted(want, key=str)


def test_licenses(spark):
    rows = [(1, "Released under the MIT License. See mit  license"), (2, "No word here"), (3, None), (4, "GNU General-Public\nLICENSE, version 3"), (5, "permitlicense apache LICENSE"), (6, "is licensed under CC BY-NC 4.0."), (7, "SPDX-License-Identifier: BSD-3-Clause")]
    got = {r["doc_id"]: r for r in licenses.scan(frame(spark, rows)).collect()}
    assert (got[1]["n_words"], got[1]["n_base"], got[1]["first_word"], got[1]["last_word"], got[1]["labels"]) == (8, 2, 3, 6, "mit")
    assert (got[2]["n_base"], got[2]["first_word"], got[2]["labels"], got[2]["score"]) == (0, None, "", 0.0) and got[3]["n_words"] == 0
    assert got[4]["base_labels"] == "gpl" and "gpl-3.0" in got[4]["labels"] and got[5]["base_labels"] == "apache" and got[6]["labels"] == "cc-by-nc" and got[7]["labels"] == "bsd-3-clause"
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    text = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in licenses.scan(docs).collect():
        w = re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", text[r["doc_id"]].encode().lower())
        at = [i for i in range(len(w)) for p in (b"mit license", b"apache license", b"general public license") if w[i : i + len(p.split())] == p.split()]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(w), len(at), min(at, default=None), max(at, default=None))
    assert 200 <= len(licenses.rules()) and licenses.scan(frame(spark, [])).count() == 0


def test_license_gate_and_suppression(spark):
    """The gate never loses what the rules find, and what stands is what brute force leaves of all matches."""
    seps = [" ", "    ", "-", "\n\t ", " . "]
    names = [n for line in licenses.FAMILIES for part in line.split(" | ")[2:] for n in part.split(";")] + [p for _, _, p in licenses.NOTICES]
    plain = [re.sub(r"\(\?![^)]*\)|[\[\]^$]", "", re.sub(r"\(\?:([^()|]*)(?:\|[^()]*)?\)\??", r"\1", n)) for n in names]
    rows = []
    for i, n in enumerate(plain):
        for k, sep in enumerate(seps):
            rows.append((len(rows), f"x {('licensed under ' if (i + k) % 3 == 0 else '')}{n.strip()} licence".replace(" ", sep).upper() if k % 2 else f"SPDX-License-Identifier: {n.strip()}".replace(" ", sep)))
    got = {r["doc_id"]: r for r in licenses.scan(frame(spark, rows)).collect()}
    for i, t in rows:
        joined = b" ".join(re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t.encode().lower()))
        every = []
        for r in licenses.rules():
            for m in r.pattern.finditer(joined):
                if r.keyword in joined:
                    a = joined[: m.start()].count(b" ")
                    every.append((r.priority, a, a + m.group().count(b" ") + 1, r.label))
        # Suppressed: inside one of higher priority, or inside a longer or equal one of the same that comes first.
        every.sort(key=lambda x: (x[0], x[1] - x[2], x[1], x[3]))
        stand = []
        for x in every:
            if not any(y[1] <= x[1] and x[2] <= y[2] for y in stand):
                stand.append(x)
        base = {lab for p, lab in (("mit license", "mit"), ("apache license", "apache"), ("general public license", "gpl")) if f" {p} " in f" {joined.decode()} "}
        assert got[i]["labels"] == ",".join(sorted({x[3] for x in stand} | base)), t
    assert sum(1 for r in got.values() if r["labels"]) > 100


def test_toxic_pairs():
    """A word that is neutral by itself and toxic beside an insult is kept, and its pair tells."""
    rng = np.random.default_rng(3)
    sets, labels = [], []
    for i in range(1200):
        insult, group = i % 2, i // 2 % 2
        noise = rng.integers(100, 400, 12)
        sets.append(np.unique(np.concatenate([noise, [7] * insult, [9] * group]).astype(np.uint32)))
        labels.append(float(insult and group))
    m = toxicity.fit(sets, np.array(labels))
    score = lambda *t: float(toxicity.sigmoid(m.raw(m.slot[list(t)], np.zeros(len(t), np.int64), 1))[0])
    assert score(7, 9) > 0.7 > 0.5 > max(score(7), score(9))


def test_secrets(spark):
    r = random.Random(3)
    token = "".join(r.choices("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", k=44))
    rows = [(1, "é PassWord = 'abcdefgh1234' token: short"), (2, "AKIA" + "B7" * 8 + " 0123456789abcdef0"), (3, None), (4, f"é value {token} end"), (5, "this_is_an_ordinary_identifier_name and/some/path/to/a/file-2024"), (6, "token:password: abcdefghijklmnop")]
    model = secrets.fit(spark.read.parquet(f"{SF}/documents.parquet"))
    got = {x["doc_id"]: x for x in secrets.scan(frame(spark, rows), model).collect()}
    assert got[1]["spans"] == "assign:2:26" and got[1]["base_sha256"] == hashlib.sha256(b"assign:2:26").hexdigest()
    assert got[2]["spans"] == "access:0:20,hex:21:38" and got[3]["spans"] == "" and got[3]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    assert got[4]["spans"] == f"markov:8:{8 + len(token)}" and got[5]["spans"] == "" and got[6]["n_assign"] == 0
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    text = {x["doc_id"]: x["text"] for x in docs.collect()}
    for x in secrets.scan(docs, model).collect():
        found = secrets.base_spans(text[x["doc_id"]])
        assert [x["n_assign"], x["n_access"], x["n_hex"]] == [sum(f[1] == k for f in found) for k in range(3)]
    cut = {x["doc_id"]: x for x in secrets.redact(frame(spark, rows), model).collect()}
    assert cut[4]["text"] == "é value [SECRET] end" and cut[4]["n_chars"] == len(cut[4]["text"]) and cut[3]["text"] is None
    assert secrets.scan(frame(spark, []), model).count() == 0


def test_secrets_around_base_spans(spark):
    r = random.Random(14)
    letters = "".join(r.choices("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ", k=40))
    model = secrets.fit(spark.read.parquet(f"{SF}/documents.parquet"))
    rows = frame(spark, [(1, f"see {letters[:20]}Q0123456789abcdef0Q{letters[20:]} end"), (2, "getHttpConnectionFactoryFromConfig")])
    assert {x["doc_id"]: x["text"] for x in secrets.redact(rows, model).collect()} == {1: "see [SECRET] end", 2: "getHttpConnectionFactoryFromConfig"}


def test_language(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    m = language.fit(language.sample(docs))
    rows = language.identify(docs, m).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r["lang"] == r["lang_pred"] for r in rows]) > 0.95 and all(0 <= r["score"] <= 1 for r in rows)
    odd = {r["doc_id"]: r for r in language.identify(frame(spark, [(1, None), (2, "123 — 45"), (3, "the and of is"), (4, "")]), m).collect()}
    assert [odd[k]["lang_pred"] for k in (1, 2, 4)] == ["und"] * 3 and odd[3]["lang_pred"] == "en"
    scores = np.array([[0, -5, -5], [0, -5, -5], [-5, 0, -5], [-5, 0, -5], [-5, -5, 0]], float)
    paths = [(p, scores[range(5), p].sum() - 4 * (np.diff(p) != 0).sum()) for p in np.ndindex(3, 3, 3, 3, 3)]
    assert language.viterbi(scores, 4).tolist() == list(max(paths, key=lambda x: x[1])[0])
    assert language.keep_identified(frame(spark, [(1, None), (3, "the and of is")]), m).count() == 1
    assert language.identify(frame(spark, []), language.fit([])).count() == 0


def test_language_rejects_what_it_has_not_learned(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    m = language.fit(language.sample(docs))
    r = random.Random(8)
    gibberish = " ".join("".join(r.choices("abcdefghijklmnopqrstuvwxyz", k=r.randint(2, 9))) for _ in range(30))
    rows = [(1, "Это простой русский текст про кошек и собак"), (2, "这是一个中文句子"), (3, gibberish), (4, "the and of is")]
    assert [x["doc_id"] for x in language.keep_identified(frame(spark, rows), m).collect()] == [4]
    assert {x["lang_pred"] for x in language.identify(frame(spark, rows[:3]), m).collect()} == {"und"}
    held = docs.where(K.crc_mod("doc_id", 5) == 0)
    assert language.keep_identified(held, m).count() == language.identify(held, m).where("spans[0] IS NOT NULL").count() >= 0.995 * held.count()


def test_language_path_over_two_others(spark, monkeypatch):
    """Two other languages gain twice for one change."""
    scores = np.array([[0, -6, -2.9]] * 4 + [[-6, 0, -2.9]] * 4)
    model = language.Model(["a", "b", "c"], None, None, None, None, -np.inf)
    monkeypatch.setattr(language, "word_scores", lambda s, m: (K.words(s, K.LETTERS), scores, np.zeros(8)))
    (_, score, spans), = language.label(next(K.slices(pa.array(["a b c d e f g h"]))), model)
    assert spans == [(0, 4, "a"), (4, 8, "b")] and score < 1
    assert language.viterbi(scores).tolist() == [0] * 4 + [1] * 4


def test_toxicity(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    m = toxicity.fit(*toxicity.sample(docs, labels))
    rows = toxicity.predict(docs, m).join(labels, "doc_id").where("held_out").collect()
    pos, neg = [r["score"] for r in rows if r["toxic"]], [r["score"] for r in rows if not r["toxic"]]
    assert np.mean([p > n for p in pos for n in neg]) > 0.8
    odd = toxicity.predict(frame(spark, [(1, None), (2, ""), (None, "stupid idiot")]), m).collect()
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in odd)
    assert [r["held_out"] for r in odd[:2]] == [zlib.crc32(str(i).encode()) % 3 == 1 for i in (1, 2)]
    s = next(K.slices(pa.array(["x y z stupid x"])))
    t, _ = toxicity.terms(s)
    r = [k for k in sorted(set(m.slot[t].tolist())) if k < len(m.weights) - 1]
    pairs = sum(float(m.vectors[a] @ m.vectors[b]) for i, a in enumerate(r) for b in r[:i])
    assert m.score(s)[0] == pytest.approx(toxicity.sigmoid(np.array([m.bias + m.weights[r].sum() + pairs]))[0])
    assert toxicity.predict(frame(spark, []), toxicity.fit([], np.zeros(0))).count() == 0


def test_decontamination(spark, texts):
    r = random.Random(9)
    word = lambda: "".join(r.choices("aeioubcdfgst", k=7))
    item = [word() for _ in range(36)]
    near = [word() if i % 5 == 0 else w for i, w in enumerate(item)]
    other = lambda n: " ".join(word() for _ in range(n))
    rows = [(1, other(80) + " " + " ".join(item) + " " + other(70)), (2, other(30) + " " + " ".join(near) + " " + other(9)), (3, other(200)), (4, None), (5, " ".join(r.sample(item, 36)))]
    bench = spark.createDataFrame([(7, " ".join(item)), (8, other(30)), (9, None), (10, "")], "item_id long, text string")
    docs = frame(spark, rows)
    assert by_id(decontam.contaminated(docs, bench), "doc_id", "item_id") == [(1, 7), (2, 7)]
    assert sorted(x["doc_id"] for x in decontam.clean(docs, bench).collect()) == [3, 4, 5]
    assert decontam.contaminated(docs, bench.limit(0)).count() == 0 and decontam.contaminated(docs.limit(0), bench).count() == 0
    a, b = np.array([1, 2, 3, 4, 2]), np.array([2, 4, 3, 2, 9])
    assert decontam.lcs(a, b) == 3


def test_decontamination_of_many_items(spark, monkeypatch):
    """Far more passages than the rank has directions."""
    monkeypatch.setattr(decontam, "RANK", 8)
    r = random.Random(10)
    vocab = ["".join(r.choices("aeioubcdfgst", k=6)) for _ in range(900)]
    items = [r.choices(vocab, k=r.randint(20, 59)) for _ in range(400)]
    edited = lambda w: [r.choice(vocab) if r.random() < 0.2 else x for x in w[:-8]] + w[-8:]
    rows = [(i, " ".join(r.choices(vocab, k=50) + (edited(w) if i % 2 else w) + r.choices(vocab, k=50))) for i, w in enumerate(items[:60])]
    bench = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(items)], "item_id long, text string")
    assert by_id(decontam.contaminated(frame(spark, rows), bench), "doc_id", "item_id") == sorted(((i, i) for i in range(60)), key=str)


def test_decontamination_without_the_end(spark):
    r = random.Random(11)
    word = lambda: "".join(r.choices("aeioubcdfgst", k=7))
    item = [word() for _ in range(59)]
    other = lambda n: [word() for _ in range(n)]
    weak = [w if i % 3 else word() for i, w in enumerate(item[:51])]
    rows = [(1, other(40) + item[:51] + other(40)), (2, other(30) + item[:51]), (3, other(40) + item[13:43] + other(40)), (4, other(40) + weak + other(40)), (5, other(40) + weak + item[51:]), (6, item[:12] + other(60))]
    found = decontam.contaminated(frame(spark, [(d, " ".join(w)) for d, w in rows]), spark.createDataFrame([(7, " ".join(item))], "item_id long, text string"))
    assert by_id(found, "doc_id", "item_id") == [(1, 7), (2, 7), (3, 7), (5, 7)]


def test_packing(spark, texts):
    path = public_tokenizers.path("word_bpe_49k.json")
    from tokenizers import Tokenizer

    model = Tokenizer.from_file(path)
    odd = ["It's a TEST x\x85y ́a 12 <|endoftext|> b", "a\x1cb", "ΑΣ ΟΔΟΣ fi İx é Éa. A.B. x.,", "can't 's", "　日本 語"]
    docs = texts + [(100 + i, t) for i, t in enumerate(odd)]
    got = packing.pack(packing.pieces(frame(spark, docs).repartition(3), path)).collect()
    want = []
    for d, t in docs:
        ids = model.encode(t or "", add_special_tokens=False).ids + [0]
        want += [(d, k, a, len(p), zlib.crc32(np.array(p, "<u4").tobytes())) for k, a in enumerate(range(0, len(ids), 2048)) for p in [ids[a : a + 2048]]]
    assert sorted(((*r[:5],) for r in got), key=str) == sorted(want, key=str)
    bins = {}
    for r in got:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for v in bins.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 2048
    assert len(bins) <= -(-sum(r["length"] for r in got) // 2048) + 3
    assert packing.Encoder(path, 3)([t or "" for _, t in docs]) == packing.Encoder(path)([t or "" for _, t in docs])
    assert packing.pack(packing.pieces(frame(spark, []), path)).count() == 0


def test_plan_places_every_item():
    r = random.Random(2)
    for _ in range(30):
        cap = r.choice([10, 64, 2048])
        counts = {n: r.randint(1, 40) for n in r.sample(range(1, cap + 1), min(cap, 9))}
        out, bins = packing.plan(counts, cap)
        fill, placed = {}, dict.fromkeys(counts, 0)
        for n, rank, first, b, each, at in sorted(out, key=lambda x: x[1]):
            placed[n] += b * each
            for s in range(first, first + b):
                fill.setdefault(s, []).extend((at + k * n, n) for k in range(each))
        assert placed == counts and set(fill) == set(range(bins))
        for v in fill.values():
            at = 0
            for o, n in sorted(v):
                assert o == at
                at += n
            assert at <= cap


def test_dedup_stage_keeps_one_row_of_each_group(spark):
    import corpus_pipeline

    r = random.Random(13)
    say = lambda: " ".join("".join(r.choices("abcdefgh", k=7)) for _ in range(60))
    a, b, c, d, e, f = (say() for _ in range(6))
    rows = [(None, a), (1, a), (None, b), (None, c), (5, a + " end"), (5, d), (9, e), (9, e), (None, f), (None, f), (None, f + " end"), (7, None), (None, "")]
    kept = corpus_pipeline.dedup_stage(spark, frame(spark, rows).repartition(3), SF)
    assert kept.columns == frame(spark, []).columns
    got = by_id(kept, "doc_id", "text")
    last = [x for x in got if x[1] in (f, f + " end")]
    assert len(last) == 1
    assert sorted((x for x in got if x not in last), key=str) == sorted([(1, a), (None, b), (None, c), (5, d), (9, e), (7, None), (None, "")], key=str)


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = [docs]
    for _, stage in corpus_pipeline.STAGES[:-1]:
        kept.append(K.durable(stage(spark, kept[-1], SF)))
        assert kept[-1].columns == docs.columns
    groups = {r["doc_id"]: r["component_id"] for r in jaccard.link(kept[1]).collect()}
    assert {r["doc_id"] for r in kept[2].collect()} == {d for d, c in groups.items() if d == c}
    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    assert not [r for r in kept[3].collect() if any(i in r["text"] for i in items)]
    assert kept[4].count() == kept[3].count() and not [r for r in kept[4].collect() if secrets.base_spans(r["text"])]
    out = corpus_pipeline.run(spark, SF)
    assert {r["doc_id"] for r in out.select("doc_id").distinct().collect()} == {r["doc_id"] for r in kept[4].collect()}


def test_packing_encoder_forgets_only_when_idle():
    text = "Known chunks, and known chunks again"
    e = packing.Encoder(public_tokenizers.path("word_bpe_49k.json"))
    with e:
        first = e([text])
        e.forget()
        assert e.ids
    e.timer.cancel()
    e.forget()
    assert not e.ids and e([text]) == first == [e.encode(text)]
