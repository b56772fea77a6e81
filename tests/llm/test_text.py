import random
import re

import pytest

from codedreg.llm import language, pii, toxicity

EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
IP = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
CARD = re.compile(r"[0-9]([\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def plain(text):
    digits = lambda s: re.sub("[^0-9]", "", s)
    return {
        "email": [m.span() for m in EMAIL.finditer(text)],
        "ip": [m.span() for m in IP.finditer(text) if all(int(x) <= 255 for x in m[0].split("."))],
        "card": [m.span() for m in CARD.finditer(text) if 16 <= len(digits(m[0])) <= 19 and pii.luhn(digits(m[0]))],
        "phone": [m.span() for m in PHONE.finditer(text) if 8 <= len(digits(m[0])) <= 15],
    }


def test_plain_detectors_follow_the_patterns():
    draw = random.Random(1)
    bits = ["a", "B9", "@", ".", "x.y", "-", " ", "+", "(", ")", "1", "255", "256", "4111 1111 1111 1111", "4111-1111-1111-1111", "+1 (415) 555-1234", "é", "\n", "192.168.0.1", "joe@site.org", "00001.2.3.4"]
    for _ in range(4000):
        text = "".join(draw.choice(bits) for _ in range(draw.randrange(25)))
        assert pii.detect(text) == plain(text), text


@pytest.mark.parametrize(
    "text, kind, found",
    [
        ("write to john.doe [at] example (dot) com today", "email", "john.doe [at] example (dot) com"),
        ("write john at example dot com today", "email", "john at example dot com"),
        ("usеr@exаmple.com", "email", "usеr@exаmple.com"),
        ("ｊｏｈｎ＠example.com", "email", "ｊｏｈｎ＠example.com"),
        ("jo​hn@example.com", "email", "jo​hn@example.com"),
        ("call plus one four one five five five five one two three four now", "phone", "plus one four one five five five five one two three four"),
        ("pay " + "four " + "one " * 14 + "one", "card", "four " + "one " * 14 + "one"),
        ("at one nine two dot one six eight dot zero dot one", "ip", "one nine two dot one six eight dot zero dot one"),
        ("host one nine two . one six eight . zero . one up", "ip", "one nine two . one six eight . zero . one"),
        ("host 192.168.one.one up", "ip", "192.168.one.one"),
        ("mail john at example.com now", "email", "john at example.com"),
        ("mail joe @ site . org now", "email", "joe @ site . org"),
        ("mail joe -at- site -dot- com now", "email", "joe -at- site -dot- com"),
        ("mail joe_at_site_dot_com now", "email", "joe_at_site_dot_com"),
        ("call plus 1 415 five five five one two three four now", "phone", "plus 1 415 five five five one two three four"),
        ("call +١ ٤١٥ ٥٥٥ ١٢٣٤ now", "phone", "+١ ٤١٥ ٥٥٥ ١٢٣٤"),
    ],
)
def test_disguises(text, kind, found):
    _, full = pii.find_all(text)
    assert found in [text[a:b] for a, b in full[kind]]
    assert pii.mask_text(text, full) == text.replace(found, f"<{kind}>")


def test_ordinary_words_stay():
    for text in ("look at example.com", "it was found at shop.example.org today", "a look-at-me thing. Then", "chapter 1. two. three of 4", "x . y @ z", "rooms 1, 2, three, 4", "meet me at the shop dot", "one two three four five six seven eight", "at noon the dot com boom", "", "a" * 100_000, "1" * 50_000, "." * 50_000):
        assert pii.listed(pii.find_all(text)[1]) == ""


def test_recall_of_disguises():
    """Identifiers drawn at random, disguised in drawn ways, inside drawn words: nearly all are found whole."""
    draw = random.Random(8)
    spelled = ["zero", "one", "two", "three", "four", "five", "six", "seven", "eight", "nine"]
    word = lambda: "".join(draw.choice("bcdfglmnprstv") + draw.choice("aeiou") for _ in range(draw.randrange(2, 4)))
    total = caught = 0
    for _ in range(1500):
        kind = draw.choice(["email", "phone", "ip"])
        if kind == "email":
            at, dot = draw.choice([(" at ", " dot "), (" [at] ", " [dot] "), ("(at)", "(dot)"), (" @ ", " . "), (" -at- ", " -dot- "), ("_at_", "_dot_"), (" at ", "."), ("@", " dot "), ("＠", "."), (" <at> ", " (.) ")])
            own = f"{word()}{at}{word()}{dot}{draw.choice(['com', 'org', 'net'])}"
        elif kind == "phone":
            digits = [str(draw.randrange(10)) for _ in range(11)]
            own = draw.choice(["plus " + " ".join(spelled[int(d)] for d in digits), "plus " + "".join(digits[:4]) + " " + " ".join(spelled[int(d)] for d in digits[4:]), "+" + "".join(chr(0x660 + int(d)) for d in digits), "+" + "".join(chr(0xFF10 + int(d)) for d in digits)])
        else:
            parts = [draw.randrange(256) for _ in range(4)]
            say = lambda n: " ".join(spelled[int(d)] for d in str(n))
            own = draw.choice([" dot ".join(map(say, parts)), " . ".join(map(say, parts)), f"{parts[0]}.{parts[1]}.{spelled[parts[2] % 10]}.{spelled[parts[3] % 10]}"])
        text = f"{word()} {word()}, {own}, {word()}."
        total += 1
        caught += own in [text[a:b] for a, b in pii.find_all(text)[1][kind]]
    assert caught >= 0.95 * total


def test_many_plain_spans_in_one_disguise():
    text = "a@b.cc " * 30 + "joe at site dot org"
    base, full = pii.find_all(text)
    assert len(base["email"]) == 30 and set(base["email"]) <= set(full["email"]) and len(full["email"]) == 31


def test_pii_rows(spark):
    rows = [(1, "a@b.cc and 1.2.3.4", "x"), (2, None, "x"), (3, "", "x"), (None, "q at r dot com", "x")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, spans string")
    by = {r["doc_id"]: r for r in pii.find_pii(frame).collect()}
    assert by[1]["spans"] == "email:0:6,ip:11:18" and by[2]["spans"] == "" and by[None]["spans"] == "email:0:14" and by[None]["n_email"] == 0
    out = {r["doc_id"]: r["text"] for r in pii.masked(frame).collect()}
    assert out == {1: "<email> and <ip>", 2: None, 3: "", None: "<email>"}
    assert pii.masked(frame).columns == frame.columns and pii.find_pii(frame.limit(0)).count() == 0


def corpus(n=600):
    draw = random.Random(4)
    words = {"aa": ["lumo", "tira", "nola", "peri", "sato"], "bb": ["grund", "stein", "wacht", "brück", "zwerg"]}
    insults = ["blokhead", "grumfool"]
    rows = []
    for i in range(n):
        lang = "aa" if i % 2 else "bb"
        own = ["".join(draw.choice(words[lang]) for _ in range(draw.randrange(1, 3))) for _ in range(draw.randrange(5, 40))]
        toxic = int(draw.random() < 0.3)
        if toxic:
            own[draw.randrange(len(own))] = draw.choice(insults)
        rows.append((i, " ".join(own), lang, toxic))
    return rows


@pytest.fixture(scope="module")
def tables(spark):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, lang) for i, t, lang, _ in rows] + [(9001, None, None), (9002, "", "aa"), (9003, "123 !!", "bb"), (9004, "lumo tira " * 20000, None), (None, "lumo", "aa")], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, x) for i, _, _, x in rows] + [(9002, 1, None)], "doc_id long, quality int, toxic int")
    return docs, labels, {i: x for i, _, _, x in rows}


def test_language(spark, tables):
    docs, _, _ = tables
    model = language.fit(docs)
    rows = {r["doc_id"]: r for r in language.identify(docs, model).collect()}
    langs = {r["doc_id"]: r["lang"] for r in docs.collect()}
    held = [i for i, r in rows.items() if r["held_out"] and i is not None and i < 9000]
    assert held and sum(rows[i]["lang_pred"] == langs[i] for i in held) >= 0.97 * len(held)
    assert all(rows[i]["lang_pred"] == "und" and rows[i]["score"] == 0 for i in (9001, 9002, 9003))
    assert rows[9004]["lang_pred"] == "aa" and all(0 <= r["score"] <= 1 for r in rows.values())
    nothing = language.identify(docs, language.fit(docs.where("lang is null")))
    assert {r["lang_pred"] for r in nothing.collect()} == {"und"}
    assert language.identify(docs.limit(0), model).count() == 0


def test_unknown_words_fall_back():
    model = language.Model([("aa", 0, "lumo", 5), ("bb", 0, "stein", 5), ("aa", 3, "umo", 5), ("bb", 3, "tei", 5), ("aa", 1, "o", 1), ("bb", 1, "t", 1)])
    assert (model.word("lumo") == model.rows[0][model.tables[0]["lumo"]]).all()
    assert model.word("xumo").argmax() == 0 and model.word("xteix").argmax() == 1 and model.word("qt").argmax() == 1 and model.word("qqq") is None


def test_toxicity(spark, tables):
    docs, labels, truth = tables
    model = toxicity.fit(docs, labels)
    rows = {r["doc_id"]: r for r in toxicity.score_documents(docs, model).collect()}
    held = [i for i, r in rows.items() if r["held_out"] and i in truth]
    assert held and sum(rows[i]["predicted"] == truth[i] for i in held) >= 0.97 * len(held)
    assert all(0 <= r["score"] <= 1 for r in rows.values()) and rows[9001]["predicted"] == 0
    odd = ["lumo tira blok-he.ad nola", "lumo g r u m f o o l peri", "peri b1okhead tira", "nola blokheead sato", "nola blok head sato", "lumo tira,blokhead", "lumo tira nola peri"]
    found = toxicity.score_documents(spark.createDataFrame(list(enumerate(odd)), "doc_id long, text string"), model).collect()
    assert {r["doc_id"]: r["predicted"] for r in found} == {0: 1, 1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 0}
    again = toxicity.score_documents(docs, toxicity.fit(docs.repartition(7), labels.repartition(3))).collect()
    assert {r["doc_id"]: round(r["score"], 6) for r in again} == {i: round(r["score"], 6) for i, r in rows.items()}
    clash = docs.withColumn("score", docs["doc_id"]).withColumn("held_out", docs["lang"])
    assert sorted(map(str, toxicity.score_documents(clash, model).collect())) == sorted(map(str, rows.values()))
    assert toxicity.score_documents(docs.limit(0), model).count() == 0
    bare = toxicity.score_documents(docs, toxicity.fit(docs, labels.limit(0))).collect()
    assert {r["score"] for r in bare} == {0.0}


def written(parts):
    """Symbols of each sentence as (letters, marks as spaces)."""
    c, starts, size, owner = parts
    back = {toxicity.MARK: " "} | {i: chr(96 + i) for i in range(1, 27)}
    return [("".join(back.get(x, "?") for x in c[a : a + n].tolist()), o) for a, n, o in zip(starts.tolist(), size.tolist(), owner.tolist())]


def test_sentences():
    texts = ["You, id-iot!  Go a w a y now. 1d1ot sc0 ", "", "x", "one\ntwo? three.four", "É 5 $$ m0r0n"]
    assert written(toxicity.sentences(texts)) == [(" you idiot ", 0), (" go away now ", 0), (" diot sc ", 0), (" one ", 3), (" two ", 3), (" threefour ", 3), (" ? moron ", 4)]
    long = "ab " * 100
    parts = [x for x, _ in written(toxicity.sentences([long]))]
    assert all(len(x) <= toxicity.LONGEST for x in parts) and len(parts) > 5 and parts[0].startswith(" ab") and parts[-1].endswith("ab ")


def test_table_is_the_kernel():
    """Scores by a sentence's table equal kernel values by counting subsequences of whole sentences."""
    import itertools

    import numpy as np

    def vector(c):
        out = {}
        for at in itertools.combinations(range(len(c)), toxicity.ORDER):
            if at[-1] - at[0] < toxicity.SPAN:
                key = tuple(c[i] for i in at)
                out[key] = out.get(key, 0) + toxicity.DECAY ** (at[-1] - at[0] + 1)
        squares = sum(max(len(c) - p[-1], 0) * float(w) ** 2 for p, w in zip(toxicity.PLACES, toxicity.WEIGHTS))
        return {k: v / squares**0.5 for k, v in out.items()}

    draw = random.Random(6)
    texts = ["you idiot", "what a worthless scum", "xy z"] + ["".join(draw.choice("idot scumwrhl é") for _ in range(draw.randrange(4, 30))) for _ in range(30)]
    c, starts, size, owner = toxicity.sentences(texts)
    own = [c[a : a + n] for a, n in zip(starts, size)]
    sample = toxicity.Sample(np.concatenate(own).astype(np.uint8), size, np.arange(len(size)), np.zeros(len(size), int))
    values = toxicity.likeness(sample, np.arange(len(size)), np.arange(3))
    for i, s in enumerate(own):
        for j in range(3):
            a, b = vector(s.tolist()), vector(own[j].tolist())
            assert values[i, j] == pytest.approx(sum(v * b.get(k, 0) for k, v in a.items()), abs=1e-5)
    _, key, value = toxicity.sparse_rows(*sample.laid(np.array([0])))
    table = np.bincount(key, value, toxicity.KEYS).astype("float32")
    assert sample.margins(table) == pytest.approx(values[:, 0], abs=1e-5)


def test_toxicity_reads_every_letter(spark, tables):
    docs, labels, _ = tables
    model = toxicity.fit(docs, labels)
    calm = "lumotiranolasatoperi" * 8
    texts = [calm + "blokhead", calm[:70] + "blokhead" + calm, "lumo,tira,nola,sato,peri,lumo,tira,nola,sato,peri,lumo,tira,nola,sato,blokhead", calm, "lumo,tira_nola/sato.peri", "lumo tira nola. " * 40_000 + "you blokhead", "lumo tira nola. " * 40_000]
    found = toxicity.score_documents(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), model).collect()
    score = {r["doc_id"]: r["score"] for r in found}
    assert score[0] > score[3] and score[1] > score[3] and score[2] > score[4] and score[5] > score[6]


def test_toxicity_on_the_given_tables(spark):
    """Held out: figures of the README."""
    folder = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet")
    marked = labels.where("toxic is not null").groupBy("doc_id").agg({"toxic": "max"}).toDF("doc_id", "toxic")
    rows = toxicity.score_documents(docs, toxicity.fit(docs, labels)).where("held_out").join(marked, "doc_id").select("score", "predicted", "toxic").toPandas()
    rank, y = rows["score"].rank(), rows["toxic"]
    auc = (rank[y == 1].sum() - y.sum() * (y.sum() + 1) / 2) / (y.sum() * (1 - y).sum())
    caught = rows[(rows["predicted"] == 1) & (y == 1)].shape[0]
    assert auc > 0.94 and caught >= 0.85 * y.sum() and caught >= 0.8 * rows["predicted"].sum(), (auc, caught, rows["predicted"].sum(), y.sum())
