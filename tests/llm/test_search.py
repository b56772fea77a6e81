import math
import random

import numpy as np
import pytest

from codedreg.llm import fingerprints, jaccard, linededup, topk
from codedreg.llm.components import connected_components


def brute_top(rows, every, k):
    ok = {i: [math.floor(64 * x) for x in v] for i, v in rows if v is not None and all(x is not None and math.isfinite(x) for x in v)}
    out = []
    for q in ok:
        if q % every == 0:
            scored = sorted((-sum(a * b for a, b in zip(ok[q], v)), i) for i, v in ok.items() if i != q)[:k]
            out += [(q, n + 1, i, -s) for n, (s, i) in enumerate(scored)]
    return sorted(out)


@pytest.mark.parametrize("kind", ["random", "ties", "few", "negative"])
def test_top_k(spark, kind):
    rng = np.random.default_rng(4)
    n = 12 if kind == "few" else 300
    rows = [(i, rng.normal(size=6).tolist()) for i in range(n)]
    if kind == "ties":
        rows = [(i, [0.5] * 6 if i % 3 else [float(i % 5)] * 6) for i in range(n)]
    if kind == "negative":
        rows = [(i, (-np.abs(rng.normal(size=6)) * (1 if i % 20 else -1)).tolist()) for i in range(n)]
    rows += [(1000, None), (1020, [1.0, None, 0.0]), (1040, [float("nan")] * 6), (1060, [float("inf")] * 6)]
    frame = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<double>, score string").repartition(7)
    vectors = topk.integer_vectors(frame)
    got = sorted(tuple(r) for r in topk.top_k(topk.queries_of(vectors, 20), vectors, 20).collect())
    assert got == brute_top(rows, 20, 20)


def test_top_k_of_nothing(spark):
    frame = spark.createDataFrame([], "vec_id long, embedding array<float>")
    vectors = topk.integer_vectors(frame)
    assert topk.top_k(topk.queries_of(vectors, 20), vectors).count() == 0


def test_components(spark):
    rng = random.Random(5)
    links = [(rng.randrange(400), rng.randrange(400)) for _ in range(250)] + [(1000, 1000 + i) for i in range(50)] + [(2000 + i, 2001 + i) for i in range(60)]
    parent = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: find(x) for a, b in links for x in (a, b) if a != b}


def documents(n, seed, words=(0, 60)):
    rng = random.Random(seed)
    texts = []
    for _ in range(n):
        if texts and rng.random() < 0.6:
            own = rng.choice(texts).split(" ")
            for _ in range(rng.randrange(4)):
                own[rng.randrange(len(own))] = rng.choice("abcdefgh")
            texts.append(" ".join(own))
        else:
            texts.append(" ".join(rng.choice("abcdefghijklmnopqrstuvw") + str(rng.randrange(3)) for _ in range(rng.randrange(*words))))
    return texts


def word_sets(texts, k):
    out = []
    for t in texts:
        low = (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", low) if x]
        out.append({tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set()))
    return out


def brute_components(ids, sets, percent):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in zip(ids, sets):
        for j, b in zip(ids, sets):
            if i < j and a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = find(i), find(j)
                parent[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}


@pytest.mark.parametrize("k, percent, seed", [(4, 85, 1), (5, 80, 2), (4, 85, 3)])
def test_jaccard(spark, k, percent, seed):
    texts = documents(250, seed) + [None, "", "   \n", "One", "one", "one two three", "ONE two  three", "É x y z w", "é x y z w", "long words here " * 3000]
    ids = [i * 3 + 1 for i in range(len(texts))]
    frame = spark.createDataFrame([(i, t, "s") for i, t in zip(ids, texts)] + [(None, "one", "s"), (1, texts[0], "s")], "doc_id long, text string, rep string").repartition(5)
    rows = jaccard.jaccard_components(frame, k, percent).collect()
    sets = word_sets(texts, k)
    named = [r for r in rows if r["doc_id"] is not None]
    assert len(named) == len(ids) and len(rows) == len(ids) + 1
    assert {r["doc_id"]: r["n_shingles"] for r in named} == {i: len(s) for i, s in zip(ids, sets)}
    assert {r["doc_id"]: r["component_id"] for r in named} == brute_components(ids, sets, percent)


def test_jaccard_hot_group(spark, monkeypatch):
    """A large group of near copies that are not all alike, over small blocks."""
    monkeypatch.setattr(jaccard, "SMALL", 10)
    monkeypatch.setattr(jaccard, "BLOCK", 40)
    monkeypatch.setattr(jaccard, "FREQUENT", 3)
    rng = random.Random(8)
    base = [f"w{i}" for i in range(80)]
    texts = []
    for _ in range(150):
        own = list(base)
        for _ in range(rng.randrange(7)):
            own[rng.randrange(80)] = f"v{rng.randrange(30)}"
        texts.append(" ".join(own))
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(frame).collect()}
    assert got == brute_components(list(range(150)), word_sets(texts, 4), 85)


def test_patterned_words_do_not_collide(spark):
    """A word that follows the Thue-Morse sequence and its complement, beside ordinary words and among long ones."""
    morse = "".join("ab"[bin(i).count("1") % 2] for i in range(1024))
    other = morse.translate(str.maketrans("ab", "ba"))
    texts = [morse, other, f"x y {morse} z w", f"x y {other} z w", "a" * 70 + "b" + "a" * 70, "a" * 71 + "b" + "a" * 69, morse]
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(frame).collect()}
    assert got == brute_components(list(range(len(texts))), word_sets(texts, 4), 85) and got[1] == 1 and got[6] == 0


@pytest.mark.parametrize("level, small, block", [(0, 4, 16), (1, 256, 2048)])
def test_split_columns_lose_no_link(spark, monkeypatch, level, small, block):
    """Many documents share their rarest shingles, and columns are split from the first class of frequency on."""
    monkeypatch.setattr(jaccard, "PART_LEVEL", level)
    monkeypatch.setattr(jaccard, "SMALL", small)
    monkeypatch.setattr(jaccard, "BLOCK", block)
    monkeypatch.setattr(jaccard, "ROWS_TOGETHER", 8)
    rng = random.Random(77)
    base = [f"w{i}" for i in range(60)]
    texts = []
    for i in range(160):
        own = list(base)
        for _ in range(rng.randrange(5)):
            own[rng.randrange(60)] = f"v{rng.randrange(12)}"
        texts.append(" ".join(own[: 60 - rng.randrange(6)]))
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(frame).collect()}
    assert got == brute_components(list(range(160)), word_sets(texts, 4), 85)


def test_jaccard_of_nothing(spark):
    assert jaccard.jaccard_components(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def brute_lines(texts):
    where, order = {}, []
    for d, t in texts:
        for i, line in enumerate((t or "").split("\n")):
            if line.strip():
                if line not in where:
                    order.append(line)
                where.setdefault(line, []).append((d, i))
    parent = {x: x for x in order}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in order:
        for b in order:
            if a < b and linededup.alike(a, b):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    keep = {}
    for line in order:
        c = find(line)
        keep[c] = min(keep.get(c, (1 << 60, 0)), min(where[line]))
    kept = set(keep.values())
    return {d: None if t is None else "\n".join(x for i, x in enumerate(t.split("\n")) if not x.strip() or (d, i) in kept) for d, t in texts}


def test_lines(spark):
    rng = random.Random(9)
    lines = [" ".join(rng.choice(["alpha", "beta", "gamma", "delta", "omega"]) + str(rng.randrange(90)) for _ in range(rng.randrange(1, 20))) for _ in range(120)]
    lines += [x[:-1] + "!" for x in lines[:40]] + ["x", "y", "", "  ", "tiny"]
    texts = [(i, "\n".join(rng.choice(lines) for _ in range(rng.randrange(0, 6)))) for i in range(150)] + [(500, None), (501, ""), (502, "a long line " * 2000), (503, "A long  line " * 2000)]
    frame = spark.createDataFrame([(i, t, "s") for i, t in texts] + [(None, lines[0], "s")], "doc_id long, text string, drop string").repartition(5)
    out = linededup.dedup_lines(frame)
    assert out.columns == frame.columns
    rows = out.collect()
    assert {r["doc_id"]: r["text"] for r in rows if r["doc_id"] is not None} == brute_lines(texts)
    assert [r["text"] for r in rows if r["doc_id"] is None] == [lines[0]]
    assert linededup.dedup_lines(frame.limit(0)).count() == 0


def test_pairs_are_verified_exactly():
    rng = random.Random(5)
    base = ["".join(rng.choice("abcde é\t") for _ in range(rng.randrange(1, 120))) for _ in range(300)]
    other = ["".join(c if rng.random() > rng.choice([0, 0.005, 0.02]) else rng.choice("xyz") for c in x) for x in base]
    assert linededup.pairs_alike(base, other).tolist() == [linededup.alike(a, b) for a, b in zip(base, other)]
    assert linededup.pairs_alike([], []).tolist() == []


def test_keys_are_those_of_spark(spark):
    lines = ["a", "héllo wörld", "x" * 100, " tab\t", "日本"]
    rows = spark.createDataFrame([(x,) for x in lines], "own string").selectExpr("own", "xxhash64(own) as key").collect()
    assert all(r["key"] == linededup.line_key(r["own"]) for r in rows)


def test_rows_that_share_an_id_keep_their_own_lines(spark):
    rows = [(1, "only in first\nshared by both rows"), (1, "shared by both rows\nonly in second"), (2, "twice\nsame"), (2, "twice\nsame"), (3, "twice")]
    out = [tuple(r) for r in linededup.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    left = [x for d, t in out if d == 1 for x in t.split("\n")]
    assert sorted(x for x in left if x) == ["only in first", "only in second", "shared by both rows"]
    assert sorted(t for d, t in out if d > 1) == ["", "twice\nsame", "twice\nsame"]


def near_lines(rng, clusters, size, words, edits):
    """Near copies: every line of a cluster changes some of the cluster's words."""
    lines = []
    for _ in range(clusters):
        base = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(3, 9))) for _ in range(words)]
        for _ in range(size):
            own = list(base)
            for _ in range(rng.randrange(edits + 1)):
                own[rng.randrange(words)] = "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(6))
            lines.append(" ".join(own))
    return lines


@pytest.mark.parametrize("words, edits", [(20, 2), (30, 4)])
def test_recall_in_clusters(spark, words, edits):
    """Of all truly alike pairs of large clusters of near copies, nearly all end in one component."""
    import numpy as np

    rng = random.Random(21)
    lines = near_lines(rng, 3, 250, words, edits) + near_lines(rng, 60, 3, 25, 3)
    pairs = [(i, j) for i in range(len(lines)) for j in range(i + 1, len(lines)) if i // 250 == j // 250 or i >= 750]
    alike = linededup.pairs_alike([lines[i] for i, _ in pairs], [lines[j] for _, j in pairs])
    texts = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string").repartition(5)
    component = {r["node"]: r["component"] for r in linededup.line_groups(texts).collect()}
    of = [component.get(linededup.line_key(x), linededup.line_key(x)) for x in lines]
    joined = np.array([of[i] == of[j] for i, j in pairs])
    assert alike.sum() > 5000 and joined[alike].mean() >= 0.98
    sig = linededup.signatures(lines)
    shared = np.array([(sig[i] == sig[j]).sum() >= linededup.AGREE for (i, j), a in zip(pairs, alike) if a])
    assert shared.mean() >= 0.98


@pytest.mark.parametrize("block", [7, 1024])
def test_lines_of_a_template(spark, monkeypatch, block):
    """Lines that share much but are mostly not alike fill the same buckets; the alike ones among them must still meet."""
    monkeypatch.setattr(linededup, "BLOCK", block)
    rng = random.Random(12)
    draw = lambda: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(7))
    shared = [draw() for _ in range(17)]
    heads = []
    for _ in range(100):
        own = list(shared)
        for place in (4, 9, 15):
            own.insert(place, draw())
        heads.append(own)
    lines = [" ".join(x) for x in heads]
    for own in heads:
        # one more word: alike its own head only
        other = list(own)
        other[4] = draw()
        lines.append(" ".join(other))
    rng.shuffle(lines)
    texts = [(i, "\n".join(lines[4 * i : 4 * i + 4])) for i in range(50)]
    wanted = brute_lines(texts)
    assert sum(t.count("\n") + 1 for t in wanted.values() if t) < 120
    out = linededup.dedup_lines(spark.createDataFrame(texts, "doc_id long, text string").repartition(3))
    assert {r["doc_id"]: r["text"] for r in out.collect()} == wanted


def test_fingerprints(spark):
    texts = {i: " ".join(f"word{(i * j) % 977}" for j in range(1, 40 * (i % 7) + 2)) for i in range(60)} | {70: "", 71: "é" * 10, 72: "long text here " * 3000, 73: "long text here " * 3000}
    frame = spark.createDataFrame([(i, t, "s") for i, t in texts.items()] + [(99, None, "s")], "doc_id long, text string, g string").repartition(5)
    rows = {r["doc_id"]: r for r in fingerprints.fingerprint_documents(frame).collect()}
    full = texts | {99: ""}
    order = sorted(full, reverse=True)
    assert len(rows) == len(full)
    import hashlib

    for now, after in zip(order, order[1:] + order[:1]):
        edited = fingerprints.edit(full[now], full[after])
        r = rows[now]
        assert r["n_chars"] == len(full[now]) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        own, other = fingerprints.chunk_set(full[now].encode()), fingerprints.chunk_set(edited.encode())
        assert r["fingerprint"] == fingerprints.fingerprint(own) and r["edited_fingerprint"] == fingerprints.fingerprint(other)
        assert r["near_edited"] == pytest.approx(fingerprints.likeness(fingerprints.parse(r["fingerprint"]), other))
        assert 0 <= r["near_next"] <= 1
    assert rows[72]["fingerprint"] == rows[73]["fingerprint"] and rows[73]["near_next"] == 1.0
    assert fingerprints.fingerprint_documents(frame.limit(0)).count() == 0
    alone = fingerprints.fingerprint_documents(frame.where("doc_id = 5")).first()
    assert alone["near_next"] == 1.0


def test_chunks_resist_shifts():
    rng = random.Random(2)
    text = " ".join(rng.choice(["red", "green", "blue", "cyan", "teal"]) + str(rng.randrange(999)) for _ in range(2000))
    a, b = (fingerprints.chunk_set(t.encode()) for t in (text, "inserted in front " + text))
    assert fingerprints.likeness(a, b) > 0.97
    assert sum(fingerprints.boundaries(text.encode())[-1:]) == len(text)
