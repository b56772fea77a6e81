"""What Python workers keep between tasks, and what line dedup computes once a row."""

import public_tokenizers as P
from codedreg.llm import common, jaccard, linededup, pii, toxicity
from codedreg.llm.common import kept, lean
from codedreg.llm.tokens import file_coder

FILE = P.path("byte_bpe_50k.json")


def test_a_process_keeps_the_tables_of_one_operator():
    own = file_coder(FILE, P.PATTERN)
    assert file_coder(FILE, P.PATTERN) is own
    assert list(lean(iter)([1, 2])) == [1, 2]
    assert file_coder(FILE, P.PATTERN) is not own
    made = []
    for key in ("a", "a", "b", "a"):
        kept(key, lambda: made.append(key))
    assert made == ["a", "b", "a"]


def test_stages_before_packing_let_the_coder_of_a_reused_worker_go(spark, monkeypatch):
    texts = ["one two three four five six seven eight\nand a line of its own", None, "mail a@b.com\nand a line of its own"] * 2
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    sent, own = [], type(docs).mapInArrow
    monkeypatch.setattr(type(docs), "mapInArrow", lambda self, f, *a, **b: sent.append(f) or own(self, f, *a, **b))
    model = toxicity.Model(None, 0.0, None, 0.5)
    for stage in (linededup.dedup_lines, jaccard.jaccard_components, pii.masked, lambda d: toxicity.score_documents(d, model)):
        assert stage(docs).count() == len(texts)
    assert len(sent) > 10
    for f in sent:
        file_coder(FILE, P.PATTERN)
        assert common._KEPT
        assert list(f(iter([]))) is not None
        assert not common._KEPT


def test_rows_are_hashed_before_their_lines_are_laid_out(spark):
    docs = spark.createDataFrame([(1, "a\nb\n \n　\t\nc")], "doc_id long, text string")
    found = linededup._occurrences(docs)
    plan = found._jdf.queryExecution().optimizedPlan().toString().split("\n")
    generate = next(i for i, x in enumerate(plan) if "Generate" in x)
    assert not any("xxhash64(doc_id" in x for x in plan[:generate])
    assert [r["line"] for r in found.orderBy("line").collect()] == [0, 1, 4]


def test_normal_lines_and_windows():
    lines = ["", " ", "a  B", "\ta b ", "a　b", "a b", "ΑΣ ΑΣ", "x\x1cy", "\xa0z", "a​b c"]
    assert [linededup.normal_line(x) for x in lines] == [" ".join(x.lower().split()) for x in lines]
    text = "abcdefabcdef\U0010ffff\0abcdef"
    hashes = linededup.window_hashes(text).tolist()
    windows = [text[i : i + 6] for i in range(len(text) - 5)]
    assert len(set(zip(windows, hashes))) == len(set(windows)) == len(set(hashes))
