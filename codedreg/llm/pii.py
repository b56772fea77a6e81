"""Personal data with exact source offsets, plain and disguised.

Plain identifiers are found in the text as it stands.  A transducer then rewrites the text: look-alike characters
become the ASCII ones they imitate, invisible characters vanish, runs of spelled digits become digits, and the "at" and
"dot" disguises of addresses become @ and dots.  It keeps the source span of every character it writes, so what the
same detectors find in the rewritten text maps back to the source.  Such a span is added unless it overlaps a plain one
of its kind without holding more than it; plain spans always stay.

Null text is empty and has no spans; an empty table gives no rows; repeated rows are each reported; extra columns are
not read.  All detectors are linear in the length of the text, very long ones included.
"""

from __future__ import annotations

import functools
import hashlib
import re
import unicodedata
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codedreg.llm.common import lean

KINDS = ("email", "ip", "card", "phone")
RESULT = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string"

Span = tuple[int, int]

LOCAL = re.compile(r"[A-Za-z0-9._%+-]+")
HOST = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
#: A run of digits is entered at its start only: entered later, it would end, and fail or not, at the same place.
ADDRESS = re.compile(r"(?<![0-9])([0-9]+)\.([0-9]+)\.([0-9]+)\.([0-9]+)")
DIGITS = re.compile(r"[0-9](?:[ -]?[0-9])+")
PHONE = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
LOCAL_SET = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def emails(text: str) -> Iterator[Span]:
    """The part before an @ reaches back to the start of its run of characters, or to the end of the last match."""
    end = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > end and text[start - 1] in LOCAL_SET:
            start -= 1
        host = HOST.match(text, at) if start < at else None
        if host:
            end = host.end()
            yield start, end
        at = text.find("@", at + 1)


def addresses(text: str) -> Iterator[Span]:
    for m in ADDRESS.finditer(text) if "." in text else ():
        if all(len(x := part.lstrip("0")) <= 3 and int(x or 0) <= 255 for part in m.groups()):
            yield m.span()


def luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) << (i & 1)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def cards(text: str) -> Iterator[Span]:
    for m in DIGITS.finditer(text):
        if m.end() - m.start() >= 16 and 16 <= len(digits := m[0].replace(" ", "").replace("-", "")) <= 19 and luhn(digits):
            yield m.span()


def phones(text: str) -> Iterator[Span]:
    if "+" not in text:
        return
    for m in PHONE.finditer(text):
        if 8 <= sum(c.isdigit() for c in m[0]) <= 15:
            yield m.span()


DETECTORS = dict(zip(KINDS, (emails, addresses, cards, phones)))


def detect(text: str) -> dict[str, list[Span]]:
    return {kind: list(find(text)) for kind, find in DETECTORS.items()}


#: Letters of other scripts that look like ASCII letters, and what they look like.
LOOK_ALIKES = dict(zip("авекмнорстухіјѕԁԛԝһҽАВЕКМНОРСТУХІЈЅαεικνορτυχΑΒΕΖΗΙΚΜΝΟΡΤΥΧ", "abekmhopctyxijsdqwheABEKMHOPCTYXIJSaeikvoptuxABEZHIKMNOPTYX"))
#: Characters without width.
INVISIBLE = "\u00ad\u200b\u200c\u200d\u2060\ufeff"
#: Digit words.
DIGIT_WORDS = {"zero": "0", "oh": "0", "one": "1", "two": "2", "three": "3", "four": "4", "five": "5", "six": "6", "seven": "7", "eight": "8", "nine": "9"}
DIGIT_RUN_MIN = 3

WORD = "(?:" + "|".join(DIGIT_WORDS) + ")"
#: A number word or figures, and what may stand between two of them.
TOKEN = f"(?:{WORD}|[0-9]+)"
BETWEEN = r"(?:[ ]*\.[ ]*|[ ,-]{1,2}|[ ]dot[ ])"
SPELLED = re.compile(rf"(?<!\w)(?:(plus)[ ]+|\+[ ]?)?({TOKEN}(?:{BETWEEN}{TOKEN})+)(?!\w)", re.I)
ONE_TOKEN = re.compile(TOKEN, re.I)
ONE_WORD = re.compile(WORD, re.I)
BRACKETED = re.compile(r"[ \t]*(?:\[|\(|\{|<)[ \t]*(at|dot|@|\.)[ \t]*(?:\]|\)|\}|>)[ \t]*", re.I)
PLAIN_DOT = re.compile(r"(?<=[A-Za-z0-9])[ \t]+dot[ \t]+(?=[A-Za-z0-9])", re.I)
PLAIN_AT = re.compile(r"(?<=[A-Za-z0-9])[ \t]+at[ \t]+(?=[A-Za-z0-9-]+(?:[ \t]+dot[ \t]+|[ \t]*[\[({<][ \t]*(?:dot|\.)[ \t]*[\])}>][ \t]*)[A-Za-z0-9])", re.I)
SPACED_AT = re.compile(r"(?<=[A-Za-z0-9])[ \t]+@[ \t]+(?=[A-Za-z0-9])")
SPACED_DOT = re.compile(r"(?<=[A-Za-z0-9])[ \t]+\.[ \t]+(?=[A-Za-z0-9])")
#: at and dot between dashes or underscores, the former only before the latter.
DASHED_AT = re.compile(r"(?<=[A-Za-z0-9])[ \t]*[-_]+at[-_]+[ \t]*(?=[A-Za-z0-9]+[ \t]*[-_]+dot[-_]+[ \t]*[A-Za-z0-9])", re.I)
DASHED_DOT = re.compile(r"(?<=[A-Za-z0-9])[ \t]*[-_]+dot[-_]+[ \t]*(?=[A-Za-z0-9])", re.I)
#: Top-level labels before which a spelled "at" counts without a spelled dot, and words that stand before a plain "at".
TOP_LABELS = "com|org|net|edu|gov|info|biz|io|de|fr|es|uk|eu|us"
BEFORE_AT = "look|looking|looked|me|us|you|him|her|them|it|is|are|was|were|be|been|found|available|hosted|site|page|online|here|more|visit|work|works|working|meet|see|or|and|shop|stay|arrive|live|only|also|back|up|out"
AT_HOST = re.compile(rf"(?<![A-Za-z0-9._%+-])(?!(?:{BEFORE_AT})[ \t])[A-Za-z0-9._%+-]+([ \t]+at[ \t]+)(?=(?:[A-Za-z0-9-]+\.)+(?:{TOP_LABELS})\b)", re.I)
HINT = re.compile(rf"dot|[\[({{<][ \t]*(?:at|\.|@)[ \t]*[\])}}>]|[ \t]@[ \t]|[ \t]at[ \t]+[a-z0-9-]+\.[a-z]|(?:{WORD}|[0-9])[ ]*[ ,.-][ ]*{WORD}|{WORD}[ ]*[ ,.-][ ]*[0-9]", re.I)
#: Decimal digits of other scripts.
OTHER_DIGITS = {chr(c): str(unicodedata.decimal(chr(c))) for c in range(0x80, 0x11000) if unicodedata.decimal(chr(c), None) is not None}
FOREIGN = re.compile("[" + "".join(LOOK_ALIKES) + "".join(OTHER_DIGITS) + INVISIBLE + "！-～①-⒛\U0001d400-\U0001d7ff]")


@functools.cache
def plain_form(c: str) -> str:
    """What one character imitates."""
    if c in INVISIBLE:
        return ""
    if c in LOOK_ALIKES:
        return LOOK_ALIKES[c]
    if c in OTHER_DIGITS:
        return OTHER_DIGITS[c]
    folded = unicodedata.normalize("NFKC", c)
    return folded if folded.isascii() else c


class Tape:
    """A text with the source span of each of its characters."""

    def __init__(self, text: str):
        self.text, self.starts, self.ends = text, range(len(text)), range(1, len(text) + 1)

    def rewrite(self, edits: list[tuple[int, int, str]]) -> None:
        """Replace spans, given in order and not overlapping; every new character stands for its whole source span."""
        if not edits:
            return
        parts, starts, ends, at = [], [], [], 0
        for a, b, new in edits:
            parts += [self.text[at:a], new]
            starts += self.starts[at:a]
            ends += self.ends[at:a]
            if b > a:
                starts += [self.starts[a]] * len(new)
                ends += [self.ends[b - 1]] * len(new)
            at = b
        self.text = "".join(parts) + self.text[at:]
        self.starts = starts + list(self.starts[at:])
        self.ends = ends + list(self.ends[at:])

    def source(self, span: Span) -> Span:
        return self.starts[span[0]], self.ends[span[1] - 1]


def _digit_edits(text: str) -> list[tuple[int, int, str]]:
    """In a run of number words and figures with a word in it, each word gives its digit; what stood between two tokens of the run
    goes, but for a dot.

    Without figures or a plus, DIGIT_RUN_MIN words make a run.
    """
    out = []
    for run in SPELLED.finditer(text):
        tokens = list(ONE_TOKEN.finditer(text, run.start(2), run.end(2)))
        words = [t for t in tokens if not t[0].isdigit()]
        if not words and not run[1] or len(words) == len(tokens) < DIGIT_RUN_MIN and not run[1]:
            continue
        if run[1]:
            out.append((run.start(1), run.start(2), "+"))
        for token, after in zip(tokens, [*tokens[1:], None]):
            end = after.start() if after else token.end()
            between = text[token.end() : end].lower()
            new = token[0] if token[0].isdigit() else DIGIT_WORDS[token[0].lower()]
            out.append((token.start(), end, new + "." * ("." in between or "dot" in between)))
    return out


#: What is rewritten in turn: a pattern, the group that goes, and what stands for it (None: by the word found).
REWRITES = ((PLAIN_AT, 0, "@"), (DASHED_AT, 0, "@"), (BRACKETED, 0, None), (PLAIN_DOT, 0, "."), (DASHED_DOT, 0, "."), (SPACED_AT, 0, "@"), (AT_HOST, 1, "@"))


def disguised(text: str) -> Tape | None:
    """The rewritten text, or None if nothing in it hints at a disguise."""
    foreign = not text.isascii() and FOREIGN.search(text)
    if not foreign and not HINT.search(text):
        return None
    tape = Tape(text)
    if foreign:
        tape.rewrite([(m.start(), m.end(), plain_form(m[0])) for m in FOREIGN.finditer(text)])
    tape.rewrite(_digit_edits(tape.text))
    for pattern, group, new in REWRITES:
        tape.rewrite([(m.start(group), m.end(group), new or ("@" if m[1].lower() in ("at", "@") else ".")) for m in pattern.finditer(tape.text)])
    # a dot between spaces counts after a host that an @ stands before
    tape.rewrite([(m.start(), m.end(), ".") for m in SPACED_DOT.finditer(tape.text) if HOST_BEFORE.search(tape.text, max(0, m.start() - HOST_LENGTH), m.start())])
    return tape if tape.text != text else None


#: Characters of a host label that are looked at before a dot between spaces (labels are at most 63 long).
HOST_LENGTH = 65
HOST_BEFORE = re.compile(r"@[A-Za-z0-9-]+\Z")


def find_all(text: str) -> tuple[dict[str, list[Span]], dict[str, list[Span]]]:
    """Plain spans by kind, and all spans by kind."""
    base = detect(text)
    tape = disguised(text)
    if tape is None:
        return base, base
    full = {}
    for kind, spans in detect(tape.text).items():
        own, i, merged = base[kind], 0, []
        for span in map(tape.source, spans):
            while i < len(own) and own[i][1] <= span[0]:
                i += 1
            stop = i
            while stop < len(own) and own[stop][0] < span[1]:
                stop += 1
            met = own[i:stop]
            if all(span[0] <= a and b <= span[1] and (a, b) != span for a, b in met):
                merged.append(span)
        full[kind] = sorted(own + merged)
    return base, full


def listed(spans: dict[str, list[Span]]) -> str:
    return ",".join(f"{kind}:{a}:{b}" for kind in KINDS for a, b in spans[kind])


def mask_text(text: str, spans: dict[str, list[Span]]) -> str:
    """Every span replaced by its kind in angle brackets; of overlapping spans the longest from the left counts."""
    out, at = [], 0
    for a, b, kind in sorted(((a, b, kind) for kind in KINDS for a, b in spans[kind]), key=lambda x: (x[0], -x[1])):
        if a >= at:
            out += [text[at:a], f"<{kind}>"]
        at = max(at, b)
    return "".join(out) + text[at:]


def find_pii(docs: DataFrame) -> DataFrame:
    """Counts of plain identifiers, a digest of their spans, and all spans."""
    names = [x.split()[0] for x in RESULT.split(", ")]

    def run(batches):
        for batch in batches:
            rows = []
            for text in batch.column("text"):
                base, full = find_all(text.as_py() or "")
                rows.append((*(len(base[k]) for k in KINDS), hashlib.sha256(listed(base).encode()).hexdigest(), listed(full)))
            if rows:
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(pa.array, zip(*rows), [pa.int64()] * 4 + [pa.string()] * 2)], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(lean(run), RESULT)


def masked(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The same rows and columns with identifiers masked; null text stays null."""

    def run(batches):
        for batch in batches:
            texts = [None if (t := x.as_py()) is None else mask_text(t, find_all(t)[1]) for x in batch.column(text_col)]
            at = batch.schema.get_field_index(text_col)
            yield batch.set_column(at, text_col, pa.array(texts, pa.string()))

    return docs.mapInArrow(lean(run), docs.schema)
