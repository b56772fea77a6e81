"""Byte-level BPE through a sentencepiece model that is written straight from a rank vocabulary.

Every byte stands for one printable character, every vocabulary entry for one piece whose score is its negative
rank, and the normaliser is the identity.  Merging the best-scored adjacent pair first is then the same as merging
the lowest rank first, so each pre-token gets the ids the rank file defines.  Decoding maps pieces back to bytes.

Null texts count as empty and give no ids.  What a worker has encoded it keeps in tables of bounded size: words in a
table looked up for many texts at once, pre-tokens in two generations (a full one becomes the older, and what is used
again moves to the new one).  This costs or saves time and never changes a result.
"""

from __future__ import annotations

import base64
import functools
import hashlib
import re
import struct
import sys
import unicodedata
from array import array
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame

from codedreg.llm.common import kept
from codedreg.llm.wordtable import SPACE, TEXT, WordTable, spread

CACHE_ENTRIES = 200_000
GROUP_CHARS = 500_000
#: Printable stand-ins for the 256 bytes start here.
BYTE_BASE = 0x100

RESULT = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def read_ranks(path: str) -> list[bytes]:
    """Token bytes by rank."""
    with open(path, "rb") as file:
        pairs = [line.split() for line in file if line.strip()]
    out: list[bytes] = [b""] * len(pairs)
    for token, rank in pairs:
        out[int(rank)] = base64.b64decode(token)
    return out


def stand_in(raw: bytes) -> str:
    return "".join(chr(BYTE_BASE + b) for b in raw)


def stand_ins(texts: list[str]) -> list[str]:
    """stand_in of each text's bytes, for all at once; 255 never occurs in UTF-8 and parts them."""
    raw = np.frombuffer(b"\xff".join(x.encode() for x in texts), np.uint8)
    return (raw.astype("<u2") + np.uint16(BYTE_BASE)).tobytes().decode("utf-16-le").split(chr(BYTE_BASE + 255))


def _varint(n: int) -> bytes:
    n &= (1 << 64) - 1
    out = bytearray()
    while n > 0x7F:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    out.append(n)
    return bytes(out)


def _field(number: int, value) -> bytes:
    if isinstance(value, bytes):
        return _varint(number << 3 | 2) + _varint(len(value)) + value
    if isinstance(value, float):
        return _varint(number << 3 | 5) + struct.pack("<f", value)
    return _varint(number << 3) + _varint(int(value))


def serialise_model(tokens: list[bytes]) -> bytes:
    """A sentencepiece ModelProto: pieces in rank order, then the unknown piece that no input can reach."""
    pieces = [_field(1, stand_in(raw).encode()) + _field(2, -float(rank)) for rank, raw in enumerate(tokens)]
    pieces.append(_field(1, b"<unk>") + _field(2, 0.0) + _field(3, 2))
    trainer = _field(3, 2) + _field(4, len(pieces)) + _field(40, len(tokens)) + b"".join(_field(n, -1) for n in (41, 42, 43))
    normaliser = _field(1, b"identity") + _field(3, 0) + _field(4, 0) + _field(5, 0)
    return b"".join(_field(1, p) for p in pieces) + _field(2, trainer) + _field(3, normaliser)


def _classes(last: int) -> tuple[str, str]:
    """Character ranges of letters and of numbers up to a last code point, for engines without property classes."""
    found: dict[str, list[list[int]]] = {"L": [], "N": []}
    for code in range(last + 1):
        ranges = found.get(unicodedata.category(chr(code))[0])
        if ranges is not None:
            if ranges and ranges[-1][1] == code - 1:
                ranges[-1][1] = code
            else:
                ranges.append([code, code])
    return tuple("".join(f"\\U{a:08x}-\\U{b:08x}" for a, b in found[k]) for k in "LN")


#: The characters of Unicode's White_Space property.
LATIN_SPACES = r"\t-\r \x85\xa0"
SPACES = LATIN_SPACES + r"\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"


@functools.cache
def splitter(pattern: str, last: int = sys.maxunicode) -> re.Pattern:
    """The published pre-token pattern with its property classes spelled out, for texts without code points over last."""
    letters, numbers = _classes(last)
    spaces = LATIN_SPACES if last <= 0xFF else SPACES
    inner = {r"\s": spaces, r"\p{L}": letters, r"\p{N}": numbers, r"\S": f"^{spaces}"}
    out, inside, i = [], False, 0
    while i < len(pattern):
        key = next((k for k in inner if pattern.startswith(k, i)), None)
        if key:
            out.append(inner[key] if inside else f"[{inner[key]}]")
            i += len(key)
            continue
        inside = pattern[i] == "[" or inside and pattern[i] != "]"
        out.append(pattern[i])
        i += 1
    return re.compile("".join(out))


def split_pieces(pattern: str, text: str) -> list[str]:
    """All pre-tokens.  The width of a text's code points picks the smallest character classes that cover it."""
    try:
        text.encode("latin-1")
        last = 0xFF
    except UnicodeEncodeError:
        last = 0xFFFF if len(text.encode("utf-16-le", "surrogatepass")) == 2 * len(text) else sys.maxunicode
    return splitter(pattern, last).findall(text)


#: Fixed value: the published pre-token pattern.
GPT_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""

#: White space other than the space and the line feed.
RARE_SPACES = "\t\x0b\x0c\r\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"


def crowded(text: str) -> bool:
    """Whether a space may stand beside other white space; else no pre-token crosses the place before a space."""
    return "  " in text or " \n" in text or "\n " in text or any(c in text for c in RARE_SPACES)


class Generations:
    """A bounded table that forgets what two generations have not used."""

    def __init__(self, learn):
        self.new: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.learn = learn

    def all(self, keys: list[str]) -> list[bytes]:
        """Values of the keys; unknown ones are learnt together."""
        found = list(map(self.new.get, keys))
        gaps = [i for i, v in enumerate(found) if v is None]
        if not gaps:
            return found
        missing = {keys[i] for i in gaps}
        if len(self.new) + len(missing) > CACHE_ENTRIES:
            self.old, self.new = self.new, {}
        old, new = self.old, self.new
        unknown = []
        for x in missing:
            v = old.get(x)
            if v is None:
                unknown.append(x)
            else:
                new[x] = v
        if unknown:
            new.update(self.learn(unknown))
        for i in gaps:
            found[i] = new[keys[i]]
        return found


class PieceCoder:
    """Encodes texts to little-endian id bytes through tables of what words and pre-tokens encode to."""

    def __init__(self, pattern: str):
        self.find = functools.partial(split_pieces, pattern)
        self.plain = pattern == GPT_PATTERN
        self.known = Generations(self.learn)
        self.words = WordTable(self.learn_words)

    def learn(self, missing: list[str]) -> dict[str, bytes]:
        """What these pre-tokens encode to."""
        raise NotImplementedError

    def learn_words(self, words: list[bytes]) -> list[bytes]:
        own = []
        for x in words:
            text = x.decode() if x[0] != TEXT else x[1:].decode()
            own.append([text] if x[0] == SPACE and text[1:].isalpha() else self.find(text))
        coded = self.learn(list({p for x in own for p in x}))
        return [coded[p[0]] if len(p) == 1 else b"".join([coded[x] for x in p]) for p in own]

    def encode(self, text: str) -> bytes:
        return self._together([text])[0]

    def encode_many(self, texts: Iterable[str]) -> Iterator[bytes]:
        """ids of each text; many texts share one look at the tables."""
        held, size = [], 0
        for text in texts:
            held.append(text)
            size += len(text)
            if size > GROUP_CHARS:
                yield from self._together(held)
                held, size = [], 0
        yield from self._together(held)

    def _together(self, texts: list[str]) -> list[bytes]:
        """Texts where white space stands alone or in runs of line feeds go through the words, others through the pattern."""
        by_words = [self.plain and not crowded(x) for x in texts]
        coded = iter(self.words.encode(b"".join(b"\xff" + x.encode() for x, plain in zip(texts, by_words) if plain)))
        return [next(coded) if plain else b"".join(self.known.all(self.find(x))) for x, plain in zip(texts, by_words)]


class Coder(PieceCoder):
    """Encodes by a serialised sentencepiece model and decodes by the inverse byte mapping; one per worker process."""

    def __init__(self, tokens: list[bytes], pattern: str):
        super().__init__(pattern)
        self.model = sentencepiece.SentencePieceProcessor(model_proto=serialise_model(tokens))
        back = {chr(BYTE_BASE + b): b for b in range(256)}
        vocabulary = [bytes(back[c] for c in self.model.id_to_piece(i)) for i in range(len(tokens))]
        self.laid = np.frombuffer(b"".join(vocabulary), np.uint8)
        self.sizes = np.array([len(x) for x in vocabulary], np.int64)
        self.places = np.cumsum(self.sizes) - self.sizes

    def vocabulary_size(self) -> int:
        return len(self.sizes)

    def learn(self, missing: list[str]) -> dict[str, bytes]:
        coded = self.model.encode(stand_ins(missing), num_threads=1)
        return {piece: array("I", ids).tobytes() for piece, ids in zip(missing, coded)}

    def decode(self, ids: bytes) -> bytes:
        own = np.frombuffer(ids, "<u4")
        return self.laid[spread(self.places[own], self.sizes[own])].tobytes()


def coder(ranks_path: str, pattern: str) -> Coder:
    return kept(("ranks", ranks_path, pattern), lambda: Coder(read_ranks(ranks_path), pattern))


def encode_documents(docs: DataFrame, ranks_path: str, pattern: str, *, digests: bool = False) -> DataFrame:
    """doc_id with its ids and decoded bytes (or, with digests, their SHA-256), one row per input row.

    Null text is empty; a null doc_id stays null; repeated rows stay repeated; extra columns are not read.
    """
    schema = RESULT if digests else "doc_id long, n_tokens long, ids array<long>, decoded binary"

    def run(batches):
        own = coder(ranks_path, pattern)
        for batch in batches:
            rows: list[tuple] = []
            for ids in own.encode_many(t.as_py() or "" for t in batch.column("text")):
                raw = own.decode(ids)
                if digests:
                    rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(raw).hexdigest()))
                else:
                    rows.append((len(ids) // 4, memoryview(ids).cast("I").tolist(), raw))
            columns = list(zip(*rows)) or [(), (), ()]
            kinds = [pa.int64(), pa.string(), pa.string()] if digests else [pa.int64(), pa.list_(pa.int64()), pa.binary()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(pa.array, columns, kinds)], schema_names(schema))

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def schema_names(schema: str) -> list[str]:
    return [part.split()[0] for part in schema.split(", ")]
