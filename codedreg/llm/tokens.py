"""Token ids of a tokenizer file of the `tokenizers` library, with bounded tables of pre-tokens in each worker."""

from __future__ import annotations

import json
from array import array

from tokenizers import Tokenizer

from codedreg.llm.bpe import GPT_PATTERN, Coder, PieceCoder
from codedreg.llm.common import kept


class FileCoder(PieceCoder):
    """ids as Tokenizer.encode(text, add_special_tokens=False) gives them; special strings in a text are ordinary text."""

    def __init__(self, model: Tokenizer):
        super().__init__(GPT_PATTERN)
        self.model = model

    def vocabulary_size(self) -> int:
        return self.model.get_vocab_size(with_added_tokens=True)

    def _together(self, texts: list[str]) -> list[bytes]:
        return [array("I", x.ids).tobytes() for x in self.model.encode_batch(texts, add_special_tokens=False)]


def byte_of() -> dict[str, int]:
    """The byte each character of a byte-level vocabulary stands for: itself if printable, else the next free one from 256."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(printable)]
    return {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(rest)}


def ranked_tokens(own: dict) -> list[bytes] | None:
    """Token bytes by id, if the file is a byte-level BPE whose ids follow the order of its merges."""
    model, before = own.get("model", {}), own.get("pre_tokenizer") or {}
    plain = own.get("normalizer") is None and before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True)
    if not plain or model.get("type") != "BPE" or model.get("ignore_merges"):
        return None
    back, special = byte_of(), {x["id"] for x in own.get("added_tokens", [])}
    ids = sorted((i, t) for t, i in model["vocab"].items() if i not in special)
    merged = [("".join(m) if isinstance(m, list) else m.replace(" ", "", 1)) for m in model["merges"]]
    if [i for i, _ in ids] != list(range(len(ids))) or [t for _, t in ids][256:] != merged or any(c not in back for _, t in ids for c in t):
        return None
    return [bytes(back[c] for c in t) for _, t in ids]


def file_coder(path: str, pattern: str) -> PieceCoder:
    """The rank coder if the file amounts to ranks under this pattern, else the library itself, text by text."""
    return kept(("file", path, pattern), lambda: _file_coder(path, pattern))


def _file_coder(path: str, pattern: str) -> PieceCoder:
    model = Tokenizer.from_file(path)
    model.encode_special_tokens = True
    model.no_padding()
    model.no_truncation()
    tokens = ranked_tokens(json.loads(model.to_str())) if pattern == GPT_PATTERN else None
    return Coder(tokens, pattern) if tokens else FileCoder(model)
