"""Token ids of whole texts by a public tokenizer file, with a bounded cache of words.

A BPE file with word ends never joins pieces across white space or across its pre-tokens, so a text's ids
are the ids of its words.  Texts made of characters for which that was checked (``PLAIN``: ASCII and
precomposed Latin letters, which normalisation leaves alone and lower-casing maps one to one) go through
the cache; all others go to the library whole, and so do texts that hold the string of an added token where these count as tokens.
"""

from __future__ import annotations

import os
import re

import regex

from .common import BoundedCache

PLAIN = re.compile("[^\t-\r -~¡-įı-ɏ‐-‧€]")
#: Pre-token pattern of the file (fixed value).
PRE_TOKEN = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")


def byte_letters() -> dict[int, str]:
    """Byte-level alphabet: printable bytes stand for themselves, the others for letters from 256 on."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in printable}
    table.update({b: chr(256 + k) for k, b in enumerate(b for b in range(256) if b not in table)})
    return table


class WordIds:
    """ids of a text as little-endian unsigned 32-bit bytes.

    ``added_tokens``: strings of the file's added tokens in a text become these tokens, as by the library's default; else they are ordinary text.
    """

    def __init__(self, path: str, added_tokens: bool = False, limit: int = 400_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.encode_special_tokens = not added_tokens
        added = [re.escape(t.content) for t in self.model.get_added_tokens_decoder().values()] if added_tokens else []
        self.whole = re.compile("|".join([PLAIN.pattern, *added]))
        self.bpe, self.letters = self.model.model, byte_letters()
        self.runs = BoundedCache(self._run, limit // 2)
        self.words = BoundedCache(self._word, limit)

    def _run(self, run: str) -> bytes:
        word = run if run.isascii() else run.encode().decode("latin-1").translate(self.letters)
        return b"".join([t.id.to_bytes(4, "little") for t in self.bpe.tokenize(word)])

    def _word(self, word: str) -> bytes:
        return b"".join(map(self.runs.__getitem__, PRE_TOKEN.findall(word)))

    def encode(self, text: str | None) -> bytes:
        if not text:
            return b""
        if self.whole.search(text):
            return b"".join([i.to_bytes(4, "little") for i in self.model.encode(text, add_special_tokens=False).ids])
        return b"".join(map(self.words.__getitem__, text.lower().split()))


_models: dict[tuple[str, bool], WordIds] = {}


def word_ids(path: str, added_tokens: bool = False) -> WordIds:
    """One cache for each worker process, file and reading of added tokens."""
    if (path, added_tokens) not in _models:
        _models[path, added_tokens] = WordIds(path, added_tokens)
    return _models[path, added_tokens]
