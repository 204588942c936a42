"""Token ids of whole texts by a public tokenizer file, with tables of what was encoded before.

The byte-level tokenizer first cuts a text into pre-tokens and then merges each by itself.
Texts within Latin-1 (the usual case) are cut here by the same rule; each pre-token is looked
up in a bounded per-worker table, and one that is missing goes to the library's merge model
alone, without its cutting. Other texts are cut just at lone spaces between two other
characters, where a pre-token always ends, and missing parts go through the whole tokenizer.
The ids equal those of the whole text (tested).
"""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Callable

import numpy as np
import pyarrow as pa

from .common import worker_cache

DEFAULT_FILE = "byte_bpe_50k.json"
#: Once a table is so large it stays as it is: what is frequent came early.
PRETOKENS, PARTS = 400_000, 100_000
#: Longer ones are rare and large, so they stay out of the tables.
LONGEST_KEPT = 48
# Latin-1 members of the classes of letters, numbers and white space.
LETTERS = "A-Za-z\xaa\xb5\xba\xc0-\xd6\xd8-\xf6\xf8-\xff"
NUMBERS = "0-9\xb2\xb3\xb9\xbc-\xbe"
SPACES = "\x09-\x0d \x85\xa0"
_LATIN = re.compile(rf" ?[{LETTERS}]+|'(?:s|t|re|ve|m|ll|d)| ?[{NUMBERS}]+| ?[^{SPACES}{LETTERS}{NUMBERS}]+|[{SPACES}]+(?![^{SPACES}])|[{SPACES}]+")
_CUT = re.compile(r"(?<=\S)(?= \S)")
# Bytes that stand for themselves in the byte-level alphabet; the others follow from code point 256 on.
SHOWN = [*range(33, 127), *range(161, 173), *range(174, 256)]


def byte_alphabet() -> str:
    """Character of each of the 256 bytes."""
    hidden = [b for b in range(256) if b not in SHOWN]
    return "".join(chr(b) if b in SHOWN else chr(256 + hidden.index(b)) for b in range(256))


class Table(dict):
    """Encoded strings as little-endian unsigned 32-bit ids; a missing one is encoded, and kept while there is room."""

    def __init__(self, ids_of: Callable[[str], list[int]], most: int):
        self.ids_of, self.most = ids_of, most

    def __missing__(self, key: str) -> bytes:
        found = array("I", self.ids_of(key)).tobytes()
        if len(self) < self.most and len(key) <= LONGEST_KEPT:
            self[key] = found
        return found


class Encoder:
    def __init__(self, file: str = DEFAULT_FILE):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        import public_tokenizers
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(public_tokenizers.path(file) if os.sep not in file else file)
        self.tokenizer.encode_special_tokens = True
        whole, merge, alphabet = self.tokenizer.encode, self.tokenizer.model.tokenize, byte_alphabet()
        self.pretokens = Table(lambda c: [t.id for t in merge((c if c.isascii() else c.encode().decode("latin-1")).translate(alphabet))], PRETOKENS)
        self.parts = Table(lambda c: whole(c, add_special_tokens=False).ids, PARTS)

    def _encode(self, text: str) -> bytes:
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return b"".join(map(self.parts.__getitem__, _CUT.split(text)))
        return b"".join(map(self.pretokens.__getitem__, _LATIN.findall(text)))

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        return [self._encode(t) for t in texts]

    def encode_array(self, texts: pa.StringArray, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        """All ids, each text followed by end_id, and the offsets of the texts."""
        end = int(end_id).to_bytes(4, "little")
        found = [x + end for x in self.encode(texts.to_pylist())]
        return np.frombuffer(b"".join(found), "<u4"), np.concatenate([[0], np.cumsum([len(x) // 4 for x in found])])


def encoder(file: str = DEFAULT_FILE) -> Encoder:
    kept = worker_cache("encoders")
    if file not in kept:
        kept[file] = Encoder(file)
    return kept[file]
