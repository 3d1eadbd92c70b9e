"""Merge tokenizers: canonical encoding, vocabulary tries, counts of encodings.

A Tokenizer is a vocabulary and a merge list in rank order; text is cut into chunks (a word takes the space before it) and merges never
cross chunks. Vocabularies are given (toy lists or public files); none is trained here.
"""

from __future__ import annotations

import json
import re
from collections.abc import Iterable, Sequence
from functools import lru_cache

CHUNK = re.compile(r" ?[^ ]+| +")
BOS, EOS = -1, -2


class Tokenizer:
    def __init__(self, merges: Sequence[tuple[str, str]], alphabet: Iterable[str] = (), vocab: dict[str, int] | None = None, chunk: re.Pattern | None = CHUNK):
        self.merges, self.chunk = list(merges), chunk
        if vocab is None:
            letters = sorted(set(alphabet) | {c for a, b in merges for c in a + b})
            vocab = {t: i for i, t in enumerate(dict.fromkeys([*letters, *(a + b for a, b in merges)]))}
        self.vocab = vocab
        self.text = {i: t for t, i in vocab.items()}
        self.rank = {m: r for r, m in enumerate(self.merges)}
        self._trie: dict | None = None
        self._chunks: dict[str, tuple[int, ...]] = {}

    def pieces(self, chunk: str) -> list[str]:
        """Merges in rank order, each applied leftmost wherever its pair stands."""
        parts = list(chunk)
        while len(parts) > 1:
            ranks = [self.rank.get(p) for p in zip(parts, parts[1:], strict=False)]
            best = min((r for r in ranks if r is not None), default=None)
            if best is None:
                break
            a, b = self.merges[best]
            out, i = [], 0
            while i < len(parts):
                if i + 1 < len(parts) and parts[i] == a and parts[i + 1] == b:
                    out.append(a + b)
                    i += 2
                else:
                    out.append(parts[i])
                    i += 1
            parts = out
        return parts

    def encode(self, text: str) -> tuple[int, ...]:
        out: list[int] = []
        for chunk in self.chunk.findall(text) if self.chunk else [text]:
            ids = self._chunks.get(chunk)
            if ids is None:
                ids = tuple(self.vocab[p] for p in self.pieces(chunk))
                if len(self._chunks) < 200_000:
                    self._chunks[chunk] = ids
            out += ids
        return tuple(out)

    def decode(self, ids: Iterable[int]) -> str:
        return "".join(self.text.get(i, "") for i in ids)

    def is_canonical(self, ids: Sequence[int]) -> bool:
        return self.encode(self.decode(ids)) == tuple(ids)

    @property
    def trie(self) -> dict:
        """Nested maps by character; the key "" holds a token id."""
        if self._trie is None:
            self._trie = {}
            for t, i in self.vocab.items():
                at = self._trie
                for c in t:
                    at = at.setdefault(c, {})
                at[""] = i
        return self._trie

    def count_encodings(self, text: str) -> int:
        ways = [1] + [0] * len(text)
        for i in range(len(text)):
            at = self.trie
            for j in range(i, len(text)):
                at = at.get(text[j])
                if at is None:
                    break
                if "" in at:
                    ways[j + 1] += ways[i]
        return ways[-1]


def characters(alphabet: Iterable[str]) -> Tokenizer:
    """One token a character."""
    return Tokenizer([], alphabet)


class PublicTokenizer(Tokenizer):
    """A byte-level BPE file of the `tokenizers` format: its text tokens as vocabulary, its library as encoder."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer as Library

        with open(path, encoding="utf-8") as f:
            table = json.load(f)["model"]["vocab"]
        self.path, self._library = path, Library.from_file(path)
        self._library.encode_special_tokens = True
        byte_of = {c: b for b, c in _byte_letters().items()}
        vocab = {}
        for token, i in table.items():
            try:
                vocab[bytes(byte_of[c] for c in token).decode("utf-8")] = i
            except (KeyError, UnicodeDecodeError):
                continue  # a part of a character, or a special token
        super().__init__([], vocab=vocab)

    def encode(self, text: str) -> tuple[int, ...]:
        return tuple(self._library.encode(text, add_special_tokens=False).ids)

    def __getstate__(self):
        return {"path": self.path}

    def __setstate__(self, state):
        self.__init__(state["path"])


@lru_cache(maxsize=1)
def _byte_letters() -> dict[int, str]:
    """Bytes as printable letters, as byte-level files spell them: printable Latin-1 stays, the rest follows from U+0100 on."""
    kept = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b]
    out = {b: chr(b) for b in kept}
    for n, b in enumerate(b for b in range(256) if b not in out):
        out[b] = chr(256 + n)
    return out


# A toy tokenizer over lower-case letters for worked examples and SQL checks.
TOY_MERGES = [("t", "h"), ("th", "e"), ("i", "n"), ("a", "n"), ("o", "n"), ("e", "r"), ("an", "d"), ("in", "g")]
