"""Tokenizer ids of whole texts, exact and fast: recurring pieces of text are encoded once and looked up afterwards.

Plain texts (Latin letters, no apostrophes) are cut around runs of letters, each with the one blank before it, or
without blanks where the vocabulary drops them; the pre-tokens of the tokenizers used here never reach over such a cut. All other texts are cut only before a space that
follows a non-blank, which holds for any text. Unknown runs of letters are encoded in one go as a single text, whose
tokens show where each run starts (byte-level vocabularies) or ends (vocabularies with word ends). Where byte-level
plain texts have no marks or blanks in a row, string methods cut them before each space, line feed, comma and full stop,
and only pieces that are not known yet are cut around their letters. The table of known
pieces is bounded; what doesn't fit, and pieces too long to recur, are encoded as they come. Texts that hold a special
token are encoded whole, as the library does it.
"""

from __future__ import annotations

import os
import re
from itertools import chain, islice

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

_PLAIN = re.compile(r"\s?[^\W\d_]+|[\W\d_]+?(?=\s?[^\W\d_]|\Z)")
_ODD = re.compile(r"[^\t-\r\x20-\x26\x28-\x7e\xa1-\xac\xae-\xb1\xb4-\xb8\xba\xbb\xbf-įı-ɏ]")
_TIGHT = re.compile(r"[\t-\r ,.](?:(?<=[\t-\r ]{2})|(?<=[\W_][,.]))")
_BARE = re.compile(r"[^\W\d_]+|(?:[^\w\s]|_)+|\d+")
_SPANS = re.compile(r" *[^ ]+| +")
_MIXED = re.compile(r"[^\S ] ")
_EXACT = re.compile(r"(?<=\S)(?= )")
KNOWN = 1 << 19
_open: dict[str, SpanEncoder] = {}


def default_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class SpanEncoder:
    """ids of texts as little-endian unsigned 32-bit bytes."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        vocab = self.tok.get_vocab()
        special = sorted({t.content.lower() for t in self.tok.get_added_tokens_decoder().values()})
        self.special = re.compile("|".join(map(re.escape, special))) if special else None
        self.edge = np.zeros(max(vocab.values(), default=0) + 1, bool)
        self.ends = any(t.endswith("</w>") for t in vocab)
        for t, i in vocab.items():
            self.edge[i] = t.endswith("</w>") if self.ends else t.startswith("Ġ")
        self.known: dict[str, bytes] = {}

    def _special(self, text: str) -> bool:
        return bool(self.special and self.special.search(text.lower()))

    def pieces(self, text: str) -> list[str]:
        if self._special(text):
            return [text]
        if not _ODD.search(text):
            # white space and case are of no account to vocabularies with word ends
            if self.ends:
                return _BARE.findall(text.lower())
            if _TIGHT.search(text):
                return _PLAIN.findall(text)
            # pre-tokens end before each of these, and odd characters are not in the text
            for c in " \n,.":
                text = text.replace(c, "\x1f" + c)
            return text.split("\x1f")
        return _EXACT.split(text) if _MIXED.search(text) else _SPANS.findall(text)

    def _raw(self, pieces: list[str]) -> list[bytes]:
        return [np.asarray(e.ids, "<u4").tobytes() for e in self.tok.encode_batch_fast(pieces, add_special_tokens=False)]

    def _words(self, words: list[str]) -> list[bytes]:
        """Runs of plain letters after one space, all at once."""
        ids = np.asarray(self.tok.encode_batch_fast([(" " if self.ends else "").join(words)], add_special_tokens=False)[0].ids, "<u4")
        at = np.flatnonzero(self.edge[ids])
        if len(at) != len(words):
            return self._raw(words)
        cut = [0, *(at + 1).tolist()] if self.ends else [*at.tolist(), len(ids)]
        raw = ids.tobytes()
        return [raw[4 * a : 4 * b] for a, b in zip(cut[:-1], cut[1:], strict=True)]

    def encode(self, texts: list[str | None]) -> list[bytes]:
        known = self.known
        out: list[bytes | None] = []
        short: list[tuple[int, list[str], list[bytes | None], list[int]]] = []  # what texts with unknown pieces lack
        for t in texts:
            cut = self.pieces(t) if t else []
            got = list(map(known.get, cut))
            at = [i for i, x in enumerate(got) if x is None]
            if at:
                short.append((len(out), cut, got, at))
            out.append(None if at else b"".join(got))
        new = {cut[i] for _, cut, _, at in short for i in at}
        letters = (lambda s: s.isalpha()) if self.ends else (lambda s: s[:1] == " " and s[1:].isalpha())
        words = [s for s in new if len(s) <= 64 and letters(s) and not _ODD.search(s)]
        rest = new.difference(words)
        # words with other marks beside them are cut further
        finer = {} if self.ends else {s: c for s in rest if not _ODD.search(s) and len(c := _PLAIN.findall(s)) > 1 and not self._special(s)}
        inner = set(chain.from_iterable(finer.values())).difference(known, new)
        words += [s for s in inner if len(s) <= 64 and letters(s)]
        rest = list((rest | inner).difference(words, finer))
        made: dict[str, bytes] = {}
        for group, encode in ((words, self._words), (rest, self._raw)):
            for a in range(0, len(group), 2048):
                part = group[a : a + 2048]
                made.update(zip(part, encode(part), strict=True))
        for s, c in finer.items():
            made[s] = b"".join([known[p] if p in known else made[p] for p in c])
        known.update(islice(((s, x) for s, x in made.items() if len(s) <= 64), KNOWN - len(known)))
        for n, cut, got, at in short:
            for i in at:
                got[i] = made[cut[i]]
            out[n] = b"".join(got)
        return out


def encoder(path: str) -> SpanEncoder:
    """The process's encoder for a vocabulary file."""
    if path not in _open:
        _open[path] = SpanEncoder(path)
    return _open[path]
