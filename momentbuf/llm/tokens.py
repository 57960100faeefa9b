"""Cached encoding with the public tokenizers: each distinct stretch between blanks is encoded once by the library.

Both vocabularies pre-split a text before any merge, and no merge crosses such a
split. A blank between two characters that are not white space always starts
a new pre-token of the byte-level vocabulary, and white space always ends one of
the word vocabulary, so ids of stretches, joined, are the ids of the text. Special
tokens that a text spells out become their one id, as in the library's plain call;
they hold no blanks, so a stretch has them whole.
"""

from __future__ import annotations

import gc
import re
from array import array

import numpy as np

from momentbuf.llm.common import CACHES, worker_limits

_ODD_BLANK = re.compile(r"\s[ ]|[ ]\s")
#: White space besides blank and line end.
_RARE_BLANKS = "\t\r\x0b\x0c\x1c\x1d\x1e\x1f\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"
_PLAIN_BLANK = re.compile(r"(?<=\S) (?=\S)")
_JOINED = 64
_loaded: dict = CACHES.setdefault("tokens", {})


def _odd(t: str) -> bool:
    """Whether a blank stands next to other white space; the plain searches settle nearly all texts."""
    if "  " in t or "\n " in t or " \n" in t:
        return True
    return any(c in t for c in _RARE_BLANKS) and bool(_ODD_BLANK.search(t))


class _Known(dict):
    """What stays, and behind it what one batch alone needed."""

    def __init__(self):
        self.passing: dict[str, bytes] = {}

    def __missing__(self, w: str) -> bytes:
        return self.passing[w]


class CachedEncoder:
    """Texts to little-endian unsigned 32-bit ids. `blanks`: whether a blank belongs to the pre-token behind it."""

    def __init__(self, path: str, blanks: bool, entries: int = 600_000):
        worker_limits()
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.blanks, self.entries = blanks, entries
        self.known, self.after = _Known(), _Known()
        self.special = [x.content for x in self.lib.get_added_tokens_decoder().values()]
        pieces = [self.lib.id_to_token(i) or "" for i in range(self.lib.get_vocab_size())]
        #: Ids that open a stretch (byte level) or close a pre-token (word level), and how many bytes of text each id stands for.
        self.edge = np.array([x.startswith("\u0120") if blanks else x.endswith("</w>") for x in pieces])
        self.width = np.array([len(x) if blanks else len(x.removesuffix("</w>")) for x in pieces])

    def _learn(self, kept: _Known, words: set, before: str = "") -> None:
        """The first stretches stay, for frequent ones are among them; later ones pass with their batch. Many short stretches go to the library as one text, whose ids are cut again at the stretches' edges; where a stretch's ids don't stand for its own bytes (the library changed some), it goes alone."""
        new = [w for w in words if w not in kept]
        kept.passing = {}
        into = kept if len(kept) + len(new) <= self.entries else kept.passing
        if self.blanks and not before:
            plain = []
        else:
            plain = [w for w in new if w and (not self.blanks or w.strip() is w)]
            spelt = {w for w in plain for s in self.special if s in w}
            plain = [w for w in plain if w not in spelt] if spelt else plain
        joined = set(plain)
        alone = [w for w in new if w not in joined]
        for at in range(0, len(plain), _JOINED):
            block = plain[at : at + _JOINED]
            ids = np.array(self.lib.encode_batch_fast([before + " ".join(block)], add_special_tokens=False)[0].ids, np.uint32)
            # A stretch ends where the ids so far stand for as many bytes as the stretches so far, at an edge of the vocabulary's own.
            size = self.width[ids].cumsum()
            want = np.cumsum([len((w if self.blanks else w.lower()).encode("utf-8", "surrogatepass")) + len(before) for w in block])
            last = np.searchsorted(size, want)
            fits = len(size) > 0 and last[-1] == len(size) - 1 and (size[last] == want).all()
            if not fits or not (self.edge[ids[np.r_[0, last[:-1] + 1]]].all() if self.blanks else self.edge[ids[last]].all()):
                alone += block
                continue
            raw, cuts = ids.tobytes(), np.r_[0, 4 * (last + 1)].tolist()
            for i, w in enumerate(block):
                into[w] = raw[cuts[i] : cuts[i + 1]]
        for w in alone:
            into[w] = self._alone(before + w)

    def _alone(self, text: str) -> bytes:
        return array("I", self.lib.encode(text, add_special_tokens=False).ids).tobytes()

    def encode(self, texts: list[str | None]) -> list[bytes]:
        gc.disable()  # millions of strings and no cycles
        try:
            return self._encode(texts)
        finally:
            gc.enable()

    def _encode(self, texts: list[str | None]) -> list[bytes]:
        if not self.blanks:
            cut = [(t or "").replace("\n", " ").split(" ") for t in texts]
            self._learn(self.known, set().union(*cut))
            return [b"".join(map(self.known.__getitem__, x)) for x in cut]
        cut = [(t or "").split(" ") if not _odd(t or "") else _PLAIN_BLANK.split(t) for t in texts]
        self._learn(self.known, {x[0] for x in cut})
        self._learn(self.after, set().union(*(x[1:] for x in cut)), " ")
        return [self.known[x[0]] + b"".join(map(self.after.__getitem__, x[1:])) for x in cut]


def encoder(path: str, blanks: bool) -> CachedEncoder:
    """One encoder for each file and worker."""
    if path not in _loaded:
        _loaded[path] = CachedEncoder(path, blanks)
    return _loaded[path]


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
