"""Token ids of whole texts with a public byte-level BPE, each distinct word encoded once.

A space between two characters that are not white space always starts a new pre-token of this
kind of tokenizer; so does a comma or full stop after a letter or digit, and a lone line feed is one of
its own. Merges never cross pre-tokens, so a text's ids are the concatenation of its parts' ids,
which are kept in a bounded cache; unseen parts are encoded by the tokenizers library many at a time
and cut apart by the known byte length of every id. Texts with runs of white space or unusual
punctuation are cut at safe spaces only. Texts that hold the string of an added token (which the library turns
into that token's id) are encoded whole.
"""

from __future__ import annotations

import gc
import json
import re
from functools import lru_cache

import numpy as np

#: parts kept at most, and characters in a part that is kept
CACHE, PART = 700_000, 40

#: what rules out the cheap cuts: white space in a row or at an end, a mark after no Latin letter or digit
_ODD = re.compile("\\s\\s|^\\s|\\s$|(?<![A-Za-z0-9\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f])[.,]|\0")
#: a text of these characters alone needs only the pairs below looked for
_OTHER = re.compile("[^A-Za-z0-9\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f .,\n]")
_PAIRS = ("  ", " \n", "\n ", "\n\n", " .", "\n.", "..", ",.", " ,", "\n,", ".,", ",,")
_SAFE = re.compile(r"(?<=\S)(?= \S)")
_BLOCK = 4000


def default_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def odd(t: str) -> bool:
    if _OTHER.search(t) or not t or t[0] in " \n.," or t[-1] in " \n":
        return bool(_ODD.search(t))
    return any(p in t for p in _PAIRS)


class Encoder:
    """ids(texts) gives the raw little-endian ids of each whole text, ``width`` bytes an id."""

    def __init__(self, path: str, cache: int = CACHE):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tk = Tokenizer.from_file(path)
        vocab = self.tk.get_vocab()
        self.width = 2 if max(vocab.values()) < 1 << 16 else 4
        self.kind = np.dtype(f"<u{self.width}")
        self.lengths = np.zeros(max(vocab.values()) + 1, np.int64)
        for t, i in vocab.items():
            self.lengths[i] = len(t)  # one character of a token's name is one byte
        told = json.loads(self.tk.to_str())
        pre = told.get("pre_tokenizer") or {}
        self.regular = pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
        self.regular = self.regular and not told.get("normalizer")
        self.added = [t["content"] for t in told.get("added_tokens") or []]
        self.known: dict[str, bytes] = {}
        self.cache = cache

    def _whole(self, texts: list[str]) -> list[bytes]:
        out = []
        for i in range(0, len(texts), 256):
            got = self.tk.encode_batch_fast(texts[i : i + 256], add_special_tokens=False)
            out += [np.array(e.ids, self.kind).tobytes() for e in got]
        return out

    def _joined(self, parts: list[str], gap: str) -> dict[str, bytes]:
        """Ids of parts that neither start nor end with white space but for a first space; ``gap`` keeps them apart."""
        out: dict[str, bytes] = {}
        for i in range(0, len(parts), _BLOCK):
            some = parts[i : i + _BLOCK]
            ids = np.array(self.tk.encode_batch_fast([gap + gap.join(some)], add_special_tokens=False)[0].ids, self.kind)
            ends = np.cumsum(np.fromiter(map(len, map(str.encode, some)), np.int64, len(some)) + len(gap))
            reach = np.cumsum(self.lengths[ids])
            cut = np.searchsorted(reach, ends)
            skip = np.concatenate([[0], cut[:-1] + 1])
            fits = len(reach) and reach[-1] == ends[-1] and (reach[np.minimum(cut, len(reach) - 1)] == ends).all()
            if not fits or gap and (self.lengths[ids[skip]] != len(gap)).any():
                out.update(zip(some, self._whole(some)))
                continue
            raw, first = ids.tobytes(), len(gap) * self.width
            for p, lo, hi in zip(some, (skip * self.width + first).tolist(), ((cut + 1) * self.width).tolist()):
                out[p] = raw[lo:hi]
        return out

    def ids(self, texts: list[str]) -> list[bytes]:
        if not self.regular:
            return self._whole(texts)
        collecting = gc.isenabled()
        gc.disable()  # many small objects and no cycles
        try:
            return self._ids(texts)
        finally:
            if collecting:
                gc.enable()

    def _ids(self, texts: list[str]) -> list[bytes]:
        special = [i for a in self.added for i, t in enumerate(texts) if a in t]
        if not special:
            return self._plain(texts)
        whole = dict(zip(special, self._whole([texts[i] for i in special])))
        rest = iter(self._plain([t for i, t in enumerate(texts) if i not in whole]))
        return [whole[i] if i in whole else next(rest) for i in range(len(texts))]

    def _plain(self, texts: list[str]) -> list[bytes]:
        split, new = [], set()
        for t in texts:
            if odd(t):
                p = _SAFE.split(t)
            else:
                t = t.replace(" ", "\0 ").replace(".", "\0.").replace(",", "\0,").replace("\n", "\0\n\0")
                p = t.split("\0")
            new.update(p)
            split.append(p)
        if len(self.known) > self.cache:  # only what is in use stays
            self.known = {p: self.known[p] for p in new if p in self.known}
        new = new.difference(self.known)
        spaced, bare, rest = [], [], []
        for p in new:
            if p and not p[-1].isspace():
                if p[0] == " ":
                    if not p[1].isspace():
                        spaced.append(p)
                        continue
                elif not p[0].isspace():
                    bare.append(p)
                    continue
            rest.append(p)
        fresh = self._joined(spaced, "")
        fresh.update(self._joined(bare, "\n"))
        fresh.update(zip(rest, self._whole(rest)))
        long = {p: fresh.pop(p) for p in [p for p in fresh if len(p) > PART]}
        self.known.update(fresh)
        if not long:
            get = self.known.__getitem__
        else:
            kept = self.known
            get = lambda p: long[p] if len(p) > PART else kept[p]
        if long:
            return [b"".join(map(get if max(map(len, p)) > PART else self.known.__getitem__, p)) for p in split]
        return [b"".join(map(get, p)) for p in split]


@lru_cache(2)
def encoder(path: str, cache: int = CACHE) -> Encoder:
    """One encoder per worker process, vocabulary and cache size."""
    return Encoder(path, cache)
