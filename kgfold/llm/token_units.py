"""Whole-text token ids by the tokenizers library, made unit by unit.

A text is cut at white space into units that the tokenizer would never join, each distinct unit is encoded once per
worker process, and a text's ids are the concatenation.  Which cut is safe depends on the pre-tokenizer, so it is read
from the tokenizer file; for a kind not known here texts are encoded whole.  Texts holding ``<|`` (the start of a
special token) are encoded whole as well.  New units of ASCII are cut further, by the pre-tokenizer's own pattern:
most are known words beside punctuation or digits, so that only new pieces reach the tokenizer.
"""

from __future__ import annotations

import json
import os
import re
import sys
from array import array
from itertools import islice

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
os.environ.setdefault("RAYON_NUM_THREADS", "1")

#: The characters that have Unicode's White_Space property.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: The patterns whose ASCII form is known: letters there are lower-cased before the cut in the first.
WORDS = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
LOWER = [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]
_WORD_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\t-\r a-z0-9]+").findall
_BYTE_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?[A-Za-z]+| ?[0-9]+| ?[^\t-\r A-Za-z0-9]+|[\t-\r ]+").findall
_NATIVE = sys.byteorder == "little" and array("I").itemsize == 4
_OPEN: dict[str, UnitEncoder] = {}


class UnitEncoder:
    """``max_units`` bounds the cache (about 350 bytes a unit); a full cache keeps the half it met first, which holds
    the frequent units, so results don't change and rare units make way."""

    def __init__(self, path: str, max_units: int = 600_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.max_units = max_units
        self.cache: dict[str, bytes] = {}
        made = json.loads(self.tokenizer.to_str())
        pre, normal = made["pre_tokenizer"] or {}, made["normalizer"]
        steps = pre.get("pretokenizers", [pre])
        self.units = self.pieces = None
        if pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space"):
            self.units = re.compile(rf" ?[^{WHITE}]+|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+").findall
            if normal is None:
                self.pieces = _BYTE_PIECES
        elif steps[0].get("type") == "Split" and steps[0].get("behavior") == "Removed" and steps[0].get("invert") and r"[^\s\p{L}\p{N}]+" in (steps[0].get("pattern") or {}).get("Regex", ""):
            self.units = lambda text: text.replace("\n", " ").split(" ")  # the empty unit has no ids
            if steps[0]["pattern"]["Regex"] == WORDS and (normal or {}).get("normalizers") == LOWER:
                self.pieces = lambda unit: _WORD_PIECES(unit.lower())

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [_bytes(e.ids) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _learn(self, units: set[str]) -> None:
        cache, todo, joined = self.cache, [], {}
        if self.pieces is None:
            todo = list(units)
        else:
            cut, new = self.pieces, set()
            for u in units:
                if not u.isascii():
                    new.add(u)
                elif (parts := cut(u)) == [u]:
                    new.add(u)
                else:
                    joined[u] = parts
                    new.update(p for p in parts if p not in cache)
            todo = list(new)
        for i in range(0, len(todo), 50_000):
            part = todo[i : i + 50_000]
            cache.update(zip(part, self._whole(part), strict=True))
        get = cache.__getitem__
        cache.update([(u, b"".join(map(get, parts))) for u, parts in joined.items()])

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        if self.units is None:
            return self._whole(texts)
        cut, cache = self.units, self.cache
        if len(cache) > self.max_units:
            self.cache = cache = dict(islice(cache.items(), self.max_units // 2))
        plain = [None if "<|" in t else cut(t) for t in texts]
        found = [None if u is None else list(map(cache.get, u)) for u in plain]
        missing: set[str] = set()
        for u, f in zip(plain, found, strict=True):
            if f is not None and None in f:
                missing.update(x for x, ids in zip(u, f, strict=True) if ids is None)
        self._learn(missing)
        get, out = cache.__getitem__, []
        for t, u, f in zip(texts, plain, found, strict=True):
            out.append(self._whole([t])[0] if u is None else b"".join(map(get, u) if None in f else f))
        return out


def _bytes(ids: list[int]) -> bytes:
    return array("I", ids).tobytes() if _NATIVE else np.asarray(ids, "<u4").tobytes()


def encoder(path: str) -> UnitEncoder:
    """One encoder per worker process and file."""
    if path not in _OPEN:
        _OPEN[path] = UnitEncoder(path)
    return _OPEN[path]
