"""Text as an image: tokens, the word raster, and signed shingle features."""

from __future__ import annotations

import hashlib
import re

import numpy as np
from pyspark.sql import Column, functions as F

from .arithmetic import SIDE, gradient_bits, luminance, pack

TOKEN = r"([\p{L}\p{N}]+)"
_DIGIT = re.compile("[0-9]")


def flat(text: Column) -> Column:
    """Lower-cased tokens with single spaces between them, made in the JVM."""
    return F.trim(F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", " "))


def normalised(text: Column, least: int = 5) -> Column:
    """The analogue of an aligned crop: tokens of at least two letters without digits; null below ``least`` of them."""
    words = F.filter(F.split(flat(text), " "), lambda w: (F.length(w) > 1) & ~w.rlike("[0-9]"))
    return F.when(F.size(words) >= least, F.array_join(words, " "))


def main_content(html: Column) -> Column:
    """Text of a page without script, style, navigation, header and footer; null where nothing is left."""
    body = F.regexp_replace(html, r"(?is)<(script|style|nav|header|footer|aside)\b.*?</\1>", " ")
    words = F.trim(F.regexp_replace(F.regexp_replace(body, r"(?s)<[^>]*>", " "), r"\s+", " "))
    return F.when(F.length(words) > 0, words)


class Digests(dict):
    """Words to the first ``n`` hexadecimal digits of their md5 as a number; with ``flag`` a further bit says whether the word stays in the normalised text. Forgets at 500,000 words."""

    def __init__(self, n: int, flag: bool = False):
        self.n, self.flag = n, flag

    def __missing__(self, word: str) -> int:
        if len(self) > 500_000:
            self.clear()
        v = int(hashlib.md5(word.encode()).hexdigest()[: self.n], 16)
        if self.flag and len(word) > 1 and not _DIGIT.search(word):
            v |= 1 << 4 * self.n
        self[word] = v
        return v

    def of(self, words: list[str]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.int64, len(words))


def lines_of(text: Column) -> Column:
    """Lower-cased tokens with single spaces between them, line by line, made in the JVM in one pass over the text."""
    return F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}\n]+", " ")


def rasters(doc: np.ndarray, digits: np.ndarray, n: int) -> np.ndarray:
    """(n, 32, 32) brightness of word counts for the tokens of ``n`` texts; a token's cell is its three digits modulo 1024."""
    return luminance(np.bincount(doc * SIDE * SIDE + digits % (SIDE * SIDE), minlength=n * SIDE * SIDE)).reshape(n, SIDE, SIDE)


def token_rasters(texts: list[str | None], digests: Digests) -> np.ndarray:
    """Rasters of texts that are tokens already."""
    words = [(t or "").split() for t in texts]
    doc = np.repeat(np.arange(len(words)), [len(x) for x in words])
    return rasters(doc, digests.of([w for x in words for w in x]) & 4095, len(words))


def gradients(region: np.ndarray, digits: np.ndarray, n: int) -> np.ndarray:
    """(n, 2) halves of the gradient hash of ``n`` pieces of text: token counts over 8 x 9 cells (three digits modulo 72), each compared with its left neighbour."""
    return pack(gradient_bits(np.bincount(region * 72 + digits % 72, minlength=n * 72).reshape(n, 8, 9))) if n else np.zeros((0, 2), np.int64)


def region_signatures(doc: np.ndarray, line: np.ndarray, digits: np.ndarray, n: int, least: int = 5) -> list[str]:
    """The crop-tolerant hash of ``n`` texts: the gradient hashes of their lines of at least ``least`` tokens, or of the whole text where there is none, as one checksum of the list.

    ``line`` numbers the lines over all texts, ascending.
    """
    name, at, count = np.unique(line, return_inverse=True, return_counts=True)
    owner = np.zeros(len(name), np.int64)
    owner[at] = doc
    large = count >= least
    number = np.cumsum(large) - 1
    own = large[at]
    h = gradients(number[at[own]], digits[own], int(large.sum()))
    whole = gradients(doc, digits, n)
    parts: list[list[str]] = [[] for _ in range(n)]
    for d, (hi, lo) in zip(owner[large].tolist(), h.tolist()):
        parts[d].append(f"{hi}:{lo}")
    return [hashlib.md5(("-".join(x) or "{}:{}".format(*whole[i].tolist())).encode()).hexdigest() for i, x in enumerate(parts)]


def shingle_features(words: list[str], digests: Digests, k: int = 3, size: int = 64) -> list[int] | None:
    """Signed counts of word shingles: bucket h mod 64, sign by bit 6 of h, h four digits of the md5. None without a token."""
    if not words:
        return None
    h = digests.of([" ".join(words[i : i + k]) for i in range(max(1, len(words) - k + 1))])
    return np.bincount(h % size, weights=np.where(h >> 6 & 1, -1, 1), minlength=size).astype(np.int64).tolist()
