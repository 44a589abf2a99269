"""Vectors of whole texts for the linear models."""

from __future__ import annotations

import numpy as np

MIX = np.uint32(2_654_435_761)
#: Bytes hashed at once.
PART = 1 << 20


def hashed_ngrams(text: bytes, dimensions: int) -> np.ndarray:
    """Counts of the 1- to 3-grams of the bytes of a text, hashed to ``dimensions`` (a power of two)."""
    out, shift = np.zeros(dimensions, np.float32), np.uint32(33 - dimensions.bit_length())
    for start in range(0, len(text), PART):
        codes = np.frombuffer(text[max(start - 2, 0) : start + PART], np.uint8).astype(np.uint32)
        gram = codes
        for n in (1, 2, 3):
            if n > 1:
                gram = gram[:-1] << np.uint32(8) | codes[n - 1 :]
            new = gram[min(start, 2) + 1 - n if start else 0 :] if start else gram
            if len(new):
                out += np.bincount(((new + np.uint32(n << 28)) * MIX) >> shift, minlength=dimensions)
    return out


def shape(text: bytes, words: list[bytes]) -> list[float]:
    """How a text looks: symbols, case, repetition, line and word lengths; each about 0 to 1."""
    n, w = max(len(text), 1), max(len(words), 1)
    lines = [x for x in text.split(b"\n") if x and not x.isspace()]
    pairs = len(set(zip(words, words[1:])))
    upper = sum(map(text.count, map(bytes, zip(range(65, 91)))))
    return [
        float(np.log1p(len(words))) / 10,
        len(text) / w / 20,
        *(min(text.count(c) * 5 / w, 2.0) for c in (b"#", b"*", b"$", b"%", b"&", b"|", b"!", b"<", b"=", b"_")),
        upper / n,
        sum(map(text.count, map(bytes, zip(range(48, 58))))) / n,
        text.count(b".") / w,
        text.count(b",") / w,
        len(set(words)) / w,
        pairs / max(len(words) - 1, 1),
        sum(map(bytes.__eq__, words, words[1:])) / w,
        len(set(lines)) / max(len(lines), 1),
        min(len(lines) / w * 5, 2.0),
        float(len(words) < 10),
    ]
