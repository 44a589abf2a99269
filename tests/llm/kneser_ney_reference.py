"""The model of ``canopy.llm.kneser_ney`` in one process, as a reference for small corpora."""

from __future__ import annotations

from collections import Counter

import numpy as np

from canopy.llm.kneser_ney import MULTIPLIER, ORDER, PRUNED, in_parts


def grams(words: list[bytes]) -> tuple[np.ndarray, list[tuple[np.ndarray, np.ndarray, np.ndarray]]]:
    """For every predicted character of all words: the index of its word, and
    for each order the n-gram's hash, its context's hash and whether it exists.

    A word is start mark, its code points, end mark; the start is not predicted.
    """
    texts = [w.decode("utf-8", "replace") for w in words]
    length = np.array([len(t) + 2 for t in texts], np.int64)
    codes = np.frombuffer("".join(f"\x02{t}\x03" for t in texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)
    owner = np.repeat(np.arange(len(texts)), length)
    place = np.arange(len(codes)) - np.repeat(np.cumsum(length) - length, length)
    predicted = place > 0
    gram = context = np.zeros(len(codes), np.uint64)
    orders = []
    for m in range(1, ORDER + 1):  # what stands m-1 characters before is mixed in last: a shorter n-gram is the suffix
        before = np.concatenate([np.zeros(m - 1, np.uint64), codes[: max(len(codes) - m + 1, 0)]])[: len(codes)]
        gram = (gram ^ before + np.uint64(m)) * MULTIPLIER
        gram ^= gram >> np.uint64(29)
        if m > 1:
            context = (context ^ before + np.uint64(m + 64)) * MULTIPLIER
            context ^= context >> np.uint64(29)
        orders.append((gram.view(np.int64)[predicted], context.view(np.int64)[predicted], (place >= m - 1)[predicted]))
    return owner[predicted], orders


class Model:
    """Interpolated modified Kneser-Ney probabilities in sorted hash arrays."""

    def __init__(self, table: dict[str, np.ndarray]):
        """``table``: columns m, gram, suffix, context, n of the counted n-grams."""
        self.gram, self.logp, self.context, self.back_off = [None], [None], [None], [None]
        lower = shorter = None
        for m in range(1, ORDER + 1):
            own = table["m"] == m
            order = np.argsort(table["gram"][own])
            gram, suffix, context, n = (table[c][own][order].astype(np.int64) for c in ("gram", "suffix", "context", "n"))
            if m < ORDER:  # distinct characters that stand before it; n-grams with the start mark have none
                before, kinds = np.unique(table["suffix"][table["m"] == m + 1], return_counts=True)
                at = np.minimum(np.searchsorted(before, gram), max(len(before) - 1, 0))
                n = np.where(before[at] == gram, kinds[at], n) if len(before) else n
            discount = self.discounts(n)[np.minimum(n, 3)] if len(n) else np.zeros(0)
            kept = n > 1 if m >= PRUNED else n > 0
            discount = np.where(kept, discount, n)  # what is pruned leaves its whole mass to the back-off
            contexts, of = np.unique(context, return_inverse=True)
            total = np.bincount(of, weights=n, minlength=len(contexts))
            freed = np.bincount(of, weights=discount, minlength=len(contexts)) / np.maximum(total, 1)
            if m == 1:
                self.floor = -np.log(len(gram) + 1)
                below = np.full(len(gram), np.exp(self.floor))
            else:
                below = lower[np.minimum(np.searchsorted(shorter, suffix), max(len(lower) - 1, 0))] if len(suffix) else np.zeros(0)
            lower = np.maximum(n - discount, 0) / np.maximum(total[of], 1) + freed[of] * below
            shorter = gram
            self.gram.append(gram[kept])
            self.logp.append(np.log(np.maximum(lower[kept], 1e-12)))
            self.context.append(contexts)
            self.back_off.append(np.log(np.maximum(freed, 1e-12)))

    @staticmethod
    def discounts(n: np.ndarray) -> np.ndarray:
        """Of counts 0, 1, 2 and 3 or more, from the counts of counts."""
        n1, n2, n3, n4 = (max(int((n == k).sum()), 1) for k in range(1, 5))
        y = n1 / (n1 + 2 * n2)
        return np.clip([0, 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3], [0, 0.05, 0.05, 0.05], [0, 0.95, 1.9, 2.9])

    def score(self, words: list[bytes]) -> np.ndarray:
        """Log-probability of each word with its end mark."""
        out = []
        for part in in_parts(words):
            owner, orders = grams(part)
            logp, open_ = np.zeros(len(owner)), np.ones(len(owner), bool)
            for m in range(ORDER, 0, -1):
                gram, context, ok = orders[m - 1]
                at = np.flatnonzero(ok & open_)
                found, p = self.look_up(self.gram[m], self.logp[m], gram[at])
                logp[at] += p
                open_[at[found]] = False
                at = at[~found]
                logp[at] += self.look_up(self.context[m], self.back_off[m], context[at])[1]
            logp[open_] += self.floor
            out.append(np.bincount(owner, weights=logp, minlength=len(part)))
        return np.concatenate(out) if out else np.zeros(0)

    @staticmethod
    def look_up(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(keys):
            return np.zeros(len(wanted), bool), np.zeros(len(wanted))
        at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
        found = keys[at] == wanted
        return found, np.where(found, values[at], 0.0)


def train(docs) -> Model:
    counts = Counter(w for r in docs.select("text").collect() for w in (r["text"] or "").encode().split())
    owner, orders = grams(list(counts))
    times, rows = list(counts.values()), {}
    for m, (gram, context, ok) in enumerate(orders, 1):
        suffix = orders[m - 2][0] if m > 1 else np.zeros_like(gram)
        for o, g, s, c in zip(*(a[ok].tolist() for a in (owner, gram, suffix, context))):
            row = rows.setdefault((m, g), [m, g, s, c, 0])
            row[4] += times[o]
    return Model({c: np.array([r[k] for r in rows.values()], np.int64) for k, c in enumerate(("m", "gram", "suffix", "context", "n"))})
