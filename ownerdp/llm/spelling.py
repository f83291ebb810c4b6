"""How a word of several subwords goes on after its first one: by the counts of whole words, backing off to its spelling.

The spelling of a word is a chain of its subwords: the group of the next subword (or that the word ends) by the last one, and the subword by its share in
the group. The frequent subwords are groups of their own, the others share a few. All counts are of distinct words, each once, as words
that were never seen are built like kinds of words, not like frequent ones. The tables' size depends on the vocabulary alone.
"""

from __future__ import annotations

import numpy as np

SINGLE, SHARED = 240, 15
GROUPS = SINGLE + SHARED + 1  # the last one: the word ends
ENDS = GROUPS - 1
#: What every seen word gives to the unseen ones.
DISCOUNT = 0.75
#: Imagined words for each first subword, and for each last subword, ahead of all counts.
PRIOR, STRENGTH = 0.3, 4.0


def groups(counts: np.ndarray) -> np.ndarray:
    """The group of each id, by how often it goes on a word."""
    n = len(counts)
    out = SINGLE + (np.arange(n, dtype=np.uint64) * np.uint64(2654435761) % np.uint64(1 << 32) >> np.uint64(16)).astype(np.int64) % SHARED
    top = np.argsort(-counts, kind="stable")[:SINGLE]
    out[top] = np.arange(len(top))
    return out


def cells(ids: np.ndarray, lengths: np.ndarray, group: np.ndarray) -> np.ndarray:
    """What distinct words laid end to end add to the tables, as places in one flat row of ``table_size`` counts: pairs of a subword and the
    next one's group, subwords that go on a word, first subwords of the words that go on."""
    n = len(group)
    last = np.cumsum(lengths) - 1
    follows = np.ones(len(ids), bool)
    follows[last - lengths + 1] = False
    nxt = np.append(group[ids[1:]], ENDS)
    nxt[last] = ENDS
    longer = ids[(last - lengths + 1)[lengths > 1]]
    return np.concatenate([ids * GROUPS + nxt, n * GROUPS + ids[follows], n * (GROUPS + 1) + longer])


def table_size(n: int) -> int:
    return n * (GROUPS + 2)


class Spelling:
    """at, counts: the cells that are not zero; n_longer: tokens by first subword whose words go on; may_follow: ids that can go on a word."""

    def __init__(self, at: np.ndarray, counts: np.ndarray, n_longer: np.ndarray, group: np.ndarray, may_follow: np.ndarray):
        n = len(group)
        flat = np.zeros(table_size(n), np.float32)
        flat[at] = counts
        pairs, goes_on, kinds = flat[: n * GROUPS].reshape(n, GROUPS), flat[n * GROUPS : n * (GROUPS + 1)].astype(float), flat[n * (GROUPS + 1) :].astype(float)
        share = pairs.sum(axis=0) + 0.1
        share /= share.sum()
        total = pairs.sum(axis=1, keepdims=True)
        pairs += np.float32(STRENGTH) * share
        pairs /= total + np.float32(STRENGTH)
        self.goes_on = np.log1p(-pairs[:, ENDS].astype(float))  # the first subword of a word that is known not to end there
        self.log_next = np.log(pairs, out=pairs)
        weight = goes_on + 0.05 * may_follow
        self.log_in_group = np.log(np.maximum(weight, 1e-9) / np.maximum(np.bincount(group, weight, GROUPS), 1e-9)[group])
        self.group, self.log_mass, self.n_longer = group, np.log(DISCOUNT * kinds + PRIOR), n_longer + PRIOR

    def spell(self, ids: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Of words laid end to end, the log probability of all but the first subword, for words that have more."""
        if not len(lengths):
            return np.zeros(0)
        last = np.cumsum(lengths) - 1
        begin = last - lengths + 1
        nxt = np.append(self.group[ids[1:]], ENDS)
        nxt[last] = ENDS
        each = self.log_next[ids, nxt].astype(float)
        inside = self.log_in_group[ids]
        inside[begin] = 0
        return np.add.reduceat(each + inside, begin) - self.goes_on[ids[begin]]

    def parts(self, ids: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each word the share of unseen words that it has, in tokens, and the tokens of its first subword: a word that was seen c
        times goes on as it does with probability (max(c - DISCOUNT, 0) + share) / tokens; 0 and 0 for words of one subword."""
        first = ids[np.cumsum(lengths) - lengths]
        share = np.exp(self.log_mass[first] + self.spell(ids, lengths))
        one = lengths == 1
        return np.where(one, 0.0, share), np.where(one, 0.0, self.n_longer[first])


def log10_form(counts: np.ndarray, share: np.ndarray, tokens: np.ndarray) -> np.ndarray:
    """log10 of the probability that a word goes on as it does; zero for words of one subword."""
    longer = tokens > 0
    return np.where(longer, np.log10((np.maximum(counts - DISCOUNT, 0) + share) / np.where(longer, tokens, 1.0), where=longer, out=np.zeros(len(counts))), 0.0)
