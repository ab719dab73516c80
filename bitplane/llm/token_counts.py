"""Token counts with the whole-token shortcut.

Offline, every string of the vocabulary is run through the pre-token pattern and
the merges once; those that are one pre-token and come out as one token are
proven whole.  Counting then looks pre-tokens up and merges only the others.
"""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import regex

from .bpe import TO_BYTES, BatchMerger, MergeList, symbols

#: Fixed value: the pre-token pattern of the byte-level vocabulary.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"


def prove_whole(rules: MergeList) -> set[str]:
    """Vocabulary strings that alone are one pre-token and one token."""
    find, whole = regex.compile(PATTERN).findall, set()
    for token in rules.vocab:
        try:
            text = bytes(TO_BYTES[c] for c in token).decode()
        except (KeyError, UnicodeDecodeError):
            continue
        if find(text) == [text] and len(rules.merge(rules.base_ids(token))) == 1:
            whole.add(text)
    return whole


#: Fixed value: the characters of the White_Space property other than space and line feed.
RARE_ASCII, RARE = "\t\x0b\x0c\r", "\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"


def tangled(text: str) -> bool:
    """Whether a blank is not a lone space or line feed between other characters."""
    if text[0] in " \n" or text[-1] in " \n" or any(run in text for run in ("  ", " \n", "\n ", "\n\n")):
        return True
    return any(c in text for c in RARE_ASCII) or not text.isascii() and any(c in text for c in RARE)


class Counts(dict):
    """Tokens by stretch of text, each behind ``lead``: the proven ones and a bounded memo of others."""

    LIMIT, LONG = 800_000, 64

    def __init__(self, rules: MergeList, whole: set[str], lead: str = ""):
        self.rules, self.lead, self.find = rules, lead, regex.compile(PATTERN).findall
        self.proven = {t[len(lead) :]: 1 for t in whole if t.startswith(lead)}
        self.whole = whole
        super().__init__(self.proven)

    def merged(self, pre: str) -> int:
        return 1 if pre in self.whole else len(self.rules.merge(self.rules.base_ids(symbols(pre))))

    def __missing__(self, text: str) -> int:
        n = sum(map(self.merged, self.find(self.lead + text)))
        if len(text) <= self.LONG:
            if len(self) >= self.LIMIT:
                self.clear()
                self.update(self.proven)
            self[text] = n
        return n


class TokenCounter:
    """Counts tokens of whole texts; special strings are one token each.

    Where every blank of a text is a lone space or line feed between other
    characters, a space opens the next pre-token and a line feed is one of its
    own, so the text falls apart at them before the pattern is needed.
    """

    def __init__(self, rules: MergeList, whole: set[str] | None = None):
        whole = prove_whole(rules) if whole is None else whole
        self.bare, self.spaced = Counts(rules, whole), Counts(rules, whole, " ")
        self.find, self.batch, self.whole = regex.compile(PATTERN).findall, BatchMerger(rules), whole
        self.special = regex.compile("|".join(map(regex.escape, rules.special))) if rules.special else None

    def learn(self, texts: Iterable[str]) -> None:
        """Adds the new short stretches of many texts to the memo with one pass of the pattern and one of the merges."""
        new: set[str] = set()
        for text in texts:
            if text and "<|" not in text and not tangled(text):
                for line in text.split("\n"):
                    new.update(line.split(" ")[1:])
        order = [c for c in new.difference(self.spaced) if len(c) <= Counts.LONG]
        if len(order) < 64:
            return
        if len(self.spaced) + len(order) > Counts.LIMIT:
            self.spaced.clear()
            self.spaced.update(self.spaced.proven)
        pre = self.find(" " + " ".join(order))
        rest = [i for i, p in enumerate(pre) if p not in self.whole]
        sizes = np.ones(len(pre), np.int64)
        if rest:
            sizes[rest] = np.diff(self.batch.ids([pre[i] for i in rest])[1])
        heads = np.flatnonzero(np.fromiter((p[0] == " " for p in pre), bool, len(pre)))
        self.spaced.update(zip(order, np.add.reduceat(sizes, heads).tolist()))

    def plain(self, text: str) -> int:
        if not text:
            return 0
        if tangled(text):
            return sum(map(self.bare.__getitem__, self.find(text)))
        lines = text.split("\n")
        n = (len(lines) - 1) * self.bare["\n"]
        for line in lines:
            first, *rest = line.split(" ")
            n += self.bare[first] + sum(map(self.spaced.__getitem__, rest))
        return n

    def count(self, text: str | None) -> int:
        """Null counts as empty: no token."""
        if not text:
            return 0
        if self.special is None or "<|" not in text:
            return self.plain(text)
        parts = self.special.split(text)
        return len(parts) - 1 + sum(map(self.plain, parts))
