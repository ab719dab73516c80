"""Byte-pair encoding as a streaming transducer with bounded lookahead, and its decoder.

The merge list decides how far to the right of a token boundary the text can
still move it.  Take two words that share a prefix and apply the rules in rank
order.  A rule (a, b) can only make the shared tokenization one token shorter,
by joining its last token a to a b that starts at the border in one of the words
alone; the text right of the new border then starts with a in both.  So the
border moves along chains of rules of rising rank in which the right part of
each starts with the left part of the one before, and the longest total of left
parts over all chains is a sufficient lookahead: tokens that end that many
symbols before the end of what has been read are final.  The bound needs a
proper list (all rules that make a string rank below all rules that use it),
which is checked; words of improper lists are held whole.
"""

from __future__ import annotations

import codecs
import heapq
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import regex

#: The byte-to-character table keeps printable Latin-1 bytes and moves the others up from U+0100.
PRINTABLE = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]


def byte_characters() -> list[str]:
    table, extra = [""] * 256, 0
    for b in range(256):
        if b in PRINTABLE:
            table[b] = chr(b)
        else:
            table[b], extra = chr(0x100 + extra), extra + 1
    return table


BYTE_CHARS = byte_characters()
TO_SYMBOLS = {b: c for b, c in enumerate(BYTE_CHARS)}
TO_BYTES = {c: b for b, c in enumerate(BYTE_CHARS)}


def symbols(word: str) -> str:
    """The word's UTF-8 bytes, one character each."""
    return word.encode("utf-8", "surrogatepass").decode("latin-1").translate(TO_SYMBOLS)


class MergeList:
    """Vocabulary and ranked merges of a tokenizer file."""

    def __init__(self, definition: dict):
        model = definition["model"]
        self.vocab: dict[str, int] = model["vocab"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        #: Rank by the two ids of a rule, and the id that each rule makes.
        self.rank_of = {self.vocab[a] << 20 | self.vocab[b]: k for k, (a, b) in enumerate(merges)}
        self.made = [self.vocab[a + b] for a, b in merges]
        self.never = len(merges)
        self.special = {t["content"]: t["id"] for t in definition.get("added_tokens", ())}
        self.names = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        self.proper = self._proper(merges)
        self.lookahead = self._lookahead(merges) if self.proper else None

    @classmethod
    def load(cls, path: str) -> MergeList:
        with open(path, encoding="utf-8") as f:
            return cls(json.load(f))

    @staticmethod
    def _proper(merges: list[tuple[str, str]]) -> bool:
        made: dict[str, int] = {}
        for k, (a, b) in enumerate(merges):
            made[a + b] = k
        return all(made.get(part, -1) < k for k, pair in enumerate(merges) for part in pair)

    @staticmethod
    def _lookahead(merges: list[tuple[str, str]]) -> int:
        best: dict[str, int] = {}
        most = 0
        for a, b in merges:
            reach = len(a) + max((best.get(b[:i], 0) for i in range(1, len(b) + 1)), default=0)
            best[a] = max(best.get(a, 0), reach)
            most = max(most, reach)
        return most + 1

    def base_ids(self, syms: str, ends: bool = False) -> list[int]:
        """Ids of single symbols; ``ends`` marks the last as the end of its word."""
        ids = [self.vocab[c] for c in syms]
        if ends and self.suffix:
            ids[-1] = self.vocab[syms[-1] + self.suffix]
        return ids

    def merge(self, ids: list[int]) -> list[int]:
        """Applies the merges, lowest rank first and leftmost among equals."""
        if len(ids) > 96:
            return self._merge_many(ids)
        rank, made, never = self.rank_of.get, self.made, self.never
        ranks = [rank(a << 20 | b, never) for a, b in zip(ids, ids[1:])]
        while ranks and (low := min(ranks)) < never:
            i = ranks.index(low)
            ids[i : i + 2] = [made[low]]
            del ranks[i]
            if i:
                ranks[i - 1] = rank(ids[i - 1] << 20 | ids[i], never)
            if i < len(ranks):
                ranks[i] = rank(ids[i] << 20 | ids[i + 1], never)
        return ids

    def _merge_many(self, ids: list[int]) -> list[int]:
        n, rank, made = len(ids), self.rank_of.get, self.made
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := rank(ids[i] << 20 | ids[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            low, i, a, b = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j < 0 or ids[j] != b:
                continue
            ids[i], ids[j] = made[low], -1
            after[i] = k = after[j]
            if k >= 0:
                before[k] = i
                if (r := rank(ids[i] << 20 | ids[k])) is not None:
                    heapq.heappush(heap, (r, i, ids[i], ids[k]))
            if (h := before[i]) >= 0 and (r := rank(ids[h] << 20 | ids[i])) is not None:
                heapq.heappush(heap, (r, h, ids[h], ids[i]))
        return [i for i in ids if i >= 0]

    def word_ids(self, syms: str) -> list[int]:
        """Ids of one whole word given as symbols."""
        return self.merge(self.base_ids(syms, ends=True))


class PairTable:
    """Ranks of id pairs for whole arrays: open addressing, multiplicative hash."""

    BITS, FACTOR = 18, np.uint64(0x9E3779B97F4A7C15)

    def __init__(self, rules: MergeList):
        self.never = rules.never
        self.keys = np.full(1 << self.BITS, -1, np.int64)
        self.ranks = np.full(1 << self.BITS, self.never, np.int32)
        left = np.fromiter(rules.rank_of, np.int64, len(rules.rank_of))
        ranks = np.fromiter(rules.rank_of.values(), np.int32, len(left))
        at = self.place(left)
        while len(left):
            free = self.keys[at] < 0
            self.keys[at[free]] = left[free]
            own = self.keys[at] == left
            self.ranks[at[own]] = ranks[own]
            left, ranks, at = left[~own], ranks[~own], (at[~own] + 1) & ((1 << self.BITS) - 1)

    def place(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * self.FACTOR) >> np.uint64(64 - self.BITS)).astype(np.int64)

    def of(self, keys: np.ndarray) -> np.ndarray:
        at = self.place(keys)
        found = self.keys[at]
        out = np.where(found == keys, self.ranks[at], self.never).astype(np.int32)
        open_ = np.flatnonzero((found != keys) & (found >= 0))
        while len(open_):
            at[open_] = (at[open_] + 1) & ((1 << self.BITS) - 1)
            found = self.keys[at[open_]]
            hit = found == keys[open_]
            out[open_[hit]] = self.ranks[at[open_[hit]]]
            open_ = open_[~hit & (found >= 0)]
        return out


class BatchMerger:
    """Merges many short words at once: every round applies each word's lowest rule."""

    def __init__(self, rules: MergeList):
        self.rules, self.pairs = rules, PairTable(rules)
        self.made = np.array(rules.made, np.int64)
        self.base = np.array([rules.vocab.get(c, -1) for c in BYTE_CHARS], np.int64)
        self.last = np.array([rules.vocab.get(c + rules.suffix, -1) for c in BYTE_CHARS], np.int64)

    def ids(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in a row, and the places where each word's ids begin (one more at the end)."""
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        flat = np.frombuffer(b"".join(raw), np.uint8)
        ids = self.base[flat]
        ends = np.cumsum(sizes)
        ids[ends - 1] = self.last[flat[ends - 1]]
        owner = np.repeat(np.arange(len(raw)), sizes)
        rank = np.full(len(ids), self.pairs.never, np.int32)
        inner = np.flatnonzero(owner[:-1] == owner[1:])
        rank[inner] = self.pairs.of(ids[inner] << 20 | ids[inner + 1])
        done: list[tuple[np.ndarray, np.ndarray]] = []
        while len(ids):
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            low = np.minimum.reduceat(rank, starts)
            sizes = np.diff(np.r_[starts, len(ids)])
            going = np.repeat(low < self.pairs.never, sizes)
            if not going.all():
                done.append((owner[~going], ids[~going]))
                ids, owner, rank = ids[going], owner[going], rank[going]
                live = low < self.pairs.never
                low, sizes = low[live], sizes[live]
                if not len(ids):
                    break
            hit = np.flatnonzero(rank == np.repeat(low, sizes))
            chained = np.r_[False, hit[1:] == hit[:-1] + 1]
            if chained.any():  # of a run of equal overlapping pairs every other one, from the left
                run = np.cumsum(~chained) - 1
                first = hit[~chained]
                hit = hit[(hit - first[run]) % 2 == 0]
            ids[hit] = self.made[rank[hit]]
            keep = np.ones(len(ids), bool)
            keep[hit + 1] = False
            where = np.cumsum(keep) - 1
            ids, owner, rank = ids[keep], owner[keep], rank[keep]
            at = where[hit]
            touched = np.zeros(len(ids), bool)
            touched[at] = touched[at[at > 0] - 1] = True
            near = np.flatnonzero(touched)
            rank[near] = self.pairs.never
            near = near[near + 1 < len(ids)]
            near = near[owner[near] == owner[near + 1]]
            rank[near] = self.pairs.of(ids[near] << 20 | ids[near + 1])
        owner = np.concatenate([o for o, _ in done]) if done else np.empty(0, np.int64)
        flat_ids = np.concatenate([i for _, i in done]) if done else np.empty(0, np.int64)
        order = np.argsort(owner, kind="stable")
        begins = np.searchsorted(owner[order], np.arange(len(raw) + 1))
        return flat_ids[order], begins


class OpenWord:
    """A word that arrives in parts; keeps lookahead + step symbols at most."""

    def __init__(self, rules: MergeList, step: int = 4096):
        self.rules, self.step, self.held = rules, step, ""

    def push(self, syms: str) -> list[int]:
        out: list[int] = []
        ahead = self.rules.lookahead
        for i in range(0, len(syms), self.step):
            self.held += syms[i : i + self.step]
            if ahead is None or len(self.held) <= ahead + self.step:
                continue
            done, final = 0, len(self.held) - ahead
            for i in self.rules.merge(self.rules.base_ids(self.held)):
                size = len(self.rules.names[i])
                if done + size > final:
                    break
                out.append(i)
                done += size
            self.held = self.held[done:]
        return out

    def close(self) -> list[int]:
        held, self.held = self.held, ""
        return self.rules.word_ids(held) if held else []


class ChunkIds(dict):
    """Ids (little-endian 32-bit) by closed stretch of normal text; bounded, filled on demand.  Ids stand for themselves."""

    LIMIT, LONG = 800_000, 64

    def __init__(self, encode):
        super().__init__()
        self.encode = encode

    def __missing__(self, chunk: str | bytes) -> bytes:
        if isinstance(chunk, bytes):
            return chunk
        ids = packed(self.encode(chunk))
        if len(chunk) <= self.LONG:
            if len(self) >= self.LIMIT:
                self.clear()
            self[chunk] = ids
        return ids


def packed(ids: list[int]) -> bytes:
    return np.array(ids, "<u4").tobytes()


class WordEncoder:
    """Streaming encoder of the word tokenizer: NFC, lower case, white space dropped, word ends marked.

    ``push`` takes text in any pieces and returns the ids that no later text can
    change; ``finish`` returns the rest.  What is held between calls is bounded by
    ``window`` characters plus the lookahead, except for a run of punctuation
    marks without a letter or a blank in it, which is one pre-token and is held whole.

    Every text takes one way.  ``feed`` reads characters and lets go of what is stable: stretches closed by
    a blank, and ids of a word that is still open but is longer than the lookahead.  ``ids_of``
    then puts the ids of closed stretches in; the memo is its cache, filled in batches.
    """

    #: Fixed value: the pre-token pattern of the vocabulary.
    PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\p{White_Space}\p{L}\p{N}]+"

    def __init__(self, rules: MergeList, window: int = 1 << 16):
        self.rules, self.window = rules, window
        self.words = regex.compile(self.PATTERN).findall
        self.letters = regex.compile(r"\p{L}+")
        self.blank = regex.compile(r"(?r)\p{White_Space}")
        # U+0130 grows a mark when lower-cased, so no pre-token need end behind it.
        self.turn = regex.compile(r"(?r)(?<=\p{L})(?<!\u0130)[\x21-\x40\x5B-\x60\x7B-\x7E]")
        self.specials = regex.compile("(" + "|".join(map(regex.escape, rules.special)) + ")") if rules.special else None
        self.longest = max(map(len, rules.special), default=0)
        #: str.split() also splits at these four, which the vocabulary takes for marks.
        self.odd = regex.compile(r"[\x1c-\x1f]").search
        self.marked = regex.compile(self.PATTERN + r"|\n").findall
        self.memo = ChunkIds(self.chunk)
        self.batch = BatchMerger(rules)
        self.pending, self.open = "", None

    def chunk(self, text: str) -> list[int]:
        return [i for w in self.words(text) for i in self.word(w)]

    def word(self, word: str) -> list[int]:
        stream = OpenWord(self.rules)
        return stream.push(symbols(word)) + stream.close()

    def learn(self, new: set[str | bytes]) -> None:
        """Adds many short stretches to the memo with one pass of the pattern and one of the merges."""
        order = [c for c in new if isinstance(c, str) and len(c) <= ChunkIds.LONG]
        if len(order) < 64:
            return
        if len(self.memo) + len(order) > ChunkIds.LIMIT:
            self.memo.clear()
        found = self.marked("\n".join(order))
        words = [w for w in found if w != "\n"]
        marks = np.flatnonzero(np.fromiter((w == "\n" for w in found), bool, len(found)))
        stops = np.r_[0, marks - np.arange(len(marks)), len(words)]
        ids, begins = self.batch.ids(words) if words else (np.empty(0, np.int64), np.zeros(1, np.int64))
        raw, cut = ids.astype("<u4").tobytes(), (begins[stops] * 4).tolist()
        self.memo.update(zip(order, [raw[a:b] for a, b in zip(cut, cut[1:])]))

    def encode_many(self, texts: list[str]) -> Iterator[Iterator[np.ndarray]]:
        """Each text's ids in portions.  What many short texts let go of is looked up together; longer ones stream one by one."""
        fed: list[list[str | bytes] | None] = []
        new: set[str | bytes] = set()
        for text in texts:
            fed.append(self.feed(text) + self.end() if len(text) < self.window else None)
            new.update(fed[-1] or ())
        self.learn(new.difference(self.memo))
        for text, items in zip(texts, fed):
            yield self.encode(text) if items is None else iter((self.joined(items),))

    def joined(self, items: list[str | bytes]) -> np.ndarray:
        return np.frombuffer(b"".join(map(self.memo.__getitem__, items)), "<u4")

    def ids_of(self, items: list[str | bytes]) -> np.ndarray:
        self.learn(set(items).difference(self.memo))
        return self.joined(items)

    @staticmethod
    def normal(text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")
        return text.lower()

    def plain(self, norm: str, out: list[str | bytes]) -> None:
        """Closed stretches of normal text without special strings; blanks always part pre-tokens."""
        if self.odd(norm):
            out.append(packed(self.chunk(norm)))
        else:
            out += norm.split()

    def closed(self, text: str, out: list[str | bytes]) -> None:
        """Lets go of a stretch that ends where a pre-token ends."""
        parts = self.specials.split(text) if self.specials is not None and "<|" in text else [text]
        for part in parts:
            special = self.rules.special.get(part)
            norm = "" if special is not None else self.normal(part)
            if self.open is not None:
                head = self.letters.match(norm)
                if head:
                    out.append(packed(self.open.push(symbols(head[0]))))
                    norm = norm[head.end() :]
                out.append(packed(self.open.close()))
                self.open = None
            if special is not None:
                out.append(packed([special]))
            elif norm:
                self.plain(norm, out)

    def feed(self, text: str) -> list[str | bytes]:
        """Reads text; returns what has become stable, closed stretches and ids."""
        self.pending += text
        out: list[str | bytes] = []
        if len(self.pending) < self.window:
            return out
        held = self.pending
        if m := self.blank.search(held) or self._turn(held):
            self.pending = held[m.start() :]
            self.closed(held[: m.start()], out)
        elif (at := self._inside(held)) and self.letters.fullmatch(self.normal(held[:at])):
            self.open = self.open or OpenWord(self.rules)
            out.append(packed(self.open.push(symbols(self.normal(held[:at])))))
            self.pending = held[at:]
        return out

    def end(self) -> list[str | bytes]:
        """The end of the text: what is held is stable."""
        out: list[str | bytes] = []
        held, self.pending = self.pending, ""
        self.closed(held, out)
        return out

    def push(self, text: str) -> np.ndarray:
        return self.ids_of(self.feed(text))

    def _turn(self, held: str) -> regex.Match | None:
        """The last place behind a letter and before an ASCII mark or digit, outside special strings."""
        m = self.turn.search(held, endpos=len(held) - self.longest)
        while m and "<|" in held[max(0, m.start() - self.longest) : m.start() + 2]:
            m = self.turn.search(held, endpos=max(0, m.start() - 1))
        return m

    def _inside(self, held: str) -> int:
        """A place inside a run of letters over which nothing composes; 0 if there is none."""
        for at in range(len(held) - 1, max(1, len(held) - 64), -1):
            a, b = held[max(0, at - 4) : at], held[at]  # more than one character, as a final jamo composes with the two before it
            if not unicodedata.combining(b) and unicodedata.normalize("NFC", a + b) == unicodedata.normalize("NFC", a) + unicodedata.normalize("NFC", b):
                return at
        return 0

    def finish(self) -> np.ndarray:
        return self.ids_of(self.end())

    def encode(self, text: str) -> Iterator[np.ndarray]:
        """Ids of a whole text in bounded portions."""
        for i in range(0, len(text), self.window):
            yield self.push(text[i : i + self.window])
        yield self.finish()


class TokenDecoder:
    """Incremental byte-to-text state machine.

    ``surface`` gives what a tokenizer file without decoder gives: token strings
    with one space between.  Otherwise the tokens' bytes are joined and word ends
    become spaces.  A UTF-8 sequence cut between two tokens or two calls is held
    until it is whole; broken ones become U+FFFD.
    """

    def __init__(self, rules: MergeList, surface: bool = True):
        self.surface, self.first = surface, True
        size = max(rules.names) + 1
        self.table = [b""] * size
        for i, name in rules.names.items():
            if surface or i in rules.special.values():
                self.table[i] = name.encode()
            else:
                end = bool(rules.suffix) and name.endswith(rules.suffix)
                body = name[: len(name) - len(rules.suffix)] if end else name
                self.table[i] = bytes(TO_BYTES[c] for c in body) + (b" " if end else b"")
        self.state = codecs.getincrementaldecoder("utf-8")("replace")

    def push(self, ids: np.ndarray | list[int]) -> str:
        if not len(ids):
            return ""
        joined = (b" " if self.surface else b"").join(map(self.table.__getitem__, np.asarray(ids).tolist()))
        if self.surface and not self.first:
            joined = b" " + joined
        self.first = False
        return self.state.decode(joined)

    def finish(self) -> str:
        self.first = True
        rest = self.state.decode(b"", True)
        self.state.reset()
        return rest
