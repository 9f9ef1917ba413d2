"""A tokenizer's merges compiled to a deterministic transducer whose arcs carry emitted-token counts.

Symbols are the bytes of a normalised text without its white space; the last byte of a piece (a word, a digit, a run of signs) is
a symbol of its own, byte + 256. Reading it always leads back to state 0, between pieces.

Merging is decided from the left: of all tokens that end at a place exactly one can be the last token there, the one that does not
merge, as a whole or in part, with the last token of what is before it. So a state holds, for each place from which some
token may still be going on, the node of the token trie reached from there, the last token there, and how many tokens that place
lies behind. An arc's annotation is by how many tokens the text before it grew (it may shrink: merging takes tokens back).
States and arcs are made when a text first needs them, from the merge table alone; they are kept in hashed arrays, so many
places of a stream are moved on by one numpy step.

A stream is cut into chunks at any byte. The state map of a chunk that closes a piece is constant behind its first closing
byte; one that closes none only lengthens what is open. Maps compose, closed ones absorb what is before them, so the prefix
scan of all maps is a running maximum over closed chunks; heads, the bytes before a chunk's first closing byte, are then run
from the states that the scan gives.
"""

from __future__ import annotations

import json
import re

import numpy as np

#: The normaliser, the splitting rule and the word end that this compiler knows; others are left to the library.
NORMAL = ["NFC", "Replace", "Lowercase"]
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
WORD_END = "</w>"
#: What follows an apostrophe in a piece of its own.
AFTER_APOSTROPHE = ("s", "t", "m", "d", "re", "ve", "ll")
SPACE, LETTER, NUMBER, OTHER, UNKNOWN = range(5)
WIDTH = 512
LANES, MOST_STATES, MOST_BELOW, BLOCK = 2048, 150_000, 24, 1 << 21
LATIN = re.compile("[^\x00-ɏ]")


def visible() -> dict[int, str]:
    """Byte-level vocabularies write bytes as characters: printable Latin-1 as itself, the others, in order, from U+0100 on."""
    own = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = [b for b in range(256) if b not in own]
    return {b: chr(b) if b in own else chr(256 + rest.index(b)) for b in range(256)}


def known(spec: dict) -> bool:
    """Whether a tokenizer file (parsed) is of the kind compiled here."""
    normal, split, model = spec.get("normalizer") or {}, spec.get("pre_tokenizer") or {}, spec["model"]
    rules = [x["type"] for x in normal.get("normalizers", [])]
    cuts = split.get("pretokenizers", [])
    return (
        rules == NORMAL and [x["type"] for x in cuts] == ["Split", "ByteLevel"] and cuts[0]["pattern"].get("Regex") == SPLIT and cuts[0]["invert"]
        and not cuts[1]["use_regex"] and not cuts[1]["add_prefix_space"] and model["type"] == "BPE" and model.get("end_of_word_suffix") == WORD_END
        and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "fuse_unk", "byte_fallback", "ignore_merges"))
        and all(x["special"] and not x["normalized"] and not x["lstrip"] and not x["rstrip"] and not x["single_word"] for x in spec["added_tokens"])
    )


class Merges:
    """The merge table: tokens as strings of symbols, and which two may stand side by side."""

    def __init__(self, model: dict):
        byte = {c: b for b, c in visible().items()}
        vocab = model["vocab"]

        def symbols(t: str) -> tuple[int, ...]:
            last = t.endswith(WORD_END) and t != WORD_END
            s = [byte[c] for c in (t[: -len(WORD_END)] if last else t)]
            return (*s[:-1], s[-1] + 256 * last)

        self.spell = {i: symbols(t) for t, i in vocab.items()}
        self.single = {s[0]: i for i, s in self.spell.items() if len(s) == 1}
        self.made: dict[tuple[int, int], tuple[int, int]] = {}
        self.parts: dict[int, tuple[int, int, int]] = {}
        for rank, pair in enumerate(model["merges"]):
            a, b = pair if isinstance(pair, list) else pair.split(" ")
            left, right, whole = vocab[a], vocab[b], vocab[a + b]
            self.made.setdefault((left, right), (rank, whole))
            self.parts.setdefault(whole, (rank, left, right))
        never = len(model["merges"])
        self.right = {i: self._spine(i, 2, never) for i in self.spell}
        self.left = {i: self._spine(i, 1, never) for i in self.spell}
        self.pairs: dict[tuple[int, int], bool] = {}
        reached = {*self.single.values()}
        for whole, (rank, a, b) in self.parts.items():  # in order of rank, so parts come first
            if a in reached and b in reached and not self._meet(a, b, rank):
                reached.add(whole)
        self.tokens = sorted(reached)

    def _spine(self, token: int, side: int, never: int) -> tuple[tuple[int, int], ...]:
        """What stands at one edge of a token while it is put together: (part, rank at which it goes into a larger one)."""
        out, until = [(token, never)], never
        while token in self.parts:
            until, token = self.parts[token][0], self.parts[token][side]
            out.append((token, until))
        return tuple(out)

    def _meet(self, a: int, b: int, before: int) -> bool:
        """Whether some merge across the border of a and b comes before that rank. Of equal ranks the one further left is first."""
        for x, x_until in self.right[a]:
            for y, y_until in self.left[b]:
                m = self.made.get((x, y))
                if m and m[0] < before and m[0] < x_until and m[0] <= y_until:
                    return True
        return False

    def stand(self, a: int, b: int) -> bool:
        """Whether tokens a, b stay as they are side by side."""
        out = self.pairs.get((a, b))
        if out is None:
            out = self.pairs[a, b] = not self._meet(a, b, 1 << 60)
        return out


class Transducer:
    """next(state, symbol) and emits(state, symbol), made when first asked for."""

    def __init__(self, model: dict):
        self.merges = Merges(model)
        self.kids: list[dict[int, int]] = [{}]
        self.token = [-1]
        for i in self.merges.tokens:
            at = 0
            for s in self.merges.spell[i]:
                child = self.kids[at].get(s)
                if child is None:
                    child = self.kids[at][s] = len(self.kids)
                    self.kids.append({})
                    self.token.append(-1)
                at = child
            self.token[at] = i
        self.below: list[list[int] | None] = [None] * len(self.kids)  # tokens under a node, if they are few
        for node in range(len(self.kids) - 1, -1, -1):
            held: list[int] | None = []
            for k in self.kids[node].values():
                own = [self.token[k]] if self.token[k] >= 0 else []
                held = None if held is None or self.below[k] is None or len(held) + len(own) + len(self.below[k]) > MOST_BELOW else held + own + self.below[k]
            self.below[node] = held
        self.reset()

    def reset(self) -> None:
        """Forgets all states but 0."""
        self.merges.pairs.clear()
        self.live: dict[tuple[int, int], bool] = {}
        start = (0, -1, 0)
        self.states, self.number = [start], {start: 0}
        self._room(1 << 16)

    def _room(self, size: int) -> None:
        old = getattr(self, "key", None) if len(self.states) > 1 else None
        keep = (self.key[old >= 0], self.to[old >= 0], self.out[old >= 0]) if old is not None else None
        self.size, self.used = size, 0
        self.key, self.to, self.out = np.full(size, -1, np.int64), np.zeros(size, np.int32), np.zeros(size, np.int16)
        if keep:
            for k, t, o in zip(*(x.tolist() for x in keep), strict=True):
                self._put(k, t, o)

    def _put(self, key: int, to: int, out: int) -> None:
        at = key * 0x9E3779B1 >> 12 & self.size - 1
        while self.key[at] >= 0:
            at = at + 1 & self.size - 1
        self.key[at], self.to[at], self.out[at] = key, to, out
        self.used += 1

    def _goes_on(self, node: int, last: int) -> bool:
        """Whether some token under node can follow last."""
        few = self.below[node]
        if few is None or last < 0:
            return True
        out = self.live.get((node, last))
        if out is None:
            out = self.live[node, last] = any(self.merges.stand(last, t) for t in few)
        return out

    def arc(self, state: int, symbol: int) -> tuple[int, int]:
        """(next state, tokens emitted), worked out from the merge table."""
        open_, last, count = [], -1, 0
        s = self.states[state]
        for i in range(0, len(s), 3):
            node = self.kids[s[i]].get(symbol)
            if node is None:
                continue
            t = self.token[node]
            if t >= 0 and (s[i + 1] < 0 or self.merges.stand(s[i + 1], t)):
                last, count = t, s[i + 2] + 1
            if self.kids[node]:
                open_.append((node, s[i + 1], s[i + 2]))
        if symbol >= 256:
            return 0, count
        flat = [x for node, t, k in open_ if self._goes_on(node, t) for x in (node, t, k - count)]
        key = (*flat, 0, last, 0)
        to = self.number.get(key)
        if to is None:
            to = self.number[key] = len(self.states)
            self.states.append(key)
        return to, count

    def step(self, state: np.ndarray, symbol: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Arcs of many states at once."""
        key = state * np.int64(WIDTH) + symbol
        at = key * np.int64(0x9E3779B1) >> np.int64(12) & np.int64(self.size - 1)
        found = self.key[at]
        odd = np.flatnonzero(found != key)
        while len(odd):
            empty = found[odd] < 0
            if empty.any():
                for k in np.unique(key[odd[empty]]).tolist():
                    if self.used * 2 > self.size:
                        self._room(self.size * 4)
                    self._put(k, *self.arc(k // WIDTH, k % WIDTH))
                at = key * np.int64(0x9E3779B1) >> np.int64(12) & np.int64(self.size - 1)
                odd = np.arange(len(key))
            else:
                at[odd] = at[odd] + 1 & self.size - 1
            found = self.key[at]
            odd = odd[found[odd] != key[odd]]
        return self.to[at].astype(np.int64), self.out[at]

    def walk(self, state: int, symbols: np.ndarray) -> tuple[int, np.ndarray]:
        """One place after the other: for what no lane can be cut from."""
        out = np.zeros(len(symbols), np.int16)
        seen: dict[tuple[int, int], tuple[int, int]] = {}
        for i, c in enumerate(symbols.tolist()):
            found = seen.get((state, c))
            if found is None:
                found = seen[state, c] = self.arc(state, c)
            state, out[i] = found
        return state, out

    def run(self, symbols: np.ndarray, lanes: int = LANES) -> np.ndarray:
        """Tokens emitted at each symbol of a stream that starts in state 0."""
        n = len(symbols)
        out = np.zeros(n, np.int16)
        if not n:
            return out
        if len(self.states) > MOST_STATES:
            self.reset()
        size = max(16, -(-n // lanes))
        start = np.arange(0, n, size)
        lengths = np.minimum(size, n - start)
        closing = np.flatnonzero(symbols >= 256)
        first = np.append(closing, n)[np.searchsorted(closing, start)] - start  # a chunk's head, up to its first closing byte
        closed = first < lengths
        state = np.zeros(len(start), np.int64)
        for k in range(int(lengths.max())):  # every map from state 0: right behind the head, whatever comes before
            rows = len(start) - (k >= lengths[-1])
            state[:rows], out[start[:rows] + k] = self.step(state[:rows], symbols[start[:rows] + k])
        # prefix scan: the last closed chunk up to each; entering states follow from it
        last = np.maximum.accumulate(np.where(closed, np.arange(len(start)), -1))
        enter = np.zeros(len(start), np.int64)
        direct = np.flatnonzero(closed[:-1]) + 1
        enter[direct] = state[direct - 1]
        # an open chunk starts from what its predecessors left open: chains of these are walked from their first
        for k in np.flatnonzero(~closed).tolist():
            if k == 0 or last[k] == k - 1:
                z = k
                while z < len(start) and not closed[z]:
                    z += 1
                a, b = int(start[k]), int(start[z]) if z < len(start) else n
                end, out[a:b] = self.walk(int(enter[k]), symbols[a:b])
                if z < len(start):
                    enter[z] = end
        heads = np.flatnonzero(closed & (enter > 0))
        now, k = enter[heads], 0
        while len(heads):
            now, out[start[heads] + k] = self.step(now, symbols[start[heads] + k])
            k += 1
            stay = first[heads] >= k
            heads, now = heads[stay], now[stay]
        return out


def cut_at_spaces(text: str, most: int) -> list[str]:
    """text in parts of most characters or, where no space is near, more."""
    out, at = [], 0
    while len(text) - at > most:
        z = text.rfind(" ", at, at + most)
        z = z if z > at else text.find(" ", at + most)
        if z < 0:
            break
        out.append(text[at:z])
        at = z
    return [*out, text[at:]]


class Counter:
    """Token counts of whole texts for a tokenizer file: by the transducer, or by the library for a file of another kind."""

    def __init__(self, file: str):
        if file.endswith(".model"):
            from sentencepiece import SentencePieceProcessor

            model = SentencePieceProcessor(model_file=file)
            self.fst, self.library = None, lambda x: len(model.encode(x))
            return
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(file)
        self.library = lambda x: len(self.tokenizer.encode(x, add_special_tokens=False).ids)
        with open(file, encoding="utf-8") as f:
            spec = json.load(f)
        self.fst = Transducer(spec["model"]) if known(spec) else None
        self.special = re.compile("|".join(re.escape(x["content"]) for x in sorted(spec["added_tokens"], key=lambda x: -len(x["content"]))) or "(?!)")
        self.classes = np.full(0x110000, UNKNOWN, np.uint8)

    def classed(self, points: np.ndarray) -> np.ndarray:
        """Kinds of code points, which the library's own splitter tells for each once."""
        out = self.classes[points]
        if (out == UNKNOWN).any():
            for p in np.unique(points[out == UNKNOWN]).tolist():
                cut = [a for _, (a, _) in self.tokenizer.pre_tokenizer.pre_tokenize_str(f"q{chr(p)}1")]
                self.classes[p] = {(0, 2): LETTER if self._is_letter(p) else SPACE, (0, 1, 2): NUMBER if self._is_number(p) else OTHER}[tuple(cut)]
            out = self.classes[points]
        return out

    def _is_letter(self, p: int) -> bool:
        return self.tokenizer.pre_tokenizer.pre_tokenize_str(f"q{chr(p)}1")[0][1] == (0, 2)

    def _is_number(self, p: int) -> bool:
        return len(self.tokenizer.pre_tokenizer.pre_tokenize_str(chr(p) * 2)) == 2

    def normal(self, text: str) -> str:
        """The normalised text; of Latin letters all rules agree with Python's."""
        return self.tokenizer.normalizer.normalize_str(text) if LATIN.search(text) else text.lower()

    def symbols(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of a normalised text, and the place of each among the text's bytes."""
        raw = np.frombuffer(text.encode("utf-8"), np.uint8)
        points = raw if len(raw) == len(text) else np.frombuffer(text.encode("utf-32-le"), np.uint32)
        kind = self.classed(points)
        end = np.ones(len(points), bool)
        end[:-1] = (kind[1:] != kind[:-1]) | (kind[:-1] == NUMBER)
        marks = np.flatnonzero(points == 39)
        marks = marks[(marks == 0) | (kind[marks - 1] != OTHER)]
        for a in marks.tolist():
            for tail in AFTER_APOSTROPHE:
                if text.startswith(tail, a + 1):
                    end[a : a + len(tail)] = False
                    end[a + len(tail)] = True
                    break
        if points is raw:
            place = np.flatnonzero(kind != SPACE)
            return raw[place] + 256 * end[place].astype(np.int16), place
        width = 1 + (points > 0x7F) + (points > 0x7FF) + (points > 0xFFFF)
        closes = np.zeros(len(raw), np.int16)
        closes[np.cumsum(width)[end] - 1] = 256
        place = np.flatnonzero(np.repeat(kind != SPACE, width))
        return raw[place] + closes[place], place

    def counts(self, texts: list[str], most: int = BLOCK) -> list[int]:
        """One count per text. Texts are read in blocks of about most characters; a longer one is cut at spaces, which end pieces."""
        if self.fst is None:
            return [self.library(x) if x else 0 for x in texts]
        out, held, owner, size = [0] * len(texts), [], [], 0

        def close():
            for i, n in zip(owner, self._block(held), strict=True):
                out[i] += n
            held.clear()
            owner.clear()

        for i, x in enumerate(texts):
            for part in cut_at_spaces(x, most):
                if size + len(part) > most and held:
                    close()
                    size = 0
                held.append(part)
                owner.append(i)
                size += len(part)
        if held:
            close()
        return out

    def _block(self, texts: list[str]) -> list[int]:
        extra, parts = [0] * len(texts), []
        for i, x in enumerate(texts):
            if "<" in x and self.special.search(x):  # a special string is one token; what lies between is text of its own
                cut = self.special.split(x)
                extra[i] = len(cut) - 1
                parts.append("\n".join(self.normal(c) for c in cut))
            else:
                parts.append(self.normal(x))
        symbols, place = self.symbols("\n".join(parts))
        total = np.concatenate([[0], np.cumsum(self.fst.run(symbols), dtype=np.int64)])
        size = np.array([len(x.encode("utf-8")) + 1 for x in parts])
        ends = np.searchsorted(place, np.cumsum(size))
        return (np.diff(total[ends], prepend=0) + extra).tolist()
