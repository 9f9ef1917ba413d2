"""Token ids of whole texts, as the tokenizers library gives them, with the ids of repeated runs remembered.

Both public vocabularies used here treat a text run by run: no token spans a white-space boundary. A text is therefore
split into such runs (letters apart from the punctuation after them, which both vocabularies also keep apart) and a distinct
run is given to the library about once per worker; the result is the library's own. A
text in which that splitting would not be the library's (special strings, or control characters that Python and the
library class differently) goes to the library whole; so do all texts where a file's own rules are not those of these two.
"""

from __future__ import annotations

import json
import os
import re

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

import numpy as np  # noqa: E402

from predmap.llm import transducer  # noqa: E402

#: Unicode White_Space.
WHITE = "\t\n\x0b\x0c\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
ODD = "\x1c\x1d\x1e\x1f"
#: Latin letters, and what ends a run of them for both vocabularies: ASCII that is no letter, digit or apostrophe.
LATIN = "A-Za-z\xc0-\xd6\xd8-\xf6\xf8-\xff"
STOP = rf"(?=[{WHITE}!-&(-/:-@\[-`{{-~]|\Z)"
#: A run with the space before it, or white space; the library's own rule of which space belongs to the run.
BYTE_RUNS = re.compile(rf" ?[{LATIN}]++{STOP}| ?[^{WHITE}]+|[{WHITE}]+(?=[{WHITE}]|\Z)|[{WHITE}]+")
WORD_RUNS = re.compile(rf"[{LATIN}]++{STOP}|[^{WHITE}]+")
MOST_RUNS = 600_000  # remembered per worker and generation
LONG_RUN = 200


def path(name: str) -> str:
    """Where a public vocabulary file lies on this machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


VISIBLE = transducer.visible()
#: A run that both vocabularies keep in one piece; the model may then be asked without the steps before it.
WHOLE = re.compile(rf" ?[{LATIN}]+")


def kind_of(spec: dict) -> str:
    """Of a tokenizer file (parsed): "byte" keeps the space before a run, "word" drops white space, "" is neither."""
    split, model = spec.get("pre_tokenizer") or {}, spec["model"]
    plain = model["type"] == "BPE" and not any(model.get(k) for k in ("dropout", "unk_token", "continuing_subword_prefix", "end_of_word_suffix", "fuse_unk", "byte_fallback", "ignore_merges"))
    whole = all(x["special"] and not x["normalized"] and not x["lstrip"] and not x["rstrip"] and not x["single_word"] for x in spec["added_tokens"])
    if plain and whole and spec.get("normalizer") is None and split.get("type") == "ByteLevel" and split["use_regex"] and not split["add_prefix_space"]:
        return "byte"
    return "word" if transducer.known(spec) else ""


class Runs(dict):
    """run -> its ids as little-endian bytes."""

    def __init__(self, tokenizer, kind: str, dtype: str):
        super().__init__()
        self.tokenizer, self.kind, self.dtype, self.old = tokenizer, kind, dtype, {}
        self.model = tokenizer.model

    def of(self, run: str):
        if self.kind and WHOLE.fullmatch(run):
            line = run.lower() if self.kind == "word" else run
            return np.array([t.id for t in self.model.tokenize(line.encode().decode("latin-1").translate(VISIBLE))], self.dtype).tobytes()
        return np.array(self.tokenizer.encode(run, add_special_tokens=False).ids, self.dtype).tobytes()

    def __missing__(self, run: str):
        out = self.old.get(run)
        if out is None:
            out = self.of(run)
        if len(run) <= LONG_RUN:
            if len(self) >= MOST_RUNS:  # what the new generation asks for moves into it; the rest goes with the old one
                self.old = dict(self)
                self.clear()
            self[run] = out
        return out


class Encoder:
    """Ids of whole texts for one vocabulary file: 16-bit where they fit, else 32-bit."""

    def __init__(self, file: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(file)
        with open(file, encoding="utf-8") as f:
            self.kind = kind_of(json.load(f))
        self.dtype = "<u2" if max(self.tokenizer.get_vocab().values(), default=0) < 1 << 16 else "<u4"
        self.runs = Runs(self.tokenizer, self.kind, self.dtype)
        if hasattr(self.runs.model, "_resize_cache"):
            self.runs.model._resize_cache(0)  # Runs remembers more, and filling a second memory costs more than it saves
        self.special = [str(x.content) for x in self.tokenizer.get_added_tokens_decoder().values()]

    def plain(self, text: str) -> bool:
        return bool(self.kind) and not (any(c in text for c in ODD) or any(s in text for s in self.special))

    def split(self, text: str) -> list[str]:
        """The runs of a plain text. The word vocabulary is of lower case; Latin texts are lowered here, where all rules agree."""
        if self.kind == "byte":
            return BYTE_RUNS.findall(text)
        try:
            text.encode("latin-1")
        except UnicodeEncodeError:
            return WORD_RUNS.findall(text)
        return WORD_RUNS.findall(text.lower())

    def ids(self, text: str) -> np.ndarray:
        return np.frombuffer(b"".join(map(self.runs.__getitem__, self.split(text))) if self.plain(text) else self.runs.of(text), self.dtype)


_made: dict[str, Encoder] = {}


def encoder(file: str) -> Encoder:
    """One encoder per worker process and file."""
    if file not in _made:
        _made[file] = Encoder(file)
    return _made[file]
