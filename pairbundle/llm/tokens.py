"""Exact tokenisation of whole texts through their distinct pieces.

Both vocabularies used here split a text into pieces by a fixed pattern and encode every piece on its own. For texts in which all
characters are plain (printable ASCII, tab, line ends and the letters of Latin-1), Python's ``re`` states the same pattern, so the ids
of a text are those of its pieces in order, and each distinct piece goes through the tokenizers library once and is remembered. A text
with any other character is encoded as a whole by the library.

The strings of special tokens in a text are ordinary text, as the vocabularies' own description sets it (``encode_special_tokens``): a
document cannot forge an end id. ``special_strings=True`` gives the library's other reading, in which they become the special ids.
"""

from __future__ import annotations

import itertools
import os
import re

import numpy as np

from pairbundle.llm.common import worker_store

#: Letters of Latin-1 and, as bytes, the characters of plain texts.
LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
PLAIN = bytes([9, 10, 13, *range(32, 127), *(c for c in range(0xC0, 0x100) if c not in (0xD7, 0xF7))])

#: The two vocabularies' patterns for plain texts. Alternatives that cannot start alike stand in order of frequency.
SPACED = rf" ?[{LETTERS}]+| ?[0-9]+|'(?:s|t|re|ve|m|ll|d)| ?[^\s{LETTERS}0-9]+|\s+(?!\S)|\s+"
LOWERED = rf"[{LETTERS}]+|[0-9]|'(?:s|t|re|ve|m|ll|d)|[^\s{LETTERS}0-9]+"


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class _Index(dict):
    """Numbers keys in the order of their first use."""

    def __missing__(self, key):
        self[key] = n = len(self)
        return n


def is_plain(text: str) -> bool:
    try:
        return not text.encode("latin-1").translate(None, PLAIN)
    except UnicodeEncodeError:
        return False


class PieceEncoder:
    """Encodes batches of texts; keeps the ids of about ``limit`` distinct pieces between batches.

    ``path`` is a vocabulary with byte-level pieces that keep their leading space, or one of lowered pieces with word ends."""

    def __init__(self, path: str, limit: int = 600_000, special_strings: bool = False):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer, pre_tokenizers

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = not special_strings
        self.special = [t.content.lower() for t in self.tokenizer.get_added_tokens_decoder().values()] if special_strings else []
        self.limit = limit
        vocab = self.tokenizer.get_vocab()
        self.lowered = any(token.endswith("</w>") for token in vocab)
        self.find = re.compile(LOWERED if self.lowered else SPACED).findall
        self.edge = np.zeros(max(vocab.values()) + 1, bool)  # ids that end, or begin, a piece
        self.edge[[i for token, i in vocab.items() if (token.endswith("</w>") if self.lowered else token.startswith("Ġ"))]] = True
        self.line = vocab.get("Ċ")
        self.pattern = self.tokenizer.pre_tokenizer
        # Pieces with a leading space, written one after another, part at the spaces alone; the pattern is not needed again.
        self.spaces = pre_tokenizers.Sequence([pre_tokenizers.Split(" ", "merged_with_next"), pre_tokenizers.ByteLevel(add_prefix_space=False, trim_offsets=False, use_regex=False)])
        self._reset()

    def _reset(self) -> None:
        self.index = _Index()
        self.known = 0
        self.ids = np.zeros(1 << 20, np.uint32)
        self.used = 0
        self.starts = np.zeros(1 << 16, np.int64)
        self.sizes = np.zeros(1 << 16, np.int64)

    def _alone(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids, and their number for each piece, one piece at a time."""
        found = [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(pieces, add_special_tokens=False)]
        return np.concatenate([np.zeros(0, np.uint32), *found]), np.array([len(f) for f in found], np.int64)

    def _together(self, pieces: list[str], joined, sizes) -> tuple[np.ndarray, np.ndarray]:
        """The same through texts that hold many pieces; ``sizes`` finds the pieces among a text's ids again."""
        parts = [pieces[a : a + 1024] for a in range(0, len(pieces), 1024)]
        flat, counts = [np.zeros(0, np.uint32)], [np.zeros(0, np.int64)]
        for part, enc in zip(parts, self.tokenizer.encode_batch_fast([joined(p) for p in parts], add_special_tokens=False)):
            ids, n = sizes(np.array(enc.ids, np.uint32))
            if len(n) != len(part):
                ids, n = self._alone(part)
            flat.append(ids)
            counts.append(n)
        return np.concatenate(flat), np.concatenate(counts)

    def _learn(self) -> None:
        """Encodes the pieces that are new since the last call."""
        keys = list(itertools.islice(reversed(self.index), len(self.index) - self.known))
        keys.reverse()
        while len(self.starts) < len(self.index):
            self.starts, self.sizes = (np.concatenate([a, np.zeros_like(a)]) for a in (self.starts, self.sizes))
        if self.lowered:
            ends = lambda ids: (ids, np.diff(np.flatnonzero(self.edge[ids]), prepend=-1))
            kinds = [(np.ones(len(keys), bool), lambda p: self._together(p, " ".join, ends))]
        else:
            blank = np.fromiter(map(str.isspace, keys), bool, len(keys))
            spaced = np.fromiter((k[0] == " " for k in keys), bool, len(keys)) & ~blank
            begins = lambda ids: (ids, np.diff(np.flatnonzero(self.edge[ids]), append=len(ids)))

            def lines(ids):
                mark = ids == self.line
                return ids[~mark], np.diff(np.flatnonzero(mark), prepend=-1) - 1

            def run_of(p):
                self.tokenizer.pre_tokenizer = self.spaces
                try:
                    return self._together(p, "".join, begins)
                finally:
                    self.tokenizer.pre_tokenizer = self.pattern

            kinds = [(spaced, run_of), (~spaced & ~blank, lambda p: self._together(p, lambda q: "\n".join([*q, ""]), lines)), (blank, self._alone)]
        for which, encode in kinds:
            at = np.flatnonzero(which)
            flat, counts = encode([keys[k] for k in at])
            while self.used + len(flat) > len(self.ids):
                self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
            self.ids[self.used : self.used + len(flat)] = flat
            self.sizes[self.known + at] = counts
            self.starts[self.known + at] = self.used + np.cumsum(counts) - counts
            self.used += len(flat)
        self.known += len(keys)

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts, one after another, and the number of ids of each text."""
        if len(self.index) > self.limit:
            self._reset()
        get, find, rows, whole = self.index.__getitem__, self.find, [], []
        for k, text in enumerate(texts):
            if is_plain(text) and not (self.special and any(map(text.lower().__contains__, self.special))):
                rows.append(np.fromiter(map(get, find(text.lower() if self.lowered else text)), np.int32))
            else:
                rows.append(np.zeros(0, np.int32))
                whole.append(k)
        self._learn()
        flat = np.concatenate(rows) if rows else np.zeros(0, np.int32)
        lengths = self.sizes[flat]
        ends = np.cumsum(lengths)
        total = int(ends[-1]) if len(ends) else 0
        ids = self.ids[np.repeat(self.starts[flat] - (ends - lengths), lengths) + np.arange(total)] if total else np.zeros(0, np.uint32)
        upto = np.concatenate([[0], ends])[np.cumsum([len(r) for r in rows])] if rows else np.zeros(0, np.int64)
        n = np.diff(upto, prepend=0)
        if whole:
            parts = np.split(ids, upto[:-1])
            for k, enc in zip(whole, self.tokenizer.encode_batch_fast([texts[k] for k in whole], add_special_tokens=False)):
                parts[k] = np.array(enc.ids, np.uint32)
                n[k] = len(parts[k])
            ids = np.concatenate(parts)
        return ids, n


def encoder(path: str) -> PieceEncoder:
    """One encoder for each Python worker and vocabulary."""
    store = worker_store()
    if path not in store:
        store[path] = PieceEncoder(path)
    return store[path]


def text_batches(texts: list[str], characters: int = 4_000_000):
    """Index ranges of consecutive texts with about that many characters together."""
    a = size = 0
    for k, text in enumerate(texts):
        size += len(text)
        if size >= characters:
            yield a, k + 1
            a, size = k + 1, 0
    if a < len(texts):
        yield a, len(texts)
