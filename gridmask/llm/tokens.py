"""Exact encoding by a public tokenizer through a per-worker cache of the text between blanks.

A byte-level or word-level BPE never merges over the blank that starts a word, so the ids of a text are the
ids of its blank-separated pieces, one after the other. Pieces repeat, so each is encoded once in a worker.
Texts in which that is not certain (runs of blanks around other white space, control separators, the opening
characters of special strings) go to the library whole.
"""

from __future__ import annotations

import os
import re
from itertools import chain

import numpy as np

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

from .shared import ranges  # noqa: E402

_WORKER: dict[tuple[str, int], "CachedEncoder"] = {}


class _Codes(dict):
    """piece -> row of the pool; a new piece is put down for the next encoding."""

    def __init__(self) -> None:
        super().__init__()
        self.pending: list[str] = []
        self.base = 0

    def __missing__(self, piece: str) -> int:
        code = self[piece] = self.base + len(self.pending)
        self.pending.append(piece)
        return code


class CachedEncoder:
    """encode_many(texts) -> (ids of all texts in one array, number of ids of each)."""

    JOIN = 400

    def __init__(self, path: str, max_pieces: int = 1_000_000) -> None:
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        special = self.library.get_added_tokens_decoder()
        self.separator, self.separator_id = next((t.content, i) for i, t in special.items())
        self.openers = {t.content[:2] for t in special.values()}
        # word-level files drop white space; byte-level ones keep the blank in front of a word
        self.keeps_blank = len(self.library.encode("a  b", add_special_tokens=False).ids) > 2
        self.doubtful = re.compile("\\s \\s|\\s $|^ " if self.keeps_blank else "[\x1c-\x1f]")
        names = [self.library.id_to_token(i) or "" for i in range(self.library.get_vocab_size())]
        self.opens = np.array([n[:1] == "\u0120" for n in names])
        self.closes = np.array([n.endswith("</w>") for n in names])
        self.max_pieces = max_pieces
        self._seeded: dict[str, int] = {}
        self._clear()

    def _clear(self) -> None:
        self.codes = _Codes()
        self.pool = np.zeros(1 << 16, np.int32)
        self.used = 0
        self.starts = np.zeros(1 << 14, np.int64)
        self.lengths = np.zeros(1 << 14, np.int64)

    def _append(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        n, k = self.codes.base, len(sizes)
        while self.used + len(flat) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros_like(self.pool)])
        while n + k > len(self.starts):
            self.starts, self.lengths = (np.concatenate([x, np.zeros_like(x)]) for x in (self.starts, self.lengths))
        self.pool[self.used : self.used + len(flat)] = flat
        self.starts[n : n + k] = self.used + np.cumsum(sizes) - sizes
        self.lengths[n : n + k] = sizes
        self.used += len(flat)
        self.codes.base = n + k

    def _encode_pending(self) -> None:
        todo, self.codes.pending = self.codes.pending, []
        if not todo:
            return
        # a key with a blank in front stands for a text's first piece, which has none
        texts = [p[1:] if p[:1] == " " else " " + p for p in todo] if self.keeps_blank else todo
        plain = [i for i, t in enumerate(texts) if self._is_plain(t)]
        rest = sorted(set(range(len(texts))) - set(plain))
        ids = self._library_ids([texts[i] for i in plain], "" if self.keeps_blank else " ")
        bounds = np.flatnonzero(self.opens[ids]) if self.keeps_blank else np.flatnonzero(self.closes[ids]) + 1
        sizes = np.diff(bounds, append=len(ids)) if self.keeps_blank else np.diff(bounds, prepend=0)
        if len(sizes) != len(plain):  # letters that the tokenizer's normal form takes apart
            plain, rest, ids, sizes = [], list(range(len(texts))), ids[:0], sizes[:0]
        # each group ends with a separator, so that separators close all parts alike
        more = self._library_ids([texts[i] for i in rest], self.separator, self.separator)
        ends = np.flatnonzero(more == self.separator_id)
        assert len(ends) == len(rest)
        order = np.argsort(np.array(plain + rest, np.int64))
        all_ids, all_sizes = np.concatenate([ids, np.delete(more, ends)]), np.concatenate([sizes, np.diff(ends, prepend=-1) - 1])
        starts = np.cumsum(all_sizes) - all_sizes
        self._append(all_ids[ranges(starts[order], all_sizes[order])], all_sizes[order])

    def _is_plain(self, text: str) -> bool:
        """Encoded among its likes without a separator, its first or last id is still recognisable."""
        if self.keeps_blank:
            return text[0] == " " and not text[1:2].isspace() and not text[-1].isspace()
        return text.isalpha()

    def _library_ids(self, texts: list[str], between: str, last: str = "") -> np.ndarray:
        joined = [between.join(texts[i : i + self.JOIN]) + last for i in range(0, len(texts), self.JOIN)]
        encodings = self.library.encode_batch_fast(joined, add_special_tokens=False)
        return np.fromiter(chain.from_iterable(e.ids for e in encodings), np.int32)

    def _pieces(self, text: str) -> list[str] | None:
        """None: let the library have the whole text."""
        if any(o in text for o in self.openers) or self.doubtful.search(text):
            return None
        if not self.keeps_blank:
            return text.split()
        pieces = text.split(" ")
        pieces[0] = " " + pieces[0]
        return pieces

    def codes_of(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, dict[int, np.ndarray]]:
        """Codes of all pieces, their number by text, and the ids of texts encoded whole."""
        if self.codes.base > self.max_pieces:
            self._clear()
            if self._seeded:
                self.seed(self._seeded)
        rows: list[list[int]] = []
        whole: list[int] = []
        look_up = self.codes.__getitem__
        for i, text in enumerate(texts):
            pieces = self._pieces(text) if text else []
            if pieces is None:
                whole.append(i)
                pieces = []
            rows.append(list(map(look_up, pieces)))
        self._encode_pending()
        counts = np.fromiter(map(len, rows), np.int64, len(rows))
        codes = np.fromiter(chain.from_iterable(rows), np.int64, int(counts.sum()))
        ids = {i: np.array(self.library.encode(texts[i], add_special_tokens=False).ids, np.int32) for i in whole}
        return codes, counts, ids

    def seed(self, frequent: dict[str, int]) -> None:
        """Put known lengths of pieces (without ids) in front of the cache; only count_many may follow."""
        self._seeded = frequent
        n = len(frequent)
        while n > len(self.starts):
            self.starts, self.lengths = (np.concatenate([x, np.zeros_like(x)]) for x in (self.starts, self.lengths))
        self.codes.update(zip(frequent, range(n)))
        self.lengths[:n] = np.fromiter(frequent.values(), np.int64, n)
        self.codes.base = n

    def count_many(self, texts: list[str]) -> np.ndarray:
        codes, counts, whole = self.codes_of(texts)
        sums = np.concatenate([[0], np.cumsum(self.lengths[codes])])
        ends = np.cumsum(counts)
        out = sums[ends] - sums[ends - counts]
        for i, ids in whole.items():
            out[i] = len(ids)
        return out

    def encode_many(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        codes, counts, whole = self.codes_of(texts)
        sizes = self.lengths[codes]
        flat = self.pool[ranges(self.starts[codes], sizes)]
        sums = np.concatenate([[0], np.cumsum(sizes)])
        ends = np.cumsum(counts)
        lengths = sums[ends] - sums[ends - counts]
        if not whole:
            return flat, lengths
        cuts = np.cumsum(lengths)
        parts, at = [], 0
        for i in sorted(whole):
            parts += [flat[at : cuts[i]], whole[i]]
            at = cuts[i]
            lengths[i] = len(whole[i])
        return np.concatenate([*parts, flat[at:]]), lengths


def encoder(path: str, max_pieces: int = 1_000_000) -> CachedEncoder:
    """The worker's encoder for this file; it stays for the worker's later tasks."""
    key = (path, max_pieces)
    if key not in _WORKER:
        _WORKER[key] = CachedEncoder(path, max_pieces)
    return _WORKER[key]


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
