"""Exact BPE encoding in linear time, and decoding by an offset table.

Encoding walks a word from left to right.  One Aho-Corasick pass finds the
longest vocabulary token that starts at each symbol.  A candidate is accepted
if the *pair-compatibility table* says that merging by rank would leave the
boundary between it and its left neighbour in place; otherwise the candidate is
shortened to its longest proper prefix, and if none is left, the last token is
given up and shortened instead.  Positions from which no split goes on are
remembered, so every position fails at most once.  The result equals that of
applying the merges by rank.

Decoding keeps the strings of all tokens in one byte array, with one table of
offsets; a sequence of ids becomes one gather.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from . import kernels as K
from .common import text_column, tokenizer_json, with_fields

#: Texts of these characters take the vectorised way: printable ASCII, tab, line ends, Latin-1 and Latin Extended-A, without controls, no-break space and the dotted capital I.
_FAST = np.zeros(0x180, bool)
_FAST[[9, 10, 13, *range(0x20, 0x7F), *range(0xA1, 0x180)]] = True
_FAST[0x130] = False
#: The contractions that are tokens of their own.
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
_SPACE, _LETTER, _NUMBER, _OTHER = range(4)
#: Words whose ids a worker keeps; beyond it the table starts anew.
MEMO_WORDS = 400_000
_PAIR_SLOTS = 1 << 20


def byte_symbols() -> list[str]:
    """The printable character that byte-level vocabularies use for each byte."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in set(shown) else chr(next(rest)) for b in range(256)]


class BpeModel:
    """The vocabulary with what encoding and decoding need; made from the JSON of the tokenizers library."""

    def __init__(self, content: bytes):
        import ahocorasick
        import regex
        from tokenizers import Tokenizer

        spec = json.loads(content)
        model = spec["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        vocab: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self._special_split = regex.compile("(" + "|".join(regex.escape(t) for t in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        front = Tokenizer.from_str(content.decode())
        self._normalizer, self._pretokenizer = front.normalizer, front.pre_tokenizer

        shown = byte_symbols()
        self._plain = [vocab[c] for c in shown]
        self._final = [vocab[c + self.suffix] for c in shown] if self.suffix else self._plain
        self._byte_of = {c: b for b, c in enumerate(shown)}

        self.n_ids = 1 + max(max(vocab.values()), max(self.special.values(), default=0))
        spelled = [b""] * self.n_ids
        for t, i in [*vocab.items(), *self.special.items()]:
            spelled[i] = t.encode()
        #: Decoding: all strings, each with the space that parts tokens, and where each starts.
        self.spelling = np.frombuffer(b" ".join(spelled) + b" ", np.uint8)
        self.offset = np.concatenate([[0], np.cumsum([len(s) + 1 for s in spelled])])

        merged: dict[int, int] = {}
        self._left_half = np.full(self.n_ids, -1, np.int64)
        self._right_half = np.full(self.n_ids, -1, np.int64)
        last = -1
        for left, right in (m.split(" ") if isinstance(m, str) else m for m in model["merges"]):
            whole = vocab[left + right]
            if whole <= last:
                raise ValueError("ids of merged tokens must rise with the merges' ranks")
            last = whole
            merged[vocab[left] * self.n_ids + vocab[right]] = whole
            self._left_half[whole], self._right_half[whole] = vocab[left], vocab[right]
        self._merge_key = np.array(sorted(merged), np.int64)
        self._merge_whole = np.array([merged[k] for k in self._merge_key.tolist()], np.int64)

        self._automaton = ahocorasick.Automaton()
        by_symbols = {self._symbols_of_token(t): i for t, i in vocab.items()}
        self._length = np.zeros(self.n_ids, np.int64)
        self._shorter = np.full(self.n_ids, -1, np.int64)
        for s, i in by_symbols.items():
            self._automaton.add_word(s, i)
            self._length[i] = len(s)
            self._shorter[i] = next((by_symbols[s[:k]] for k in range(len(s) - 1, 0, -1) if s[:k] in by_symbols), -1)
        self._automaton.make_automaton()
        #: The pair-compatibility table: a slot keeps the last pair that fell on it.
        self._known_pair = np.full(_PAIR_SLOTS, -1, np.int64)
        self._known_stays = np.zeros(_PAIR_SLOTS, bool)
        self._memo: dict[bytes, np.ndarray] = {}
        self._classes = self._character_classes()

    # -- words ---------------------------------------------------------------

    def _symbols_of_token(self, token: str) -> str:
        ends = bool(self.suffix) and token.endswith(self.suffix)
        core = [self._byte_of[c] for c in (token[: -len(self.suffix)] if ends else token)]
        return "".join(map(chr, core[:-1])) + chr(core[-1] + 256 * ends)

    def compatible(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Whether merging by rank keeps the boundary between each left and right token."""
        pair = left * self.n_ids + right
        slot = (K.mix64(pair.astype(np.uint64)) & np.uint64(_PAIR_SLOTS - 1)).astype(np.int64)
        new = np.flatnonzero(self._known_pair[slot] != pair)
        stays = self._known_stays[slot]
        if len(new):
            stays[new] = self._boundary_stays(left[new], right[new])
            self._known_pair[slot[new]], self._known_stays[slot[new]] = pair[new], stays[new]
        return stays

    def _boundary_stays(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Undoes the merges beside a boundary, latest first; a merge across it must never come before one that is undone."""
        out = np.ones(len(left), bool)
        open_ = np.arange(len(left))
        before = np.full(len(left), self.n_ids)
        while len(open_):
            key = left * self.n_ids + right
            at = np.minimum(np.searchsorted(self._merge_key, key), len(self._merge_key) - 1)
            crossed = (self._merge_key[at] == key) & (self._merge_whole[at] < before)
            out[open_[crossed]] = False
            inner_left, inner_right = self._right_half[left], self._left_half[right]
            go_left = (inner_left >= 0) & ((left > right) | (inner_right < 0))
            go_right = (inner_right >= 0) & ~go_left
            before = np.where(go_left, left, right + 1)
            left, right = np.where(go_left, inner_left, left), np.where(go_right, inner_right, right)
            more = ~crossed & (go_left | go_right)
            open_, left, right, before = open_[more], left[more], right[more], before[more]
        return out

    def encode_words(self, words: list[bytes]) -> list[np.ndarray]:
        """Ids of pre-tokenised words; all of them advance together, one decision at a time."""
        if not words:
            return []
        symbol = np.frombuffer(b"".join(words), np.uint8).astype(np.uint32)
        stop = np.cumsum([len(w) for w in words])
        begin = np.concatenate([[0], stop[:-1]])
        if self.suffix:
            symbol[stop - 1] += 256  # so no token reaches over a word's end
            found = self._automaton.iter(symbol.astype("<u4").tobytes().decode("utf-32-le"))
            hits = np.fromiter(chain.from_iterable(found), np.int64).reshape(-1, 2)
        else:
            hits = np.array([(e + b, i) for w, b in zip(words, begin.tolist()) for e, i in self._automaton.iter(w.decode("latin-1"))], np.int64).reshape(-1, 2)
        longest = np.full(len(symbol) + 1, -1)
        longest[hits[:, 0] - self._length[hits[:, 1]] + 1] = hits[:, 1]  # matches come by their ends: the longest last

        alive = np.ones(len(symbol) + 1, bool)
        used = np.zeros(len(symbol), bool)
        token = np.zeros(len(symbol), np.int64)
        previous = np.full(len(symbol), -1)
        end = stop.astype(np.int64)
        at, left = begin.astype(np.int64), np.full(len(words), -1)  # left: where the token before starts
        candidate = longest[at]
        while len(at):
            there = candidate >= 0
            past = np.where(there, at + self._length[candidate], at)
            fits = there & alive[past]
            check = np.flatnonzero(fits & (left >= 0))
            fits[check] = self.compatible(token[left[check]], candidate[check])
            back = np.flatnonzero(~there)
            shorter = self._shorter[candidate]

            take = np.flatnonzero(fits)
            token[at[take]], previous[at[take]] = candidate[take], left[take]
            used[at[take]] = True
            left[take] = at[take]
            at[take] = past[take]
            candidate = np.where(fits, longest[at], shorter)
            if len(back):
                if (left[back] < 0).any():
                    raise ValueError("the vocabulary lacks a byte")
                alive[at[back]] = False
                given_up = left[back]
                used[given_up] = False
                at[back], left[back] = given_up, previous[given_up]
                candidate[back] = self._shorter[token[given_up]]
            more = at < end
            if not more.all():
                at, left, candidate, end = at[more], left[more], candidate[more], end[more]
        chosen = np.flatnonzero(used)
        ids = token[chosen].astype(np.uint32)
        cut = [0, *np.searchsorted(chosen, stop).tolist()]
        return [ids[a:b] for a, b in zip(cut, cut[1:])]

    def words_ids(self, words: list[bytes]) -> list[np.ndarray]:
        """As :meth:`encode_words`, with the ids of earlier words kept."""
        memo = self._memo
        new = [w for w in words if w not in memo]
        if len(memo) + len(new) > MEMO_WORDS:
            memo.clear()
            new = words
        memo.update(zip(new, self.encode_words(new)))
        return [memo[w] for w in words]

    # -- texts ---------------------------------------------------------------

    @staticmethod
    def _character_classes() -> np.ndarray:
        import regex

        out = np.full(len(_FAST), _OTHER, np.uint8)
        for c in range(len(out)):
            if regex.match(r"\s", chr(c)):
                out[c] = _SPACE
            elif regex.match(r"\p{L}", chr(c)):
                out[c] = _LETTER
            elif regex.match(r"\p{N}", chr(c)):
                out[c] = _NUMBER
        return out

    def encode_exactly(self, text: str) -> np.ndarray:
        """Ids of any text; normalising and splitting are left to the library's own parts."""
        out: list[np.ndarray] = []
        for part in self._special_split.split(text) if self._special_split else [text]:
            if part in self.special:
                out.append(np.array([self.special[part]], np.uint32))
            elif part:
                normal = self._normalizer.normalize_str(part) if self._normalizer else part
                out += self.words_ids([bytes(self._byte_of[c] for c in piece) for piece, _ in self._pretokenizer.pre_tokenize_str(normal) if piece])
        return np.concatenate(out) if out else np.zeros(0, np.uint32)

    def _fast_rows(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Rows without special tokens whose characters are all in _FAST."""
        bad = (data >= 0xC6) | (data == 0x7F) | ((data < 0x20) & (data != 9) & (data != 10) & (data != 13))
        lead = np.flatnonzero((data >= 0xC2) & (data < 0xC6))
        if len(lead):
            point = ((data[lead] & 0x1F).astype(np.int64) << 6) | (data[lead + 1] & 0x3F)
            bad[lead] |= ~_FAST[np.minimum(point, len(_FAST) - 1)]
        if len(data) > 1:
            bad[:-1] |= (data[:-1] == ord("<")) & (data[1:] == ord("|"))  # special tokens
        total = np.concatenate([[0], np.cumsum(bad)])
        return total[offsets[1:]] == total[offsets[:-1]]

    def _pieces(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and ends of the pre-tokenised words of lower-cased fast rows."""
        n = len(data)
        kind = self._classes[data]
        fresh = np.ones(n, bool)  # starts a character
        lead = np.flatnonzero(data >= 0xC2)
        if len(lead):
            point = ((data[lead] & 0x1F).astype(np.int64) << 6) | (data[lead + 1] & 0x3F)
            kind[lead] = kind[lead + 1] = self._classes[point]
            fresh[lead + 1] = False
        changed = np.ones(n, bool)
        changed[1:] = (kind[1:] != kind[:-1]) | ((kind[1:] == _NUMBER) & fresh[1:])
        rows = offsets[:-1][np.diff(offsets) > 0]
        changed[rows] = True
        start = changed & (kind != _SPACE)

        # A lone apostrophe that starts a piece takes the letters of a contraction with it.
        mark = np.flatnonzero((data[:-1] == ord("'")) & start[:-1] & (kind[1:] == _LETTER) & changed[1:])
        if len(mark):
            is_row = np.zeros(n + 1, bool)
            is_row[rows] = True
            is_row[n] = True
            mark = mark[~is_row[mark + 1]]
            one = data[mark + 1]
            two = np.where(mark + 2 < n, data[np.minimum(mark + 2, n - 1)], 0)
            two[is_row[np.minimum(mark + 2, n)]] = 0
            for letters in (c[1:].encode() for c in CONTRACTIONS):
                hit = mark[(one == letters[0]) & ((two == letters[1]) if len(letters) == 2 else True)]
                start[hit + 1] = changed[hit + 1] = False
                after = hit + 1 + len(letters)
                after = after[after < n]
                after = after[~is_row[after] & (kind[after] == _LETTER)]
                start[after] = changed[after] = True
        starts = np.flatnonzero(start)
        edge = np.flatnonzero(changed)  # the next piece, space or row ends a piece
        ends = np.append(edge, n)[np.searchsorted(edge, starts, "right")]
        return starts, ends

    def encode_rows(self, column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        """Chunks (first row, all ids, offsets of the chunk's rows in them)."""
        for first, last, data, offsets in K.byte_chunks(column):
            fast = self._fast_rows(data, offsets)
            texts = pa.Array.from_buffers(pa.large_string(), last - first, [None, pa.py_buffer(offsets.astype(np.int64).tobytes()), pa.py_buffer(data.tobytes())])
            low, low_offsets = K.utf8_rows(pc.utf8_lower(pc.if_else(pa.array(fast), texts, "")))
            starts, ends = self._pieces(low, low_offsets)
            raw = low.tobytes()
            code, where = _distinct(low, raw, starts, ends)
            memo = self.words_ids([raw[s:e] for s, e in zip(starts[where].tolist(), ends[where].tolist())])
            sizes = np.array([len(m) for m in memo], np.int64)
            flat = np.concatenate(memo) if memo else np.zeros(0, np.uint32)
            at = np.cumsum(sizes) - sizes
            ids = flat[K.ranges(at[code], sizes[code])] if len(code) else flat
            size_before = np.concatenate([[0], np.cumsum(sizes[code])]) if len(code) else np.zeros(1, np.int64)
            bounds = size_before[np.searchsorted(starts, low_offsets)]
            if not fast.all():
                parts = [ids[bounds[k] : bounds[k + 1]] if fast[k] else self.encode_exactly(data[offsets[k] : offsets[k + 1]].tobytes().decode()) for k in range(last - first)]
                ids = np.concatenate(parts)
                bounds = np.concatenate([[0], np.cumsum([len(p) for p in parts])])
            yield first, ids.astype(np.uint32, copy=False), bounds

    def decode_bytes(self, ids: np.ndarray) -> np.ndarray:
        """UTF-8 of the tokens' strings with one space between them."""
        out = K.take_spans(self.spelling, self.offset[ids], self.offset[ids.astype(np.int64) + 1])
        return out[:-1]


def _distinct(data: np.ndarray, raw: bytes, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The number of each piece among the distinct ones, and where each of these is first found.

    Pieces are told apart by hashes; then each is held against the first of its number, so clashes can't go unseen.
    """
    code, unique = pd.factorize(K.span_hash(K.prefix_hash(data), starts, ends))
    where = np.zeros(len(unique), np.int64)
    where[code[::-1]] = np.arange(len(code))[::-1]
    size, first = ends - starts, where[code]
    same = (size == size[first]).all()
    if same:
        later = np.flatnonzero(first != np.arange(len(first)))
        at = K.ranges(starts[later], size[later])
        same = (data[at] == data[at + np.repeat(starts[first[later]] - starts[later], size[later])]).all()
    if not same:
        code, _ = pd.factorize(np.array([raw[s:e] for s, e in zip(starts.tolist(), ends.tolist())], object))
        where = np.zeros(code.max() + 1, np.int64)
        where[code[::-1]] = np.arange(len(code))[::-1]
    return code, where


_models: dict[str, BpeModel] = {}


def model_of(content: bytes) -> BpeModel:
    """The model for this content, made once in a worker."""
    key = hashlib.sha256(content).hexdigest()
    if key not in _models:
        _models[key] = BpeModel(content)
    return _models[key]


_ROUNDTRIP = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def bpe_digest(docs: DataFrame, tokenizer_path: str | None = None) -> DataFrame:
    """Encodes and decodes every text; (doc_id, n_tokens, ids_sha256, decoded_sha256).

    One pass without a shuffle.  A null text is empty: no token, digests of no
    bytes.  Rows are independent, so repeated rows and a null doc_id come out as
    often as they go in; further columns are left out; no rows give no rows.
    Texts of any length are handled; a chunk holds one long text at least.
    """
    content = docs.sparkSession.sparkContext.broadcast(tokenizer_json(tokenizer_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = model_of(content.value)
        for batch in batches:
            n, ids_sha, text_sha = [], [], []
            for _, ids, bounds in model.encode_rows(batch.column(1)):
                little = ids.astype("<u4", copy=False)
                for a, b in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                    n.append(b - a)
                    ids_sha.append(hashlib.sha256(little[a:b].data).hexdigest())
                    text_sha.append(hashlib.sha256(model.decode_bytes(ids[a:b]).data).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(docs["doc_id"].cast("long"), text_column(docs)).mapInArrow(run, _ROUNDTRIP)


def bpe_encode(docs: DataFrame, tokenizer_path: str | None = None) -> DataFrame:
    """Adds a column ``ids`` (array of int) to the rows; see :func:`bpe_digest` for the edge cases."""
    content = docs.sparkSession.sparkContext.broadcast(tokenizer_json(tokenizer_path))
    kept = [c for c in docs.columns if c != "ids"]
    at = kept.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = model_of(content.value)
        for batch in batches:
            for first, ids, bounds in model.encode_rows(batch.column(at)):
                part = batch.slice(first, len(bounds) - 1)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.ListArray.from_arrays(pa.array(bounds.astype(np.int32)), pa.array(ids.astype(np.int32)))], [*kept, "ids"])

    out = docs.select(*kept)
    return out.mapInArrow(run, with_fields(out.schema, "ids array<int>"))


def bpe_decode(rows: DataFrame, tokenizer_path: str | None = None) -> DataFrame:
    """Adds ``decoded`` (string) for the ids in ``ids``; null ids decode to an empty text."""
    content = rows.sparkSession.sparkContext.broadcast(tokenizer_json(tokenizer_path))
    kept = [c for c in rows.columns if c != "decoded"]
    at = kept.index("ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = model_of(content.value)
        for batch in batches:
            texts = [model.decode_bytes(np.array(x.as_py() or [], np.int64)).tobytes().decode() for x in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], [*kept, "decoded"])

    out = rows.select(*kept)
    return out.mapInArrow(run, with_fields(out.schema, "decoded string"))
