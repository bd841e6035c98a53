"""Byte-pair encoding with a SentencePiece model in vectorised merge rounds, and decoding.

A text becomes words (a run of word marks and what follows it, line feeds apart). No piece holds a mark
after another character, nor a line feed, so words never merge with each other; the model is
checked for that. All new words of a batch are one flat array of symbols. A round finds
the least pair rank of every word, merges all its leftmost occurrences at once, drops the symbols
that were absorbed, and leaves out words without a mergeable pair. The library merges one
pair at a time; a round gives the same result unless a merge creates a pair that ranks no later than the
one merged. Rounds look for that, and the rare words where it occurs are encoded by a queue.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import re
import struct

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MARK = "▁"
_NONE = np.int64(1 << 40)


def _fields(data: bytes):
    """(number, value) of the fields of one protocol-buffer message."""
    at = 0

    def varint():
        nonlocal at
        shift = value = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            if b < 128:
                return value
            shift += 7

    while at < len(data):
        head = varint()
        kind = head & 7
        if kind == 0:
            yield head >> 3, varint()
        elif kind == 2:
            n = varint()
            yield head >> 3, data[at : at + n]
            at += n
        else:
            n = 4 if kind == 5 else 8
            yield head >> 3, data[at : at + n]
            at += n


class PieceModel:
    """Pieces, scores and kinds of a BPE model with byte fallback, and the tables made from them."""

    UNKNOWN, CONTROL, BYTE = 2, 3, 6

    def __init__(self, model: bytes):
        self.pieces: list[str] = []
        scores, kinds = [], []
        prefix, squeeze, escape, charsmap, model_type = True, True, True, b"", 1
        for n, value in _fields(model):
            if n == 1:
                got = dict(_fields(value))
                self.pieces.append(got[1].decode("utf-8"))
                scores.append(struct.unpack("<f", got.get(2, b"\0\0\0\0"))[0])
                kinds.append(got.get(3, 1))
            elif n == 2:
                model_type = dict(_fields(value)).get(3, 1)
            elif n == 3:
                spec = dict(_fields(value))
                charsmap, prefix, squeeze, escape = (
                    spec.get(2, b""), spec.get(3, 1), spec.get(4, 1), spec.get(5, 1),
                )
        self.kinds = np.array(kinds)
        if model_type != 2 or charsmap or not prefix or squeeze or not escape or not set(kinds) <= {1, 2, 3, 6}:
            raise ValueError("this encoder takes BPE models with identity normalisation and normal pieces")
        normal = [i for i, k in enumerate(kinds) if k == 1]
        if any("\n" in self.pieces[i] or re.search(f"[^{MARK}]{MARK}", self.pieces[i]) for i in normal):
            raise ValueError("a piece crosses words")
        self.unk = kinds.index(self.UNKNOWN)
        self.bos, self.eos = self.pieces.index("<s>"), self.pieces.index("</s>")
        self.byte_id = np.zeros(256, dtype=np.int64)
        for i, k in enumerate(kinds):
            if k == self.BYTE:
                self.byte_id[int(self.pieces[i][1:-1], 16)] = i
        self.id_of = {self.pieces[i]: i for i in normal}
        by_score = np.unique(-np.array(scores, dtype=np.float64)[normal], return_inverse=True)[1]
        rank = {p: int(r) for p, r in zip((self.pieces[i] for i in normal), by_score, strict=True)}
        # every split of a piece into two pieces or single characters is a pair that may merge;
        # symbols are piece ids, characters outside the vocabulary never merge
        keys, ranks, made = [], [], []
        for p in self.id_of:
            for cut in range(1, len(p)):
                a, b = self.id_of.get(p[:cut]), self.id_of.get(p[cut:])
                if a is not None and b is not None:
                    keys.append(a << 20 | b)
                    ranks.append(rank[p])
                    made.append(self.id_of[p])
        order = np.argsort(np.array(keys))
        self.pair_key = np.array(keys, dtype=np.int64)[order]
        self.pair_rank = np.array(ranks, dtype=np.int64)[order]
        self.pair_made = np.array(made, dtype=np.int64)[order]
        self.pair_of = {int(k): (int(r), int(m)) for k, r, m in zip(self.pair_key, self.pair_rank, self.pair_made)}
        # open-addressed table of the pairs: one or two gathers instead of a binary search
        self._bits = 20
        while (1 << self._bits) < 4 * len(keys):
            self._bits += 1
        self.slots = np.full(1 << self._bits, -1, dtype=np.int64)
        at = self._slot(self.pair_key)
        todo = np.arange(len(self.pair_key))
        while len(todo):
            free = self.slots[at[todo]] < 0
            first = np.unique(at[todo[free]], return_index=True)[1]
            placed = todo[free][first]
            self.slots[at[placed]] = placed
            todo = np.setdiff1d(todo, placed, assume_unique=True)
            at[todo] = (at[todo] + 1) & ((1 << self._bits) - 1)
        # decoding: bytes of every id, as one buffer
        surface = [
            b"" if k == self.CONTROL else " ⁇ ".encode() if k == self.UNKNOWN
            else bytes([int(p[1:-1], 16)]) if k == self.BYTE else p.replace(MARK, " ").encode()
            for p, k in zip(self.pieces, kinds, strict=True)
        ]
        self.surface = np.frombuffer(b"".join(surface), dtype=np.uint8)
        self.surface_len = np.array([len(x) for x in surface], dtype=np.int64)
        self.surface_at = np.r_[0, np.cumsum(self.surface_len)[:-1]]
        self.known: dict[str, int] = {}
        self._reset()

    def _slot(self, key: np.ndarray) -> np.ndarray:
        mixed = key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return (mixed >> np.uint64(64 - self._bits)).astype(np.int64)

    def _reset(self) -> None:
        self.known.clear()
        self.stored = np.zeros(0, dtype=np.uint32)  # ids of the known words end to end
        self.stored_at = np.zeros(0, dtype=np.int64)
        self.stored_len = np.zeros(0, dtype=np.int64)

    # -- encoding ---------------------------------------------------------

    def _lookup(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Rank and resulting piece of symbol pairs; rank _NONE where they do not merge."""
        key = left << 20 | right
        key[(left < 0) | (right < 0)] = -1
        at = self._slot(key)
        rank = np.full(len(key), _NONE)
        made = np.full(len(key), -1)
        todo = np.flatnonzero(key >= 0)
        mask = (1 << self._bits) - 1
        while len(todo):
            slot = self.slots[at[todo]]
            todo, slot = todo[slot >= 0], slot[slot >= 0]
            hit = self.pair_key[slot] == key[todo]
            rank[todo[hit]] = self.pair_rank[slot[hit]]
            made[todo[hit]] = self.pair_made[slot[hit]]
            todo = todo[~hit]
            at[todo] = (at[todo] + 1) & mask
        return rank, made

    def queue_encode(self, symbols: list[int]) -> list[int]:
        """One merge at a time: best rank first, leftmost on ties."""
        sym, n = list(symbols), len(symbols)
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        heap: list[tuple[int, int, int, int, int]] = []

        def push(i: int, j: int) -> None:
            if i >= 0 and j < n and sym[i] >= 0 and sym[j] >= 0:
                got = self.pair_of.get(sym[i] << 20 | sym[j])
                if got:
                    heapq.heappush(heap, (got[0], i, j, sym[i], sym[j]))

        for i in range(n - 1):
            push(i, i + 1)
        while heap:
            _, i, j, a, b = heapq.heappop(heap)
            if sym[i] != a or sym[j] != b or nxt[i] != j:
                continue
            sym[i] = self.pair_of[a << 20 | b][1]
            sym[j] = -(1 << 40)
            nxt[i] = nxt[j]
            if nxt[j] < n:
                prv[nxt[j]] = i
            push(prv[i], i)
            push(i, nxt[i])
        return [s for s in sym if s != -(1 << 40)]

    def encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids end to end, number of ids of each word) of non-empty words, by merge rounds over all words at once."""
        if not words:
            return np.zeros(0, dtype=np.uint32), np.zeros(0, dtype=np.int64)
        points = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype=np.uint32)
        chars, inverse = np.unique(points, return_inverse=True)
        # a character outside the vocabulary is a negative symbol: -1 - code point
        own = np.array([self.id_of.get(chr(c), -1 - int(c)) for c in chars], dtype=np.int64)
        sym = own[inverse]
        size = np.fromiter(map(len, words), np.int64, len(words))
        word = np.repeat(np.arange(len(words)), size)
        done_sym, done_word, odd = [], [], []
        start_sym, start_at = sym, np.r_[0, np.cumsum(size)]
        while len(sym):
            same = word[1:] == word[:-1]
            rank = np.full(len(sym), _NONE)
            made = np.full(len(sym), -1)
            rank[:-1], made[:-1] = self._lookup(sym[:-1], sym[1:])
            rank[:-1][~same] = _NONE
            first = np.flatnonzero(np.r_[True, ~same])
            best = np.minimum.reduceat(rank, first)
            count = np.diff(np.r_[first, len(sym)])
            least = np.repeat(best, count)
            live = least < _NONE
            if not live.all():
                done_sym.append(sym[~live])
                done_word.append(word[~live])
                sym, word, rank, made, least = sym[live], word[live], rank[live], made[live], least[live]
                if not len(sym):
                    break
            hit = rank == least
            # overlapping occurrences: every second one of a run, from the left
            edge = np.flatnonzero(hit & ~np.r_[False, hit[:-1]])
            run = np.cumsum(np.r_[False, ~hit[:-1] & hit[1:]]) if len(edge) else None
            at = np.flatnonzero(hit)
            if hit[0]:
                at_run = run[at]
            else:
                at_run = run[at] - 1
            at = at[(at - edge[at_run]) % 2 == 0]
            new = sym.copy()
            new[at] = made[at]
            # a pair made by one merge that ranks no later than it: with its neighbour before or after the round
            limit = rank[at]
            after = np.minimum(at + 2, len(sym) - 1)
            before = np.maximum(at - 1, 0)
            ok_after = (at + 2 < len(sym)) & (word[after] == word[at])
            ok_before = (at > 0) & (word[before] == word[at])
            gone = np.zeros(len(sym), dtype=bool)
            gone[at + 1] = True
            last = np.maximum(np.where(gone[before], at - 2, before), 0)  # the left neighbour as the round leaves it
            bad = np.zeros(len(at), dtype=bool)
            for ok, a, b in (
                (ok_after, new[at], sym[after]),
                (ok_after, new[at], new[after]),
                (ok_before, new[last], new[at]),
            ):
                r = self._lookup(a[ok], b[ok])[0]
                bad[np.flatnonzero(ok)[r <= limit[ok]]] = True
            keep = ~gone
            if bad.any():
                strange = np.unique(word[at[bad]])
                odd.append(strange)
                keep &= ~np.isin(word, strange)
            sym, word = new[keep], word[keep]
        if done_sym:
            sym, word = np.concatenate(done_sym), np.concatenate(done_word)
        for w in np.unique(np.concatenate(odd)) if odd else ():
            got = self.queue_encode(start_sym[start_at[w] : start_at[w + 1]].tolist())
            sym, word = np.r_[sym, np.array(got, dtype=np.int64)], np.r_[word, np.full(len(got), w)]
        order = np.argsort(word, kind="stable")
        sym, word = sym[order], word[order]
        if (sym < 0).any():  # byte fallback
            lone = sym < 0
            raw = [chr(-1 - s).encode("utf-8", "surrogatepass") for s in sym[lone]]
            width = np.ones(len(sym), dtype=np.int64)
            width[lone] = [len(x) for x in raw]
            out = np.repeat(sym, width)
            out[np.repeat(lone, width)] = self.byte_id[np.frombuffer(b"".join(raw), dtype=np.uint8)]
            sym, word = out, np.repeat(word, width)
        return sym.astype(np.uint32), np.bincount(word, minlength=len(words))

    _WORD = re.compile(f"\n|{MARK}+[^{MARK}\n]*|[^{MARK}\n]+")

    def encode(self, texts: list[str | None], ends: bool = True, most_known: int = 200_000) -> list[np.ndarray]:
        """Ids (uint32) of each text; null counts as empty. At most about `most_known` words are remembered."""
        split = [self._WORD.findall(MARK + t.replace(" ", MARK)) if t else [] for t in texts]
        if len(self.known) > most_known:
            self._reset()
        known = self.known
        fresh = list(set().union(*split) - known.keys())
        parts, sizes = [self.stored], [self.stored_len]
        for at in range(0, len(fresh), 50_000):
            part = fresh[at : at + 50_000]
            ids, n = self.encode_words(part)
            known.update(zip(part, range(len(known), len(known) + len(part))))
            parts.append(ids)
            sizes.append(n)
        if fresh:
            self.stored, self.stored_len = np.concatenate(parts), np.concatenate(sizes)
            self.stored_at = np.r_[0, np.cumsum(self.stored_len)[:-1]]
        # all words of all texts in one gather, the ends of texts as words of their own
        n_words = np.fromiter(map(len, split), np.int64, len(split))
        word = np.fromiter((known[w] for ws in split for w in ws), np.int64, int(n_words.sum()))
        size = self.stored_len[word]
        upto = np.r_[0, np.cumsum(size)]
        flat = self.stored[np.repeat(self.stored_at[word] - upto[:-1], size) + np.arange(upto[-1])]
        cut = upto[np.r_[0, np.cumsum(n_words)]].tolist()
        head, tail = (np.array([x] if ends else [], dtype=np.uint32) for x in (self.bos, self.eos))
        return [np.concatenate([head, flat[i:j], tail]) for i, j in zip(cut, cut[1:])]

    # -- decoding ---------------------------------------------------------

    def decode(self, ids: np.ndarray) -> str:
        """Text of a sequence of ids: pieces end to end, the first blank taken off, broken bytes replaced one by one."""
        ids = np.asarray(ids, dtype=np.int64)
        ids = ids[self.kinds[ids] != self.CONTROL] if len(ids) else ids
        if not len(ids):
            return ""
        width = self.surface_len[ids]
        at = np.repeat(self.surface_at[ids] - np.r_[0, np.cumsum(width)[:-1]], width) + np.arange(width.sum())
        raw = self.surface[at].tobytes()
        if self.kinds[ids[0]] == 1 and raw[:1] == b" ":
            raw = raw[1:]
        return raw.decode("utf-8", "probsum-replace-byte")


codecs.register_error("probsum-replace-byte", lambda e: ("�", e.start + 1))


def encoded(
    docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", ids: bool = True,
    chars: int = 2_000_000,
) -> DataFrame:
    """One row per document: id, n_tokens, ids_sha256, decoded_sha256 and, if asked for, the ids.

    ids are those of the library with begin and end; a null text is empty. The ids are
    hashed as little-endian unsigned 32-bit integers, the text decoded from them as UTF-8. Texts are taken some
    `chars` characters at a time, whole. The model's bytes travel with the function, half a megabyte.
    """
    with open(model_path, "rb") as f:
        data = f.read()
    schema = "id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<long>" * ids)

    def run(batches):
        model = PieceModel(data)

        def rows(part):
            got = model.encode(part["text"].tolist())
            out = {
                "id": part["id"].tolist(),
                "n_tokens": [len(x) for x in got],
                "ids_sha256": [hashlib.sha256(x.astype("<u4").tobytes()).hexdigest() for x in got],
                "decoded_sha256": [
                    hashlib.sha256(model.decode(x).encode("utf-8", "surrogatepass")).hexdigest() for x in got
                ],
            }
            if ids:
                out["ids"] = [x.astype(np.int64) for x in got]
            return pd.DataFrame(out).astype({"id": "Int64", "n_tokens": "int64"})

        for pdf in batches:
            size = pdf["text"].str.len().fillna(0).cumsum() // chars
            for _, part in pdf.groupby(size, sort=False):
                yield rows(part)

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInPandas(run, schema)
