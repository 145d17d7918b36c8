"""Piece encoding and decoding: unigram Viterbi over a double-array trie.

The vocabulary is read from a public piece model whose path is a parameter; it is
never trained or copied. Its scores are merge ranks, so a piece's log score is taken
from its rank by a Zipf rule, ``-log(rank + 2.7)`` normalised over the pieces
(``scores="zipf"``), or used as they are (``scores="model"``).

Spaces become the marker, one marker is put in front, and the text falls into
segments that start with markers; as no piece has a marker behind another
character, the best path of a text is that of its segments, and each distinct
segment is solved once per task. All segments of a batch are solved together: the
trie is walked from every position at once, and the best scores advance by end
offset. Ties prefer the longer last piece. A character no piece holds costs the
least score minus 10 and is written as its UTF-8 bytes, so decoding is exact; a
literal marker character is written as bytes for the same reason.

Defined cases: NULL and empty texts have no pieces; repeated rows encode alike.
"""

from __future__ import annotations

import hashlib
import os
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.llm._common import map_arrow, schema_with, slices

MODEL = os.environ.get("CUTFOLD_PIECE_MODEL", "/opt/tokenizers/piece_bpe_32k.model")
MARK = "▁"
_SEGMENT = re.compile(r" *[^ ]+| +")


class DoubleArray:
    """A trie in two arrays: state s moves by code c > 0 to ``base[s] + c`` if
    ``check`` of that place is s; ``value`` holds the piece that ends there."""

    def __init__(self, keys: list[tuple[int, ...]], values: list[int]):
        root: dict = {}
        for key, value in zip(keys, values):
            node = root
            for c in key:
                node = node.setdefault(c, {})
            node[0] = value
        size = 1 << 18
        base, check, value = (np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32))
        used = bytearray(size)
        used[0] = 1
        # Where a search for so many free places last ended; earlier places are too full.
        hint: dict[int, int] = {}
        todo = [(root, 0)]
        while todo:
            node, s = todo.pop()
            value[s] = node.get(0, -1)
            codes = sorted(c for c in node if c)
            if not codes:
                continue
            at = hint.get(len(codes), 1)
            while True:
                b = at - codes[0]
                if b > 0:
                    if b + codes[-1] >= len(used):
                        more = max(len(used), codes[-1])
                        used.extend(bytes(more))
                        base, check, value = (np.concatenate([x, np.full(more, fill, np.int32)]) for x, fill in ((base, 0), (check, -1), (value, -1)))
                    if not any(used[b + c] for c in codes):
                        break
                at += 1
            base[s], hint[len(codes)] = b, at
            for c in codes:
                used[b + c], check[b + c] = 1, s
                todo.append((node[c], b + c))
        # States without children keep base 0; check then never names them.
        self.base, self.check, self.value = base, check, value


class Vocabulary:
    """Pieces, log scores and the trie; a bounded object that is broadcast."""

    def __init__(self, path: str = MODEL, scores: str = "zipf"):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.surface = [b""] * n
        self.bytes = np.zeros(256, np.int32)
        ids, texts, raw = [], [], []
        for i in range(n):
            piece = sp.id_to_piece(i)
            if sp.is_byte(i):
                self.bytes[int(piece[3:5], 16)] = i
                self.surface[i] = bytes([int(piece[3:5], 16)])
            elif not (sp.is_unknown(i) or sp.is_control(i) or sp.is_unused(i)):
                if MARK in piece.lstrip(MARK):
                    raise ValueError(f"piece {i} has a marker behind another character")
                ids.append(i)
                texts.append(piece)
                raw.append(sp.get_score(i))
                self.surface[i] = piece.replace(MARK, " ").encode()
        raw = np.array(raw)
        if scores == "zipf":
            rank = np.minimum(-raw, len(ids))
            weight = 1 / (rank + 2.7)
            raw = np.log(weight / weight.sum())
        self.score = np.zeros(n)
        self.score[ids] = raw
        self.unknown = float(raw.min()) - 10
        alphabet = sorted({c for t in texts for c in t})
        self.code = np.zeros(0x110000, np.int32)
        for k, c in enumerate(alphabet):
            self.code[ord(c)] = k + 1
        self.code[ord(" ")], self.code[ord(MARK)] = self.code[ord(MARK)], 0
        own = {c: k + 1 for k, c in enumerate(alphabet)}
        self.trie = DoubleArray([tuple(own[c] for c in t) for t in texts], ids)
        self.longest = max(map(len, texts))
        self.surface_len = np.array([len(x) for x in self.surface])
        self.surface_at = np.concatenate(([0], np.cumsum(self.surface_len)[:-1]))
        self.surface_flat = np.frombuffer(b"".join(self.surface), np.uint8)
        self.is_byte = np.zeros(n, bool)
        self.is_byte[self.bytes] = True


def ragged(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Indices of the ranges ``[start, start + len)``, one after another."""
    total = int(lens.sum())
    shift = np.repeat(starts - np.concatenate(([0], np.cumsum(lens)[:-1])), lens)
    return np.arange(total) + shift


def viterbi(v: Vocabulary, segments: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Best piece ids of all segments: ``(ids, start, length)`` per segment."""
    text = np.frombuffer("".join(segments).encode("utf-32-le"), np.uint32)
    lens = np.array([len(s) for s in segments])
    first = np.concatenate(([0], np.cumsum(lens)[:-1]))
    seg = np.repeat(np.arange(len(segments)), lens)
    codes, n = v.code[text], len(text)
    room = (first + lens)[seg] - np.arange(n)
    t = v.trie
    at, state = np.arange(n), np.zeros(n, np.int32)
    found = []
    single = np.zeros(n, bool)
    for d in range(v.longest):
        inside = room[at] > d
        at, state = at[inside], state[inside]
        c = codes[at + d]
        to = t.base[state] + c
        ok = (c > 0) & (to < len(t.check))
        to = np.where(ok, to, 0)
        ok &= t.check[to] == state
        at, state = at[ok], to[ok]
        if not len(at):
            break
        hit = t.value[state] >= 0
        found.append((at[hit], np.full(int(hit.sum()), d + 1), t.value[state[hit]]))
        if d == 0:
            single[at[hit]] = True
    bare = np.flatnonzero(~single)
    found.append((bare, np.ones(len(bare), np.int64), np.full(len(bare), -1)))
    start, size, piece = (np.concatenate(x) for x in zip(*found))
    gain = np.where(piece >= 0, v.score[piece], v.unknown)
    # Boundary i of segment k sits at first[k] + k + i.
    left = start + seg[start]
    offset = start - first[seg[start]] + size
    order = np.lexsort((left, left + size, offset))
    left, size, piece, gain, offset = (x[order] for x in (left, size, piece, gain, offset))
    right = left + size
    best = np.full(n + len(segments), -np.inf)
    best[first + np.arange(len(segments))] = 0.0
    edge = np.zeros(n + len(segments), np.int64)
    group = np.flatnonzero(np.concatenate(([True], right[1:] != right[:-1]))) if len(right) else np.zeros(0, np.int64)
    end = np.append(group[1:], len(right))
    cut = np.flatnonzero(np.concatenate(([True], offset[group][1:] != offset[group][:-1]))) if len(group) else group
    for lo, hi in zip(cut, np.append(cut[1:], len(group))):
        a, b = group[lo], end[hi - 1]
        total = best[left[a:b]] + gain[a:b]
        heads = group[lo:hi] - a
        top = np.maximum.reduceat(total, heads)
        counts = end[lo:hi] - group[lo:hi]
        win = np.flatnonzero(total == np.repeat(top, counts))
        owner = np.repeat(np.arange(hi - lo), counts)[win]
        keep = np.concatenate(([True], owner[1:] != owner[:-1]))
        to = right[group[lo:hi]]
        best[to] = top
        edge[to] = a + win[keep]
    cur = first + np.arange(len(segments)) + lens
    stop = first + np.arange(len(segments))
    live = np.flatnonzero(cur > stop)
    steps = []
    while len(live):
        e = edge[cur[live]]
        steps.append((live, e))
        cur[live] = left[e]
        live = live[cur[live] > stop[live]]
    if not steps:
        return np.zeros(0, np.int32), np.zeros(len(segments), np.int64), np.zeros(len(segments), np.int64)
    who = np.concatenate([s[0] for s in steps])
    path = np.concatenate([s[1] for s in steps])
    depth = np.repeat(np.arange(len(steps)), [len(s[0]) for s in steps])
    order = np.lexsort((-depth, who))
    who, path = who[order], path[order]
    ids = piece[path]
    if (ids < 0).any():
        ch = text[left[path] - who]
        width = np.where(ids >= 0, 1, 1 + (ch > 0x7F) + (ch > 0x7FF) + (ch > 0xFFFF))
        at = np.concatenate(([0], np.cumsum(width)[:-1]))
        out = np.repeat(ids, width)
        for k in np.flatnonzero(ids < 0):
            out[at[k] : at[k] + width[k]] = v.bytes[np.frombuffer(chr(ch[k]).encode(), np.uint8)]
        who, ids = np.repeat(who, width), out
    length = np.bincount(who, minlength=len(segments))
    return ids.astype(np.int32), np.concatenate(([0], np.cumsum(length)[:-1])), length


class Encoder:
    """Encodes texts, remembering segments of up to ``KEEP`` characters until their ids
    and keys come to ``limit`` bytes; longer segments are solved anew where they occur."""

    KEEP = 48

    def __init__(self, v: Vocabulary, limit: int = 64_000_000):
        self.v, self.limit = v, limit
        self.clear()

    def clear(self):
        self.known: dict[str, int] = {}
        self.ids, self.start, self.length = np.zeros(1 << 16, np.int32), np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int64)
        self.used = self.held = self.bytes = 0

    def _append(self, segments: list[str]) -> int:
        """Solve segments and put their ids behind the others; arrays double as needed."""
        ids, start, length = viterbi(self.v, segments)
        while self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
        while self.held + len(segments) > len(self.start):
            self.start, self.length = (np.concatenate([x, np.zeros_like(x)]) for x in (self.start, self.length))
        at = slice(self.held, self.held + len(segments))
        self.ids[self.used : self.used + len(ids)] = ids
        self.start[at], self.length[at] = start + self.used, length
        first, self.used, self.held = self.held, self.used + len(ids), self.held + len(segments)
        return first

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """All ids, and the number of ids per text."""
        if self.bytes > self.limit:
            self.clear()
        split = [_SEGMENT.findall(" " + t) if t else [] for t in texts]
        known = self.known
        fresh = list(dict.fromkeys(s for ss in split for s in ss if s not in known))
        short, long = [s for s in fresh if len(s) <= self.KEEP], [s for s in fresh if len(s) > self.KEEP]
        if short:
            first = self._append(short)
            known.update(zip(short, range(first, self.held)))
            # Per segment a string, an entry and two numbers; per id four bytes.
            self.bytes += 150 * len(short) + 5 * sum(map(len, short))
        mark = self.used, self.held
        own = {}
        if long:
            first = self._append(long)
            own = dict(zip(long, range(first, self.held)))
        which = np.array([known[s] if s in known else own[s] for ss in split for s in ss], np.int64)
        lens = self.length[which]
        ids = self.ids[ragged(self.start[which], lens)]
        self.used, self.held = mark
        if 4 * len(self.ids) > self.limit:
            self.clear()
        per = np.add.reduceat(np.append(lens, 0), np.concatenate(([0], np.cumsum([len(s) for s in split])[:-1]))) if split else lens
        per = np.where([bool(s) for s in split], per, 0)
        return ids, per.astype(np.int64)


def decode_bytes(v: Vocabulary, ids: np.ndarray) -> bytes:
    """The UTF-8 bytes that the ids stand for."""
    out = v.surface_flat[ragged(v.surface_at[ids], v.surface_len[ids])].tobytes()
    return out[1:] if out.startswith(b" ") else out


def decode(v: Vocabulary, ids) -> str:
    return decode_bytes(v, np.asarray(ids, np.int64)).decode(errors="replace")


def _run(shared, emit_ids: bool):
    def run(batches):
        v = shared.value
        encoder = Encoder(v)
        for batch in batches:
            texts = [t or "" for t in batch.column(0).to_pylist()]
            for lo, hi in slices(texts, 1_000_000):
                ids, per = encoder.encode(texts[lo:hi])
                ends = np.cumsum(per)
                rest = [c.slice(lo, hi - lo) for c in batch.columns[1:]]
                names = batch.schema.names[1:]
                if emit_ids:
                    cols = [pa.array(per), pa.ListArray.from_arrays(pa.array(np.concatenate(([0], ends)), pa.int32()), pa.array(ids))]
                    yield pa.RecordBatch.from_arrays([*rest, *cols], [*names, "n_pieces", "ids"])
                    continue
                n_bytes, digest, back, same = [], [], [], []
                for text, a, b in zip(texts[lo:hi], ends - per, ends):
                    own = ids[a:b]
                    out = decode_bytes(v, own)
                    n_bytes.append(int(v.is_byte[own].sum()))
                    digest.append(hashlib.sha256(own.astype("<i4").tobytes()).hexdigest())
                    back.append(hashlib.sha256(out).hexdigest())
                    same.append(out == text.encode())
                cols = [pa.array(per), pa.array(n_bytes, pa.int64()), pa.array(digest, pa.string()), pa.array(back, pa.string()), pa.array(same, pa.bool_())]
                yield pa.RecordBatch.from_arrays([*rest, *cols], [*names, "n_pieces", "n_byte_pieces", "ids_sha256", "decoded_sha256", "round_trip"])

    return run


def encode_documents(docs: DataFrame, path: str = MODEL, scores: str = "zipf", emit_ids: bool = True, keep: tuple = ("doc_id",)) -> DataFrame:
    """``keep`` columns, ``n_pieces`` and ``ids``; or with ``emit_ids=False`` counts and
    digests of the ids and of the decoded text, and whether it is the text."""
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary(path, scores))
    src = docs.select(F.col("text").alias("_text"), *keep)
    more = "n_pieces long, ids array<int>" if emit_ids else "n_pieces long, n_byte_pieces long, ids_sha256 string, decoded_sha256 string, round_trip boolean"
    return src.mapInArrow(_run(shared, emit_ids), schema_with(src, 1, more))


def _decode_batch(shared):
    def fn(batch):
        v = shared.value
        texts = [None if x is None else decode(v, x) for x in batch.column(0).to_pylist()]
        return pa.RecordBatch.from_arrays([*batch.columns[1:], pa.array(texts, pa.string())], [*batch.schema.names[1:], "text"])

    return fn


def decode_documents(encoded: DataFrame, path: str = MODEL, keep: tuple = ("doc_id",)) -> DataFrame:
    """``keep`` columns and the ``text`` that ``ids`` stand for (NULL ids: NULL)."""
    shared = encoded.sparkSession.sparkContext.broadcast(Vocabulary(path))
    src = encoded.select(F.col("ids").alias("_ids"), *keep)
    return map_arrow(src, _decode_batch(shared), schema_with(src, 1, "text string"))


def op2_sentence_pieces(spark, sf_dir):
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), emit_ids=False)
