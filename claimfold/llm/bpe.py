"""Byte-level BPE by backtracking, exact and without a merge queue.

An Aho-Corasick automaton over the reversed tokens reads a piece of text from its
end: its state at a place names the longest token that starts there, so one pass
finds the longest token of every place, and no place is walked twice.  The
encoder then goes from the left with those tokens.  A token may follow the one
before only if the pair is compatible: merging their bytes by rank would not have
crossed their border.  Verdicts on pairs lie in a table of fixed size.  An
incompatible token gives way to its next shorter prefix token, and if none is
left, the token before is taken back and its end is barred.  Every place is
barred at most once, so the work is linear, and the first path to the end is the
one that merging gives.  Decoding joins byte ranges of one table through token
offsets.
"""

from __future__ import annotations

import json
import re as _re

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import regex
from pyspark.sql import DataFrame

from .words import chunks

#: Fixed values of the vocabulary's pre-tokenizer.
PIECES = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Longer pieces are encoded alone; slots of the table of pairs, a power of two; bytes of text encoded at once.
LONG_PIECE, PAIR_SLOTS, BATCH_BYTES = 192, 1 << 20, 4 << 20


def _byte_letters() -> dict[str, int]:
    """The printable stand-in of each byte in a byte-level vocabulary file."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


class Codec:
    """Tables of one vocabulary file, and encoding and decoding with them."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = _byte_letters()
        model = spec["model"]
        if model["type"] != "BPE" or spec.get("normalizer") or (spec["pre_tokenizer"] or {}).get("type") != "ByteLevel":
            raise ValueError("a byte-level BPE vocabulary without a normalizer is needed")
        self.prefix_space = bool(spec["pre_tokenizer"].get("add_prefix_space"))
        self.added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        n = max([*model["vocab"].values(), *self.added.values()]) + 1
        self.token = [b""] * n
        for t, i in model["vocab"].items():
            self.token[i] = t.encode() if t in self.added else bytes(letters[c] for c in t)
        for t, i in self.added.items():
            self.token[i] = t.encode()
        # Offset table for decoding.
        self.offset = np.zeros(n + 1, dtype=np.int64)
        np.cumsum([len(t) for t in self.token], out=self.offset[1:])
        self.blob = b"".join(self.token)
        # Ranks: merged id by pair, and for each id its rank and its two parts.
        self.left, self.right = np.arange(n, dtype=np.int64), np.arange(n, dtype=np.int64)
        self.rank = np.full(n, -1, dtype=np.int64)
        pairs = []
        for r, m in enumerate(model["merges"]):
            a, b = m if isinstance(m, list) else m.split(" ")
            x, y, z = model["vocab"][a], model["vocab"][b], model["vocab"][a + b]
            pairs.append((x, y, r))
            if self.rank[z] < 0:
                self.left[z], self.right[z], self.rank[z] = x, y, r
        self.pair_rank = {(x, y): r for x, y, r in pairs}
        self.n = n
        code = np.array([x * n + y for x, y, _ in pairs], dtype=np.int64)
        order = np.argsort(code)
        self.pair_code, self.pair_value = code[order], np.array([r for *_, r in pairs], dtype=np.int64)[order]
        if {t for t in self.token if len(t) == 1} != {bytes([i]) for i in range(256)}:
            raise ValueError("every byte must be a token")
        self._automaton(sorted((i for t, i in model["vocab"].items() if t not in self.added), key=lambda i: len(self.token[i])))
        self.size = np.array([len(t) for t in self.token], dtype=np.int64)
        # Table of pairs: a slot holds the pair seen last, and whether its second token may follow its first.
        self.slot_pair, self.slot_fits = np.full(PAIR_SLOTS, -1, dtype=np.int64), np.zeros(PAIR_SLOTS, dtype=bool)
        self.split = regex.compile(PIECES)
        self.special = _re.compile("(" + "|".join(_re.escape(t) for t in sorted(self.added, key=len, reverse=True)) + ")") if self.added else None
        # Decimal ids, and the bytes of all tokens, for joins by Arrow.
        self.decimal, self.raw = pa.array([str(i) for i in range(n)]), pa.array(self.token, pa.binary())

    def _automaton(self, ids: list[int]) -> None:
        """Children, failure links and longest tokens of the trie of reversed tokens; and prefix tokens.

        ids come by length, so a token's prefixes are known before it.
        """
        children: list[dict[int, int]] = [{}]
        own, known = [-1], {}
        self.shorter = np.full(self.n, -1, dtype=np.int64)
        for i in ids:
            t, node = self.token[i], 0
            for b in reversed(t):
                nxt = children[node].get(b)
                if nxt is None:
                    nxt = children[node][b] = len(children)
                    children.append({})
                    own.append(-1)
                node = nxt
            own[node] = i
            self.shorter[i] = next((known[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in known), -1)
            known[t] = i
        fail, longest, queue = [0] * len(children), list(own), list(children[0].values())
        for node in queue:  # by depth
            for b, nxt in children[node].items():
                up = fail[node]
                while up and b not in children[up]:
                    up = fail[up]
                fail[nxt] = children[up].get(b, 0)
                queue.append(nxt)
            if longest[node] < 0:
                longest[node] = longest[fail[node]]
        self.children, self.fail_list, self.longest_list = children, fail, longest
        self.fail, self.longest = np.array(fail, dtype=np.int64), np.array(longest, dtype=np.int64)
        flat = sorted((node * 256 + b, nxt) for node, row in enumerate(children) for b, nxt in row.items())
        self.edge, self.edge_to = (np.array(v, dtype=np.int64) for v in zip(*flat, strict=True))
        self.first = np.zeros(256, dtype=np.int64)
        for b, nxt in children[0].items():
            self.first[b] = nxt

    # -- compatibility of a pair -------------------------------------------------

    def fits(self, a: int, b: int) -> bool:
        """Whether b may follow a: at no moment of merging did a pair across the border come first.

        Taken apart in the reverse order of merging, the border's two neighbours
        must never have a merge of a lower rank than the merge undone last.
        """
        return bool(self.fits_many(np.array([a]), np.array([b]))[0])

    def fits_many(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """`fits` for arrays: read from the table of pairs; what it lacks is unfolded once and put there."""
        code = a * self.n + b
        slot = (code.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)).astype(np.int64) & (PAIR_SLOTS - 1)
        out = self.slot_fits[slot]
        lack = np.flatnonzero(self.slot_pair[slot] != code)
        if len(lack):
            new, at = np.unique(code[lack], return_inverse=True)
            fits = self._unfold(new // self.n, new % self.n)
            out[lack] = fits[at]
            # Two pairs of one slot: the last one stays, with its own verdict.
            slot_of = np.empty(len(new), dtype=np.int64)
            slot_of[at] = slot[lack]
            self.slot_pair[slot_of] = new
            last = self.slot_pair[slot_of] == new
            self.slot_fits[slot_of[last]] = fits[last]
        return out

    def _unfold(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """The verdicts on pairs, all of them unfolding side by side.

        Just before `limit`'s merge, a and b stood side by side; at equal ranks the left one merges first.
        """
        ok = np.ones(len(a), dtype=bool)
        at = np.arange(len(a))
        a, b = a.copy(), b.copy()
        limit, left_last = np.full(len(a), 1 << 60, dtype=np.int64), np.zeros(len(a), dtype=bool)
        while len(at):
            code = a * self.n + b
            i = np.minimum(np.searchsorted(self.pair_code, code), len(self.pair_code) - 1)
            r = np.where(self.pair_code[i] == code, self.pair_value[i], -1)
            bad = (r >= 0) & ((r < limit) | ((r == limit) & ~left_last))
            ok[at[bad]] = False
            ra, rb = self.rank[a], self.rank[b]
            go = ~bad & ((ra >= 0) | (rb >= 0))
            at, a, b, ra, rb = at[go], a[go], b[go], ra[go], rb[go]
            left_last = ra > rb
            limit = np.where(left_last, ra, rb)
            a, b = np.where(left_last, self.right[a], a), np.where(left_last, b, self.left[b])
        return ok

    # -- encoding ----------------------------------------------------------------

    def longest_tokens(self, data: bytes) -> list[int]:
        """The longest token that starts at each place of one piece, by one pass from its end."""
        out, node = [0] * len(data), 0
        children, fail, longest = self.children, self.fail_list, self.longest_list
        for at in range(len(data) - 1, -1, -1):
            b = data[at]
            while node and b not in children[node]:
                node = fail[node]
            node = children[node].get(b, 0)
            out[at] = longest[node]
        return out

    def encode_piece(self, data: bytes) -> list[int]:
        """One piece, token by token (long pieces, and the model for `encode_pieces`)."""
        out: list[int] = []
        barred = bytearray(len(data) + 1)
        longest, known = self.longest_tokens(data), {}
        at, token = 0, longest[0] if data else -1
        while at < len(data):
            last = out[-1] if out else -1
            while True:
                end = at + int(self.size[token])
                fits = last < 0 or known.get((last, token))
                if fits is None:
                    if len(known) > PAIR_SLOTS:
                        known.clear()
                    fits = known[last, token] = self.fits(last, token)
                if not barred[end] and fits:
                    out.append(token)
                    at = end
                    token = longest[at] if at < len(data) else -1
                    break
                shorter = int(self.shorter[token])
                if shorter >= 0:
                    token = shorter
                    continue
                barred[at] = 1
                token = out.pop()
                at -= int(self.size[token])
                break
        return out

    def _longest_many(self, data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The longest token of every place of pieces that lie in one array: all pieces are read from their ends side by side."""
        out = np.full(len(data), -1, dtype=np.int64)
        order = np.argsort(start - end, kind="stable")  # the longest first
        begin, place = start[order], end[order] - 1
        state = np.zeros(len(order), dtype=np.int64)
        live = int((place >= begin).sum())
        while live:
            byte = data[place[:live]]
            at = np.flatnonzero(state[:live])
            after = self.first[byte]
            node = state[at]
            while len(at):
                key = node * 256 + byte[at]
                i = np.minimum(np.searchsorted(self.edge, key), len(self.edge) - 1)
                hit = self.edge[i] == key
                after[at[hit]] = self.edge_to[i[hit]]
                node = self.fail[node[~hit]]
                at = at[~hit][node > 0]
                node = node[node > 0]
            state[:live] = after
            out[place[:live]] = self.longest[after]
            place[:live] -= 1
            live = int((place[:live] >= begin[:live]).sum())
        return out

    def encode_pieces(self, pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all pieces in a row, their number in each); each round moves every open piece by one decision."""
        size = np.fromiter(map(len, pieces), np.int64, len(pieces))
        data = np.frombuffer(b"".join(pieces), dtype=np.uint8).astype(np.int64)
        end = np.cumsum(size)
        start = end - size
        # stack[start + d] is the d-th token of a piece; barred marks a place by its index in data.
        stack, depth = np.zeros(len(data) + 1, dtype=np.int64), np.zeros(len(size), dtype=np.int64)
        for k in np.flatnonzero(size > LONG_PIECE).tolist():
            alone = self.encode_piece(pieces[k])
            stack[start[k] : start[k] + len(alone)] = alone
            depth[k] = len(alone)
        barred = np.zeros(len(data) + 1, dtype=bool)
        who = np.flatnonzero((size > 0) & (size <= LONG_PIECE))
        longest = self._longest_many(data, start[who], end[who])
        at = start.copy()
        token = np.full(len(size), -1, dtype=np.int64)
        token[who] = longest[at[who]]
        while len(who):
            t = token[who]
            to = at[who] + self.size[t]
            ok = ~(barred[to] & (to < end[who]))
            d = depth[who]
            last = np.where(d > 0, stack[start[who] + np.maximum(d - 1, 0)], -1)
            test = np.flatnonzero(ok & (last >= 0))
            ok[test] = self.fits_many(last[test], t[test])
            go = who[ok]
            stack[start[go] + depth[go]] = t[ok]
            depth[go] += 1
            at[go] = to[ok]
            more = go[at[go] < end[go]]
            token[more] = longest[at[more]]
            stay, ts = who[~ok], t[~ok]
            shorter = self.shorter[ts]
            token[stay] = shorter
            back = stay[shorter < 0]
            barred[at[back]] = True
            depth[back] -= 1
            token[back] = stack[start[back] + depth[back]]
            at[back] -= self.size[token[back]]
            who = np.concatenate([more, stay])
        keep = np.arange(len(data)) - np.repeat(start, size) < np.repeat(depth, size)
        return stack[:-1][keep], depth

    def encode(self, text: str) -> list[int]:
        return [i for piece in self.cut(text) for i in ([self.added[piece]] if piece in self.added else self.encode_piece(piece.encode()))]

    def cut(self, text: str) -> list[str]:
        """Pieces of a text; strings of added tokens stand alone."""
        if not self.special or not any(t in text for t in self.added):
            return self._cut_plain(text)
        return [p for k, part in enumerate(self.special.split(text)) if part for p in ([part] if k % 2 else self._cut_plain(part))]

    def _cut_plain(self, text: str) -> list[str]:
        if self.prefix_space and not text.startswith(" "):
            text = " " + text
        return self.split.findall(text)

    # -- decoding ----------------------------------------------------------------

    def decode_bytes(self, ids: list[int]) -> bytes:
        o = self.offset
        return b"".join([self.blob[o[i] : o[i + 1]] for i in ids])

    def decode(self, ids: list[int]) -> str:
        return self.decode_bytes(ids).decode("utf-8", errors="replace")

    # -- batches -----------------------------------------------------------------

    def run(self, texts: list[str | None]) -> tuple[np.ndarray, pa.Array, pa.Array]:
        """Token counts, comma-joined ids and decoded texts; null counts as empty.

        Distinct pieces are encoded once; Arrow joins their strings to those of the texts.
        """
        cuts = [self.cut(t) if t else [] for t in texts]
        flat = [p for c in cuts for p in c]
        ends = np.cumsum([0, *map(len, cuts)])
        codes, names = pd.factorize(np.array(flat, dtype=object))
        names = list(names)
        ids, n = self.encode_pieces([b"" if p in self.added else p.encode() for p in names])
        alone = [k for k, p in enumerate(names) if p in self.added]
        if alone:
            before = np.cumsum(n) - n
            ids = np.insert(ids, before[alone], [self.added[names[k]] for k in alone])
            n[alone] = 1
        lists = pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32))
        strings = pc.binary_join(pa.ListArray.from_arrays(lists, self.decimal.take(pa.array(ids))), ",")
        raw = pc.binary_join(pa.ListArray.from_arrays(lists, self.raw.take(pa.array(ids))), b"")
        docs, at = pa.array(ends.astype(np.int32)), pa.array(codes.astype(np.int64))
        sums = np.concatenate([[0], np.cumsum(n[codes])]) if len(codes) else np.zeros(1, dtype=np.int64)
        joined = pc.binary_join(pa.ListArray.from_arrays(docs, strings.take(at)), ",")
        data = pc.binary_join(pa.ListArray.from_arrays(docs, raw.take(at)), b"")
        try:
            decoded = data.cast(pa.string())
        except pa.ArrowInvalid:
            decoded = pa.array([d.decode("utf-8", errors="replace") for d in data.to_pylist()], pa.string())
        return sums[ends[1:]] - sums[ends[:-1]], joined, decoded


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    """The tables of a file, built once in each Python worker."""
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def encode_and_decode(docs: DataFrame, path: str, id: str = "doc_id", text: str = "text") -> DataFrame:
    """(id, n_tokens, ids, decoded) for every row: ids are decimal, joined by commas.

    `path` names a vocabulary file that every worker has.  A null or empty text
    has no tokens, an empty id string and an empty decoded text.
    """

    def run(batches):
        c = codec(path)
        for b in batches:
            for x, y in chunks(b.column(1), BATCH_BYTES):
                n, ids, decoded = c.run(b.column(1).slice(x, y - x).to_pylist())
                yield pa.RecordBatch.from_arrays([b.column(0).slice(x, y - x), pa.array(n, pa.int64()), ids, decoded], names=[id, "n_tokens", "ids", "decoded"])

    return docs.select(id, text).mapInArrow(run, f"`{id}` {docs.schema[id].dataType.simpleString()}, n_tokens long, ids string, decoded string")
