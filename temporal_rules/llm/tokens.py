"""Exact, batched tokenisation with the public ``tokenizers`` library.

Encoding text in which most words come again and again costs little when a word is encoded
once.  A text is cut where the byte-level pre-tokeniser is certain to cut as well: before a
space that a visible character follows, and before a comma, full stop or newline that stands
after a letter or digit.  Chunks are encoded by the library once per worker and remembered;
a text for which these cuts are not certain goes to the library whole.  The ids are always
those of ``Tokenizer.encode(text, add_special_tokens=False)``.
"""

from __future__ import annotations

import os

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .common import kept

_MARK = {"\x01": ",", "\x02": ".", "\x03": ""}


def encoder(path: str) -> "BatchEncoder":
    return kept(("encoder", path), lambda: BatchEncoder(path))


def by_bytes(batch: pa.RecordBatch, column: int, limit: int = 6 << 20):
    """Slices of a batch whose texts have about ``limit`` bytes, or one text, each."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    lo = 0
    while lo < batch.num_rows:
        hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + limit, side="right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


class BatchEncoder:
    """``encode`` maps an Arrow string array to all its ids and the offsets of its texts in them."""

    def __init__(self, path: str, remember: int = 200_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.type = np.uint16 if self.library.get_vocab_size(with_added_tokens=True) < 65_536 else np.uint32
        # Two generations of chunks: the young one becomes the old one when full, and what is met again moves on.
        self.known: dict[str, bytes] = {"\x03": b""}
        self.old: dict[str, bytes] = {}
        self.remember = remember
        newline = self._ids(["\n"])[0]
        self.newline = int(newline[0]) if len(newline) == 1 else None
        table = np.zeros(256, bool)
        table[[*range(32), 127, 0xC2, 0xE1, 0xE2, 0xE3]] = True
        table[10] = False
        self._unsure = table
        word = np.zeros(256, bool)
        word[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True
        self._word = word

    def _ids(self, texts: list[str]) -> list[np.ndarray]:
        return [np.asarray(e.ids, self.type) for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def encode(self, texts: pa.Array, at_once: int = 6 << 20) -> tuple[np.ndarray, np.ndarray]:
        if isinstance(texts, pa.ChunkedArray):
            texts = texts.combine_chunks()
        texts = pc.fill_null(texts.cast(pa.large_string()), "")
        ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
        parts, lengths, lo = [], [], 0
        while lo < len(texts):
            before = ends[lo - 1] if lo else 0
            hi = max(lo + 1, int(np.searchsorted(ends, before + at_once, side="right")))
            ids, n = self._some(texts.slice(lo, hi - lo))
            parts.append(ids)
            lengths.append(n)
            lo = hi
        n = np.concatenate(lengths) if lengths else np.zeros(0, np.int64)
        return (np.concatenate(parts) if parts else np.zeros(0, self.type)), np.concatenate([[0], np.cumsum(n)])

    def _certain(self, texts: pa.Array) -> np.ndarray:
        """Texts whose cuts are certain."""
        offs = np.frombuffer(texts.buffers()[1], np.int64)[texts.offset : texts.offset + len(texts) + 1]
        b = np.frombuffer(texts.buffers()[2], np.uint8)[offs[0] : offs[-1]] if texts.buffers()[2] else np.zeros(0, np.uint8)
        offs = offs - offs[0]
        if not len(b):
            return np.ones(len(texts), bool)
        space = (b == 32) | (b == 10)
        bad = self._unsure[b]
        bad[1:] |= space[1:] & space[:-1]
        bad[1:] |= (b[1:] == 124) & (b[:-1] == 60)
        after_word = np.zeros(len(b), bool)
        after_word[1:] = self._word[b[:-1]]
        after_word[2:] |= (b[:-2] == 0xC3) & (b[1:-1] >= 0x80) & (b[1:-1] != 0x97) & (b[1:-1] != 0xB7)
        full = np.flatnonzero(offs[1:] > offs[:-1])
        starts = offs[:-1][full]
        after_word[starts] = False
        bad |= ((b == 44) | (b == 46)) & ~after_word
        bad[starts] |= space[starts]
        last = offs[1:][full] - 1
        bad[last] |= space[last]
        ok = np.ones(len(texts), bool)
        ok[full] = np.add.reduceat(bad.astype(np.int64), starts) == 0
        return ok

    def _learn(self, chunks: list[str]) -> None:
        """Encode chunks not seen before, many at a time with a newline between."""
        kinds: dict[str, list[str]] = {"": [], "\n": [], "\x01": [], "\x02": [], "\x03": []}
        for c in chunks:
            kinds.get(c[:1], kinds[""]).append(c)
        # A few thousand at once: the library keeps much about every token of a call.
        for kind, some in ((kind, all_[lo : lo + 8_192]) for kind, all_ in kinds.items() for lo in range(0, len(all_), 8_192)):
            if kind == "":
                whole = [" " + c for c in some]
            elif kind == "\n":
                whole = some
            else:
                whole = [_MARK[kind] + c[1:] for c in some]
            ids = self._ids(["".join(whole) if kind == "\n" else "\n".join(whole)])[0]
            cut = np.flatnonzero(ids == self.newline)
            if self.newline is None or len(cut) != len(some) - (kind != "\n"):
                for c, one in zip(some, self._ids(whole)):
                    self.known[c] = one.tobytes()
                continue
            raw, w = ids.tobytes(), ids.itemsize
            begin = cut if kind == "\n" else np.concatenate([[0], cut + 1])
            end = np.concatenate([cut[1:] if kind == "\n" else cut, [len(ids)]])
            for c, s, e in zip(some, (begin * w).tolist(), (end * w).tolist()):
                self.known[c] = raw[s:e]

    def _some(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        ok = self._certain(texts)
        n = np.zeros(len(texts), np.int64)
        quick = texts if ok.all() else texts.filter(pa.array(ok))
        ids = np.zeros(0, self.type)
        if len(quick):
            marked = quick
            for mark, sign in (("\x01", ","), ("\x02", "."), ("\n", "\n")):
                marked = pc.replace_substring(marked, sign, " " + mark)
            marked = pc.binary_join_element_wise(pa.scalar("\x03", pa.large_string()), marked, pa.scalar("", pa.large_string()))
            lists = pc.split_pattern(marked, " ")
            coded = pc.dictionary_encode(lists.flatten())
            which = coded.indices.to_numpy(zero_copy_only=False)
            names = coded.dictionary.to_pylist()
            if len(self.known) > self.remember:
                self.old, self.known = self.known, {"\x03": b""}
            known, old = self.known, self.old
            blobs = list(map(known.get, names))
            missing = [i for i, x in enumerate(blobs) if x is None]
            if missing:
                new = []
                for i in missing:
                    name = names[i]
                    again = old.get(name)
                    if again is None:
                        new.append(name)
                    else:
                        known[name] = blobs[i] = again
                if new:
                    self._learn(new)
                    for i in missing:
                        if blobs[i] is None:
                            blobs[i] = known[names[i]]
            flat = np.frombuffer(b"".join(blobs), self.type)
            length = np.fromiter(map(len, blobs), np.int32, len(blobs)) // flat.itemsize
            first = np.cumsum(length, dtype=np.int32) - length
            size = length[which]
            ends = np.cumsum(size, dtype=np.int32)
            at = np.repeat(first[which] - (ends - size), size)
            at += np.arange(len(at), dtype=np.int32)
            ids = flat[at]
            bounds = np.frombuffer(lists.buffers()[1], np.int64 if pa.types.is_large_list(lists.type) else np.int32)[lists.offset : lists.offset + len(lists) + 1]
            bounds = bounds - bounds[0]
            total = np.concatenate([[0], ends]).astype(np.int64)
            n[ok] = total[bounds[1:]] - total[bounds[:-1]]
        if ok.all():
            return ids, n
        whole = self._ids(texts.filter(pa.array(~ok)).to_pylist())
        n[~ok] = [len(x) for x in whole]
        out = np.zeros(int(n.sum()), self.type)
        mine = np.repeat(ok, n)
        out[mine] = ids
        out[~mine] = np.concatenate(whole)
        return out, n
