"""Whole texts to token ids with the tokenizers library.

Long corpora repeat their words, and neither vocabulary joins symbols over the cuts
used here, so each distinct chunk of a step goes through the library once and the ids
of the texts are gathered from the chunks.  Chunks are told apart by two independent
64-bit hashes; a step in which they disagree is encoded text by text instead.
"""

from __future__ import annotations

import numpy as np

from reclink.llm._common import BLANK, SpanHasher, release_memory, word_spans

#: Distinct chunks that one worker keeps before it starts anew.
CACHE_CHUNKS = 400_000
#: Chunks that one call of the library gets as one text.
JOINED = 400


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _safe_next() -> np.ndarray:
    """First bytes of characters that are surely not white space: no ASCII control or
    blank, and no lead byte under which Unicode has spaces."""
    ok = np.ones(256, bool)
    ok[:0x21] = False
    ok[[0x7F, 0xC2, 0xE1, 0xE2, 0xE3]] = False
    ok[0x80:0xC0] = False
    return ok


_SAFE = _safe_next()


def spaced_chunks(data: np.ndarray, offsets: np.ndarray):
    """Cuts for byte-level vocabularies that keep white space: before a blank that leads a
    word, on both sides of a line end that a word follows, and before a line end after an
    ASCII sign.  Of a run of white space before a word the last one stands apart."""
    n = len(data)
    cut = np.zeros(n + 1, bool)
    cut[offsets] = True
    if n > 1:
        safe = _SAFE[data]
        inside = np.ones(n + 1, bool)
        inside[offsets] = False  # what follows the last byte of a text is another text
        cut[: n - 1] |= ((data[:-1] == 0x20) | (data[:-1] == 0x0A)) & safe[1:] & inside[1:n]
        cut[1:n] |= (data[:-1] == 0x0A) & safe[1:]
        cut[1:n] |= (data[1:] == 0x0A) & (data[:-1] > 0x20) & (data[:-1] < 0x7F)
    cut[n] = True
    marks = np.flatnonzero(cut)
    starts, ends = marks[:-1], marks[1:]
    return starts, ends, np.searchsorted(starts, offsets)


def _plain() -> np.ndarray:
    """Bytes of characters that lower-casing and composition leave at their length: ASCII
    signs and U+00C0-U+00FF."""
    ok = np.zeros(256, bool)
    ok[0x21:0x7F] = True
    ok[0x80:0xC0] = True
    ok[0xC3] = True
    return ok


_PLAIN = _plain()


class ChunkEncoder:
    """encode(data, offsets) -> (ids of all rows in order, ids of each row)."""

    def __init__(self, path: str, spaced: bool, cache_chunks: int = CACHE_CHUNKS):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.spaced, self.cache_chunks = spaced, cache_chunks
        size = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.token_bytes = np.array([len((self.tokenizer.id_to_token(i) or "").removesuffix("" if spaced else "</w>")) for i in range(size)], np.int64)
        self.hash, self.check = SpanHasher(11, lower=not spaced), SpanHasher(23, lower=not spaced)
        self._reset()

    def _reset(self) -> None:
        self.levels = [(np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64))] * 2
        self.chunk_at, self.chunk_len = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.pool, self.used = np.zeros(1 << 16, np.uint32), 0

    def release(self) -> None:
        """Forget the chunks at the end of a task; a worker's memory stays bounded."""
        self._reset()
        release_memory()

    def _library(self, texts: list[str]) -> list[list[int]]:
        return [x.ids for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _apart(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        ids = self._library([x.decode("utf-8", "replace") for x in texts])
        sizes = np.fromiter(map(len, ids), np.int64, len(ids))
        return np.fromiter((x for one in ids for x in one), np.uint32, int(sizes.sum())), sizes

    def _joined(self, texts: list[bytes], lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Chunks that may stand behind each other in one text; their ids are told apart by
        the bytes that ids stand for."""
        glue = b"" if self.spaced else b" "
        ids = []
        for at in range(0, len(texts), 50 * JOINED):
            some = texts[at : at + 50 * JOINED]
            each = self._library([glue.join(some[i : i + JOINED]).decode("utf-8", "replace") for i in range(0, len(some), JOINED)])
            ids += [np.array(x, np.uint32) for x in each]
        ids = np.concatenate(ids)
        ends, stops = np.cumsum(self.token_bytes[ids]), np.cumsum(lengths)
        last = np.minimum(np.searchsorted(ends, stops), len(ends) - 1)
        if (ends[last] != stops).any() or last[-1] != len(ids) - 1:
            return self._apart(texts)
        return ids, np.diff(last, prepend=-1)

    def _keep(self, ids: np.ndarray, sizes: np.ndarray) -> np.ndarray:
        """Append to the pool; returns the slots."""
        total = len(ids)
        if self.used + total > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(max(total, len(self.pool) // 2), np.uint32)])
        self.pool[self.used : self.used + total] = ids
        slots = len(self.chunk_at) + np.arange(len(sizes))
        self.chunk_at = np.concatenate([self.chunk_at, self.used + np.cumsum(sizes) - sizes])
        self.chunk_len = np.concatenate([self.chunk_len, sizes])
        self.used += total
        return slots

    def _slots(self, data, starts, ends, keys, checks) -> np.ndarray:
        if len(self.chunk_at) > self.cache_chunks:
            self._reset()
        slots = np.full(len(keys), -1, np.int64)
        for known, known_checks, known_slots in self.levels:
            if len(known):
                at = np.minimum(np.searchsorted(known, keys), len(known) - 1)
                hit = (known[at] == keys) & (known_checks[at] == checks)
                slots[hit] = known_slots[at[hit]]
        miss = np.flatnonzero(slots < 0)
        if len(miss):
            raw = data.tobytes()
            if self.spaced:
                easy = (data[starts] == 0x20) & _SAFE[data[np.minimum(starts + 1, ends - 1)]]
            else:
                odd = np.concatenate([[0], np.cumsum(~_PLAIN[data])])
                easy = odd[ends] == odd[starts]
            for some, encode in ((miss[easy[miss]], self._joined), (miss[~easy[miss]], self._apart)):
                if len(some):
                    texts = [raw[s:e] for s, e in zip(starts[some].tolist(), ends[some].tolist())]
                    slots[some] = self._keep(*(encode(texts, ends[some] - starts[some]) if encode == self._joined else encode(texts)))
            fresh = [np.concatenate(x) for x in zip(self.levels[1], (keys[miss], checks[miss], slots[miss]))]
            if len(fresh[0]) > len(self.levels[0][0]) // 2:
                fresh = [np.concatenate(x) for x in zip(self.levels[0], fresh)]
                order = np.argsort(fresh[0], kind="stable")
                self.levels = [tuple(x[order] for x in fresh), tuple(x[:0] for x in fresh)]
            else:
                order = np.argsort(fresh[0], kind="stable")
                self.levels = [self.levels[0], tuple(x[order] for x in fresh)]
        return slots

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        rows = len(offsets) - 1
        starts, ends, first = (spaced_chunks if self.spaced else lambda d, o: word_spans(d, o, BLANK))(data, offsets)
        if len(starts) == 0:
            return np.zeros(0, np.uint32), np.zeros(rows, np.int64)
        keys, checks = self.hash.spans(data, starts, ends), self.check.spans(data, starts, ends)
        distinct, at, back = np.unique(keys, return_index=True, return_inverse=True)
        if not (checks[at][back] == checks).all():
            raw = data.tobytes()
            each = self._library([raw[a:b].decode("utf-8", "replace") for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())])
            sizes = np.fromiter(map(len, each), np.int64, rows)
            return np.fromiter((x for one in each for x in one), np.uint32, int(sizes.sum())), sizes
        slots = self._slots(data, starts[at], ends[at], distinct, checks[at])[back]
        sizes, begin = self.chunk_len[slots], self.chunk_at[slots]
        stop = np.cumsum(sizes)
        ids = self.pool[np.repeat(begin - (stop - sizes), sizes) + np.arange(int(stop[-1]))]
        stop = np.concatenate([[0], stop])
        return ids, np.diff(stop[first])
