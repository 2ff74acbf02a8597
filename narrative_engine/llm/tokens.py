"""Tokenizing whole texts with a public vocabulary, fast enough for the packing and output operators.

Pre-tokens of the word vocabulary never span white space, so a text's ids are its chunks' ids in
order, whatever stands between.  Texts are taken in slices of ``SLICE_BYTES``: Arrow splits them
and numbers their chunks, each different chunk of a slice is encoded once by the library, and the
texts' ids are gathered by number.  What a worker keeps beyond a slice is one table of words,
bounded by bytes; nothing else grows with the input.
"""

from __future__ import annotations

import codecs
import functools
import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

VOCABULARY = "word_bpe_49k.json"
#: Texts that are split at once, in bytes (a longer one makes a slice of its own).
SLICE_BYTES = 4 << 20
#: What a worker's table of words may take, and its longest word; a full one takes no more.
TABLE_BYTES, LONGEST = 16 << 20, 64
#: What an entry takes besides its characters and ids.
ENTRY_BYTES = 160
#: Chunks that the library gets in one text, joined by a control character that is a pre-token of its own.
JOINED = 8_192
MARK = "\x01"
#: Marks around a word that are pre-tokens of their own; the apostrophe isn't one (contractions).
MARKS = "\"#$%&()*,-./:;?!@[]{}_+="
#: Words of Latin letters, which are one pre-token each.
LETTERS = "^[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff]+$"


def byte_letters() -> str:
    """The letter by which byte-level vocabularies write each byte: printable bytes as themselves, the others from U+0100 on; a blank stays one."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    hidden = [b for b in range(256) if b not in shown]
    signs = {b: chr(256 + n) for n, b in enumerate(hidden)} | {32: " "}
    return "".join(signs.get(b, chr(b)) for b in range(256))


BYTE_LETTERS = byte_letters()


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def gathered(flat: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """``flat[s : s + n]`` of every (s, n), one after another."""
    ends = np.cumsum(lens)
    if not len(ends):
        return flat[:0]
    return flat[np.arange(ends[-1]) + np.repeat(starts - (ends - lens), lens)]


def cut(texts: pa.Array, starts: np.ndarray, lens: np.ndarray) -> pa.Array:
    """Bytes ``start`` to ``start + len`` of each text."""
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset :][: len(texts)]
    data = np.frombuffer(texts.buffers()[2] or b"", dtype=np.uint8)
    ends = np.concatenate(([0], np.cumsum(lens))).astype(np.int64)
    return pa.LargeStringArray.from_buffers(len(texts), pa.py_buffer(ends), pa.py_buffer(gathered(data, offsets + starts, lens)))


class Encoder:
    """Texts to ids (the vocabulary has under 65,536)."""

    def __init__(self, path: str) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer, normalizers, pre_tokenizers

        self.whole = Tokenizer.from_file(path)
        if self.whole.get_vocab_size() > 1 << 16:
            raise ValueError("ids must fit 16 bits")
        self.mark = self.whole.encode(MARK, add_special_tokens=False).ids
        # lower-case Latin letters pass the normalizer unchanged, and byte_letters() does the byte mapping
        self.bare = Tokenizer(self.whole.model)
        self.bare.normalizer = normalizers.Sequence([])
        self.bare.pre_tokenizer = pre_tokenizers.Split(" ", "removed")
        #: The ids that close a word.
        self.closing = np.zeros(1 << 16, dtype=bool)
        self.closing[[i for t, i in self.whole.get_vocab().items() if t.endswith("</w>")]] = True
        self.words: dict[str, bytes] = {}
        self.held = 0

    def _joined(self, tokenizer, parts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of ``parts`` in one row, and the number of each."""
        found, sizes = [], []
        for at in range(0, len(parts), JOINED):
            own = parts[at : at + JOINED]
            text = f" {MARK} ".join(own)
            ids = np.array(tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype=np.uint16)
            cuts = np.flatnonzero(ids == self.mark[0])
            if len(cuts) == len(own) - 1:
                found.append(np.delete(ids, cuts))
                sizes.append(np.diff(np.concatenate(([-1], cuts, [len(ids)]))) - 1)
            else:  # a part holds the mark itself
                each = [np.array(e.ids, dtype=np.uint16) for e in tokenizer.encode_batch_fast(own, add_special_tokens=False)]
                found += each
                sizes.append(np.array([len(e) for e in each], dtype=np.int64))
        none = np.empty(0, dtype=np.uint16)
        return np.concatenate([none, *found]), np.concatenate([none.astype(np.int64), *sizes]).astype(np.int64)

    def _words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        known = self.words
        got = [known.get(w) for w in words]
        fresh = [w for w, g in zip(words, got) if g is None]
        flat = np.empty(0, dtype=np.uint16)
        learnt: list[bytes] = []
        for at in range(0, len(fresh), JOINED):
            own = fresh[at : at + JOINED]
            text = " ".join(own)
            text = text if text.isascii() else codecs.charmap_decode(text.encode(), "strict", BYTE_LETTERS)[0]
            ids = np.array(self.bare.encode_batch_fast([text], add_special_tokens=False)[0].ids, dtype=np.uint16)
            ends = (2 * np.flatnonzero(self.closing[ids]) + 2).tolist()
            raw = ids.tobytes()
            learnt += [raw[x:y] for x, y in zip([0, *ends], ends)]
        if self.held < TABLE_BYTES:
            for w, g in zip(fresh, learnt):
                if len(w) <= LONGEST:
                    known[w] = g
                    self.held += ENTRY_BYTES + len(w) + len(g)
                    if self.held >= TABLE_BYTES:
                        break
        more = iter(learnt)
        got = [next(more) if g is None else g for g in got]
        sizes = np.fromiter(map(len, got), dtype=np.int64, count=len(got)) // 2
        return np.frombuffer(b"".join(got), dtype=np.uint16) if got else flat, sizes

    def _different(self, parts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of different chunks in one row, and the number of each."""
        front = pc.utf8_ltrim(parts, characters=MARKS)
        core = pc.utf8_rtrim(front, characters=MARKS)
        plain = pc.match_substring_regex(core, LETTERS)
        easy = np.flatnonzero(plain.to_numpy(zero_copy_only=False))
        hard = np.flatnonzero(~plain.to_numpy(zero_copy_only=False))
        size = np.zeros(len(parts), dtype=np.int64)
        start = np.zeros(len(parts), dtype=np.int64)
        hard_ids, hard_n = self._joined(self.whole, parts.take(pa.array(hard)).to_pylist())
        pick = pa.array(easy)
        whole, front, core = parts.take(pick), front.take(pick), core.take(pick)
        own = pc.utf8_lower(core).dictionary_encode()
        word_ids, word_n = self._words(own.dictionary.to_pylist())
        size_of = lambda a: pc.binary_length(a).to_numpy()
        n_whole, n_core = size_of(whole), size_of(core)
        n_lead = n_whole - size_of(front)
        dressed = np.flatnonzero(n_whole > n_core)
        flat, number = word_ids, own.indices.to_numpy()
        word_at = np.cumsum(word_n) - word_n
        start_easy, size_easy = word_at[number], word_n[number]
        if len(dressed):
            texts, n_left = whole.take(pa.array(dressed)), n_lead[dressed]
            n_right = n_whole[dressed] - n_core[dressed] - n_left
            marks = pa.concat_arrays([cut(texts, n_left * 0, n_left), cut(texts, n_whole[dressed] - n_right, n_right)]).dictionary_encode()
            left, right = np.split(marks.indices.to_numpy(), 2)
            mark_ids, mark_n = self._joined(self.whole, marks.dictionary.to_pylist())
            mark_at = len(word_ids) + np.cumsum(mark_n) - mark_n
            both = np.concatenate((word_ids, mark_ids))
            three_at = np.stack((mark_at[left], start_easy[dressed], mark_at[right]), axis=1).reshape(-1)
            three_n = np.stack((mark_n[left], size_easy[dressed], mark_n[right]), axis=1).reshape(-1)
            new = gathered(both, three_at, three_n)
            size_new = three_n.reshape(-1, 3).sum(axis=1)
            start_easy[dressed] = len(flat) + np.cumsum(size_new) - size_new
            size_easy[dressed] = size_new
            flat = np.concatenate((flat, new))
        start[easy], size[easy] = start_easy, size_easy
        start[hard], size[hard] = len(flat) + np.cumsum(hard_n) - hard_n, hard_n
        flat = np.concatenate((flat, hard_ids))
        return gathered(flat, start, size), size

    def _slice(self, texts: pa.Array) -> Iterator[np.ndarray]:
        chunks = pc.ascii_split_whitespace(texts)
        coded = chunks.flatten()
        ends = chunks.offsets.to_numpy().astype(np.int64)
        ends -= ends[0]
        coded = pc.if_else(pc.equal(coded, ""), None, coded).dictionary_encode()  # blanks at the edges
        flat, size = self._different(coded.dictionary)
        at, number = np.cumsum(size) - size, coded.indices.fill_null(len(size)).to_numpy()
        at, size = np.append(at, 0), np.append(size, 0)
        each = size[number]
        ids = gathered(flat, at[number], each)
        until = np.concatenate(([0], np.cumsum(each)))[ends]
        for x, y in zip(until[:-1].tolist(), until[1:].tolist()):
            yield ids[x:y]

    def encode(self, texts: pa.Array) -> Iterator[np.ndarray]:
        """Ids of each text (null: none), slice by slice."""
        texts = texts.fill_null("").cast(pa.large_string())
        total = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False))
        at, before = 0, 0
        while at < len(texts):
            end = max(at + 1, int(np.searchsorted(total, before + SLICE_BYTES, side="right")))
            yield from self._slice(texts.slice(at, end - at))
            at, before = end, int(total[end - 1])
        pa.default_memory_pool().release_unused()


@functools.lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One per Python worker."""
    return Encoder(path)


def as_ids(ids: np.ndarray, end: int) -> np.ndarray:
    """Ids as little-endian unsigned 32-bit integers, ``end`` appended."""
    out = np.empty(len(ids) + 1, dtype="<u4")
    out[:-1] = ids
    out[-1] = end
    return out
