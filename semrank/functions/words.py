"""Words of texts as numbers, cut on Arrow's buffers: what a split of the lower-cased text at NOT_WORD gives, without a string per word."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession

NOT_WORD = r"[^\p{L}\p{N}]+"
CODES = 0x110000
#: Bytes of text that are cut at once, so that what is made of them stays small.
PIECE = 1_000_000


def word_edges(spark: SparkSession) -> np.ndarray:
    """Code points at which letters and digits begin and end, in turn, as Spark's own regular expressions know them."""
    every = "".join(map(chr, [*range(0xD800), *range(0xE000, CODES)]))
    kept = spark._jvm.java.util.regex.Pattern.compile(NOT_WORD).matcher(every).replaceAll("")
    codes = np.frombuffer(kept.encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
    gap = np.flatnonzero(np.diff(codes) > 1)
    return np.sort(np.concatenate([codes[:1], codes[gap + 1], codes[gap] + 1, codes[-1:] + 1]))


class Words:
    """Finds the words of texts that are in lower case in a vocabulary."""

    def __init__(self, edges: np.ndarray, vocabulary: list[str]):
        self.vocabulary = pa.array(vocabulary, pa.string())
        inside = np.zeros(CODES, dtype=np.int8)
        inside[edges[0::2]] = 1
        inside[edges[1::2]] = -1
        self.letter = np.cumsum(inside, dtype=np.int8) > 0
        self.ascii = np.concatenate([self.letter[:128], np.zeros(128, dtype=bool)])

    def pieces(self, texts: pa.Array) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
        """(from, to, words of each text, numbers of all these words in turn, -1 for one that is not in the vocabulary); a null has none."""
        texts = pc.cast(texts, pa.string())
        ends = np.frombuffer(texts.buffers()[1], dtype=np.int32)[texts.offset : texts.offset + len(texts) + 1]
        held = texts.buffers()[2]
        data = np.frombuffer(held if held is not None else b"", dtype=np.uint8)
        lo = 0
        while lo < len(texts):
            hi = max(lo + 1, int(np.searchsorted(ends, ends[lo] + PIECE, side="right")) - 1)
            yield lo, hi, *self._cut(data[ends[lo] : ends[hi]], ends[lo : hi + 1].astype(np.int64) - ends[lo])
            lo = hi

    def _cut(self, data: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(data):
            return np.zeros(len(ends) - 1, dtype=np.int64), np.zeros(0, dtype=np.int64)
        word, at = np.take(self.ascii, data), np.flatnonzero(data >= 0xC0)
        if len(at):
            # a letter of several bytes: its code point decides for all of them
            size = 2 + (data[at] >= 0xE0) + (data[at] >= 0xF0)
            for n, mask in ((2, 0x1F), (3, 0x0F), (4, 0x07)):
                own = at[(size == n) & (at + n <= len(data))]
                code = data[own].astype(np.int64) & mask
                for i in range(1, n):
                    code = code << 6 | data[own + i] & 0x3F
                found = self.letter[np.minimum(code, CODES - 1)]
                for i in range(n):
                    word[own + i] = found
        begins, stops = word.copy(), word.copy()
        begins[1:] &= ~word[:-1]
        stops[:-1] &= ~word[1:]
        # a word never goes on in the next text
        first, last = ends[:-1][ends[:-1] < len(data)], ends[1:][ends[1:] > 0] - 1
        begins[first], stops[last] = word[first], word[last]
        begin, stop = np.flatnonzero(begins), np.flatnonzero(stops) + 1
        letters = data[word]
        offsets = np.concatenate([[0], np.cumsum(stop - begin)]).astype(np.int32)
        words = pa.StringArray.from_buffers(len(begin), pa.py_buffer(offsets), pa.py_buffer(letters))
        number = pc.fill_null(pc.index_in(words, value_set=self.vocabulary), -1).to_numpy(zero_copy_only=False).astype(np.int64)
        return np.diff(np.searchsorted(begin, ends)), number
