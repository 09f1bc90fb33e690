"""Token counts by overlap resynchronisation.

A text of ordinary length is encoded at once. A huge one is encoded in windows that overlap; two neighbours are spliced
at a boundary that both must have, wherever they began: a place where white space follows something else. No pre-token
crosses such a place and the pattern looks only to the right, so from there on both windows agree, up to the reach of the
left window's cut. Where an overlap has no such place the window is widened, to the whole rest of the text if need be.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import documents, importable
from .textkernel import slices

QUERY = "op1_token_counts"
#: Characters of a window, and of its overlap with the next one at first.
WINDOW, OVERLAP = 1 << 16, 1 << 10
LIMIT = 512
SCHEMA = "doc_id long, n_bytes long, n_tokens long, over_limit boolean, n_windows int"
#: Something that no library takes for white space, then a character that all take for it.
_STABLE = re.compile(r"[^\s\x1c-\x1f\x85᠎​⁠﻿](?=[ \n])")


class WindowedEncoder:
    """Encodes texts of any length with a public vocabulary: ranks, pattern and special strings of its library."""

    def __init__(self, ranks_path: str, pattern: str, special: dict[str, int], window: int = WINDOW, overlap: int = OVERLAP):
        with open(ranks_path, "rb") as lines:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        self.library = tiktoken.Encoding("given", pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)
        size = max([*ranks.values(), *special.values()]) + 1
        self.bytes_of = np.zeros(size, dtype=np.int64)
        for token, rank in [*ranks.items(), *((k.encode(), v) for k, v in special.items())]:
            self.bytes_of[rank] = len(token)
        self.window, self.overlap = window, overlap
        self.special = max(map(len, special), default=0)

    def ids(self, text: str) -> list[int]:
        return self.library.encode(text, allowed_special="all")

    def offsets(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        """Ids, and the byte at which each begins."""
        ids = np.array(self.ids(text), dtype=np.int64)
        return ids, np.cumsum(self.bytes_of[ids]) - self.bytes_of[ids]

    def spliced(self, text: str) -> tuple[np.ndarray, int]:
        """The ids of the whole text, and the number of windows that it took."""
        if len(text) <= self.window:
            return np.array(self.ids(text), dtype=np.int64), 1
        out, begin, cut, windows = [], 0, 0, 0  # what comes before cut has been given out; begin <= cut
        while True:
            end, reach = min(begin + self.window, len(text)), self.overlap
            while end < len(text):
                # The seam must lie left of the last few characters, whose tokens the window's end may change.
                seams = [m.end() for m in _STABLE.finditer(text, max(end - reach, cut), end - self.special - 1)]
                seam = seams[len(seams) // 2] if seams else -1
                if seam > cut:
                    break
                reach *= 2
                end = min(end + reach, len(text))
            piece = text[begin:end]
            ids, at = self.offsets(piece)
            windows += 1
            lo = len(text[begin:cut].encode())
            last = end == len(text)
            hi = len(piece.encode()) + 1 if last else len(text[begin:seam].encode())
            a, b = np.searchsorted(at, [lo, hi])
            if (cut > begin and a < len(at) and at[a] != lo) or (not last and (b >= len(at) or at[b] != hi)):
                raise AssertionError("windows disagree at a stable boundary")
            out.append(ids[a:b])
            if last:
                return np.concatenate(out), windows
            # The next window begins a little left of the seam, and must find the same boundary by itself.
            begin, cut = max(seam - self.overlap // 2, 0), seam

    def count(self, text: str) -> tuple[int, int]:
        ids, windows = self.spliced(text)
        return len(ids), windows


_encoders: dict[tuple, WindowedEncoder] = {}


def token_counts(docs: DataFrame, ranks_path: str, pattern: str, special: dict[str, int], limit: int = LIMIT, window: int = WINDOW, overlap: int = OVERLAP) -> DataFrame:
    """n_bytes (UTF-8), n_tokens, over_limit (more tokens than limit) and n_windows of each whole text.

    A null or empty text has no bytes and no tokens. Rows come out as often as they come in, null ids stay null, and
    other columns aren't read. Memory follows the longest text, not the number of rows.
    """
    key = (ranks_path, pattern, tuple(special.items()), window, overlap)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if key not in _encoders:
            _encoders[key] = WindowedEncoder(ranks_path, pattern, special, window, overlap)
        encoder = _encoders[key]
        for part in slices(batches):
            texts = [t or "" for t in part.column(1).to_pylist()]
            counts = [encoder.count(t) for t in texts]
            n = np.array([c for c, _ in counts], dtype=np.int64)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array([len(t.encode()) for t in texts], pa.int64()), pa.array(n), pa.array(n > limit), pa.array([w for _, w in counts], pa.int32())],
                ["doc_id", "n_bytes", "n_tokens", "over_limit", "n_windows"])

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SCHEMA)


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    # The same vocabulary as byte_bpe_50k.json, as ranks; the tests hold the counts against that file's own library.
    return token_counts(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN, {"<|endoftext|>": 50256})
