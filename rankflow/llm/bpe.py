"""Byte-level BPE by tree reduction.

The encodings of byte strings form a monoid: each piece of text is halved down to
single bytes, and the encodings of neighbours are joined.  Two encodings can
stand side by side if the tokens that meet are what their own bytes encode to;
if not, a window around the seam is encoded anew and grown until the tokens
at both its edges agree with those outside.  An encoding in which every two
neighbours agree is the encoding of the whole: the first merge across a seam
would otherwise also happen when the two tokens there are encoded alone.
Decoding concatenates the bytes of tokens in pairs, up the tree.

A piece is cut after the largest power of two of its bytes, so that runs of one
sign, whose tokens are such powers long, meet at seams that hold at once; equal
blocks of a long piece are encoded once.
"""

from __future__ import annotations

import base64
import heapq
from array import array
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import DataFrame

from rankflow.llm.common import require, with_fields

#: Entries of each memory that a worker keeps; a full one is emptied.
MEMORY = 400_000
#: Bytes of the longest blocks that are remembered within a piece, and blocks that are; parts over which merging needs a heap.
BLOCK, BLOCKS, SHORT = 4096, 4096, 48


def load_ranks(path: str) -> dict[bytes, int]:
    """Ranks from a file of lines ``base64 rank``."""
    return {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(path).read_bytes().splitlines())}


class TreeBpe:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.pieces: dict[str, tuple[int, ...]] = {}
        self.parts: dict[bytes, tuple[bytes, ...]] = {}
        self.seams: dict[tuple[bytes, bytes], bool] = {}

    def merged(self, data: bytes) -> list[bytes]:
        """The tokens of a byte string: lowest rank first, leftmost among equals."""
        if len(data) > SHORT:
            return self._merged_by_heap(data)
        parts, ranks = [data[i : i + 1] for i in range(len(data))], self.ranks
        while len(parts) > 1:
            best, at = None, 0
            for i in range(len(parts) - 1):
                rank = ranks.get(parts[i] + parts[i + 1])
                if rank is not None and (best is None or rank < best):
                    best, at = rank, i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def _merged_by_heap(self, data: bytes) -> list[bytes]:
        """As :meth:`merged`: parts are spans linked to their neighbours, and candidate merges wait in a heap."""
        ranks, n = self.ranks.get, len(data)
        end, before = list(range(1, n + 1)), list(range(-1, n))
        queue = [(r, i, i + 2) for i in range(n - 1) if (r := ranks(data[i : i + 2])) is not None]
        heapq.heapify(queue)
        while queue:
            _, i, stop = heapq.heappop(queue)
            middle = end[i]
            # out of date if the left part is gone or either part has grown
            if middle in (0, n) or end[middle] != stop or middle == stop:
                continue
            end[i], end[middle] = stop, 0
            if stop < n:
                before[stop] = i
                if (r := ranks(data[i : end[stop]])) is not None:
                    heapq.heappush(queue, (r, i, end[stop]))
            if i and (r := ranks(data[before[i] : stop])) is not None:
                heapq.heappush(queue, (r, before[i], stop))
        out, i = [], 0
        while i < n:
            out.append(data[i : end[i]])
            i = end[i]
        return out

    def agree(self, a: bytes, b: bytes) -> bool:
        found = self.seams.get((a, b))
        if found is None:
            if len(self.seams) >= MEMORY:
                self.seams.clear()
            found = self.seams[a, b] = self.merged(a + b) == [a, b]
        return found

    def join(self, left: tuple[bytes, ...], right: tuple[bytes, ...]) -> tuple[bytes, ...]:
        """The encoding of the concatenation of two encoded byte strings."""
        if not left or not right or self.agree(left[-1], right[0]):
            return left + right
        i = j = 1
        while True:
            window = self.merged(b"".join(left[-i:]) + b"".join(right[:j]))
            left_ok = i == len(left) or self.agree(left[-i - 1], window[0])
            right_ok = j == len(right) or self.agree(window[-1], right[j])
            if left_ok and right_ok:
                return left[:-i] + tuple(window) + right[j:]
            if not left_ok:
                i = min(len(left), 2 * i)
            if not right_ok:
                j = min(len(right), 2 * j)

    def tokens(self, data: bytes, blocks: dict[bytes, tuple[bytes, ...]] | None = None) -> tuple[bytes, ...]:
        """The encoding of a byte string, by halves; ``blocks`` are those of the piece that are known."""
        if len(data) < 2:
            return (data,) if data else ()
        blocks = {} if blocks is None else blocks
        known = self.parts if len(data) <= 64 else blocks
        found = known.get(data) if len(data) <= BLOCK else None
        if found is None:
            half = 1 << (len(data) - 1).bit_length() - 1
            found = self.join(self.tokens(data[:half], blocks), self.tokens(data[half:], blocks))
            if len(data) <= BLOCK:
                if len(known) >= (MEMORY if known is self.parts else BLOCKS):
                    known.clear()
                known[data] = found
        return found

    def piece(self, text: str) -> tuple[int, ...]:
        """Ids of one match of the pattern; one that is a token as a whole is that token."""
        found = self.pieces.get(text)
        if found is None:
            data = text.encode()
            whole = self.ranks.get(data)
            found = (whole,) if whole is not None else tuple(map(self.ranks.__getitem__, self.tokens(data)))
            if len(text) <= 64:
                if len(self.pieces) >= MEMORY:
                    self.pieces.clear()
                self.pieces[text] = found
        return found

    def encode(self, text: str) -> list[int]:
        known, piece, out = self.pieces, self.piece, []
        for p in self.find(text):
            out += known.get(p) or piece(p)
        return out

    def decode(self, ids: list[int]) -> bytes:
        level = list(map(self.bytes_of.__getitem__, ids))
        while len(level) > 1:
            level = [b"".join(level[i : i + 64]) for i in range(0, len(level), 64)]
        return level[0] if level else b""


def encode_documents(docs: DataFrame, path: str, pattern: str, text_col: str = "text", decode: bool = False) -> DataFrame:
    """``docs`` with ``token_ids`` (little-endian unsigned 32-bit integers), ``n_tokens``, and on demand ``decoded`` bytes.

    Ids are those of an encoder that looks for no special tokens.  A null text
    encodes as empty.  Columns of these names in the input are replaced.  The
    vocabulary file is read by the driver and sent with the tasks.
    """
    require(docs, [text_col])
    docs = docs.drop("token_ids", "n_tokens", "decoded")
    ranks = load_ranks(path)
    schema = with_fields(docs.schema).add("token_ids", "binary").add("n_tokens", "long")
    if decode:
        schema = schema.add("decoded", "binary")

    def encode(batches: Iterator) -> Iterator:
        import pyarrow as pa

        bpe = TreeBpe(ranks, pattern)
        for whole in batches:
            for batch in (whole.slice(k, 512) for k in range(0, whole.num_rows, 512)):
                packed, count, back = [], [], []
                for text in batch.column(text_col):
                    ids = bpe.encode(text.as_py() or "")
                    packed.append(array("I", ids).tobytes())
                    count.append(len(ids))
                    if decode:
                        back.append(bpe.decode(ids))
                columns = [*batch.columns, pa.array(packed, pa.binary()), pa.array(count, pa.int64())]
                if decode:
                    columns.append(pa.array(back, pa.binary()))
                yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    return docs.mapInArrow(encode, schema)


def decode_documents(encoded: DataFrame, path: str, ids_col: str = "token_ids") -> DataFrame:
    """``encoded`` with ``decoded``: the bytes that its token ids stand for; null ids decode as empty."""
    require(encoded, [ids_col])
    encoded = encoded.drop("decoded")
    ranks, schema = load_ranks(path), with_fields(encoded.schema).add("decoded", "binary")

    def back(batches: Iterator) -> Iterator:
        import pyarrow as pa

        bpe = TreeBpe(ranks, "")
        for batch in batches:
            made = [bpe.decode(list(array("I", x.as_py() or b""))) for x in batch.column(ids_col)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(made, pa.binary())], names=schema.names)

    return encoded.mapInArrow(back, schema)
