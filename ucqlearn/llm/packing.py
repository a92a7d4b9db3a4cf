"""Cost-balanced packing of token sequences.

Documents are tokenized and packed in one pass: a task fills a buffer of ``buffer_tokens`` ids, packs it and goes on,
so that nothing is shuffled and memory has a bound. Inside a buffer, pieces in descending length go to the sequence
with the lowest estimated cost (linear plus quadratic in the piece's length, as attention stays inside a piece)
among those with room for them; a piece that fits nowhere is cut to the largest room that is left.
"""

from __future__ import annotations

import heapq
import re
import sys
import zlib
from array import array
from dataclasses import dataclass
from functools import lru_cache
from itertools import chain, count

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, texts
from .rolling import grouped

if sys.byteorder != "little" or array("I").itemsize != 4:
    raise ImportError("ids are packed as native 32-bit integers, which must be little-endian")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


# runs that the normaliser only lower-cases and the splitter cuts once: no digits, apostrophes or combining marks
PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]*)")


def _byte_signs() -> dict[int, str]:
    """The sign that stands for each byte in byte-level vocabularies: itself if printable, else the next free one from 256 on."""
    free = count(256)
    return {b: chr(b) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b else chr(next(free)) for b in range(256)}


BYTE_SIGNS = _byte_signs()


class CachedTokenizer:
    """ids of whole texts as little-endian unsigned 32-bit bytes.

    The vocabulary's normaliser and splitter never look across ASCII white space, so a text's ids are those of its
    runs without it; these are remembered, up to ``most`` runs. A run of composed Latin letters with signs at its end needs
    neither normaliser nor splitter: it is two pieces, which go to the vocabulary's model as they are."""

    def __init__(self, path: str, most: int = 500_000):
        from tokenizers import Tokenizer

        self.tokenizer, self.most = Tokenizer.from_file(path), most
        self.known: dict[bytes, bytes] = {}
        self.parts: dict[str, bytes] = {}

    def encode_all(self, documents: list[bytes]) -> list[bytes]:
        split = [x.split() for x in documents]
        new = list({*chain.from_iterable(split)}.difference(self.known))
        if len(self.known) + len(new) > self.most:
            self.known, self.parts = {}, {}
            new = list({*chain.from_iterable(split)})
        self._learn(new)
        get = self.known.__getitem__
        return [b"".join(map(get, runs)) for runs in split]

    def _learn(self, new: list[bytes]) -> None:
        hard = []
        for run in new:
            found = PLAIN.fullmatch(text := run.decode())
            if found:
                self.known[run] = self._part(found[1].lower()) + self._part(found[2])
            else:
                hard.append((run, text))
        for at in range(0, len(hard), 4096):
            some = hard[at : at + 4096]
            found = self.tokenizer.encode_batch_fast([text for _, text in some], add_special_tokens=False)
            self.known.update((run, array("I", x.ids).tobytes()) for (run, _), x in zip(some, found))

    def _part(self, text: str) -> bytes:
        """ids of what the splitter takes as one piece: letters, or signs."""
        ids = self.parts.get(text)
        if ids is None:
            shown = text if text.isascii() else "".join(map(BYTE_SIGNS.__getitem__, text.encode()))
            ids = self.parts[text] = array("I", [x.id for x in self.tokenizer.model.tokenize(shown)]).tobytes() if text else b""
        return ids

    def encode(self, text: bytes) -> bytes:
        return self.encode_all([text])[0]


@lru_cache(maxsize=2)
def worker_tokenizer(path: str) -> CachedTokenizer:
    """One for all tasks of a Python worker, so that runs once seen stay known."""
    return CachedTokenizer(path)


@dataclass(frozen=True)
class PackCost:
    """Estimated cost of a piece of n tokens: linear * n + quadratic * n * n."""

    linear: float = 1.0
    quadratic: float = 1.0 / 2048

    def __call__(self, n: int) -> float:
        return self.linear * n + self.quadratic * n * n


def rooms(tokens: int, size: int) -> list[int]:
    """Lengths of the sequences that hold exactly so many tokens: full ones, and powers of two for the rest."""
    full, rest = divmod(tokens, size)
    return [size] * full + [1 << b for b in reversed(range(rest.bit_length())) if rest >> b & 1]


def balance(lengths: list[int], size: int, cost: PackCost) -> list[tuple[int, int, int, int, int]]:
    """(document, start, length, sequence, offset) for documents of the given lengths, all over 0.

    Pieces as long as a sequence are alone in theirs. The rest is placed in descending length; among sequences with room
    the cheapest is taken, then the first. Every sequence is filled to the brim, so there is no padding."""
    out, heap, sequence = [], [], 0
    for d, n in enumerate(lengths):
        full = n // size
        for k in range(full):
            out.append((d, k * size, size, sequence, 0))
            sequence += 1
        if n % size:
            heap.append((-(n % size), d, full * size))
    left = [*rooms(-sum(x[0] for x in heap), size)]
    base, used = sequence, [0] * len(left)
    heapq.heapify(heap)
    ready = [(0.0, s) for s in range(len(left))]  # those that had room when last seen, by cost
    short: list[tuple[int, int, float]] = []  # those without, by room
    while heap:
        minus, d, start = heapq.heappop(heap)
        n = -minus
        while short and -short[0][0] >= n:  # pieces get shorter, so these have room again
            _, s, c = heapq.heappop(short)
            heapq.heappush(ready, (c, s))
        while ready and left[ready[0][1]] < n:
            c, s = heapq.heappop(ready)
            if left[s]:
                heapq.heappush(short, (-left[s], s, c))
        if ready:
            c, s = heapq.heappop(ready)
        else:  # room for all is nowhere: cut
            _, s, c = heapq.heappop(short)
            heapq.heappush(heap, (left[s] - n, d, start + left[s]))
            n = left[s]
        out.append((d, start, n, base + s, used[s]))
        used[s] += n
        left[s] -= n
        heapq.heappush(ready, (c + cost(n), s))
    return out


NAMES = ["row", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_tokens", "ids"]


def pack(docs: DataFrame, path: str | None = None, size: int = 2048, end_id: int = 1, buffer_tokens: int = 4_000_000, cost: PackCost = PackCost(), with_ids: bool = True) -> DataFrame:
    """A row for each piece: ``row`` (struct of the document's columns other than text), start, length, ids_crc32,
    doc_tokens, sequence_id, offset, sequence_tokens, ids (binary, little-endian unsigned 32-bit; null without ``with_ids``).

    A document's ids are those of its text and ``end_id``; null and empty texts have that one id. A document longer than
    the buffer is packed by itself. Repeated rows are packed as often as they come. sequence_id is unique: the number of the
    task's partition, times 2**36, plus a count. An empty table gives no pieces.
    """
    from pyspark.sql.types import BinaryType, LongType, StructField, StructType

    path = path or tokenizer_path()
    rest = [c for c in docs.columns if c != "text"]
    row_type = StructType([StructField(f.name, f.dataType, True) for f in docs.schema if f.name != "text"])
    schema = StructType([StructField("row", row_type), *[StructField(n, LongType()) for n in NAMES[1:-1]], StructField("ids", BinaryType())])
    end = end_id.to_bytes(4, "little")

    def run(batches):
        tokenizer = worker_tokenizer(path)
        context = TaskContext.get()
        sequence = (context.partitionId() if context else 0) << 36
        held, rows, total = [], [], 0

        def flush():
            nonlocal sequence
            lengths = [len(x) // 4 for x in held]
            pieces = balance(lengths, size, cost)
            sizes: dict[int, int] = {}
            for _, _, n, s, _ in pieces:
                sizes[s] = sizes.get(s, 0) + n
            all_rows = pa.concat_arrays(rows)
            for at in range(0, len(pieces), 20_000):
                some = pieces[at : at + 20_000]
                ids = [held[d][4 * a : 4 * (a + n)] for d, a, n, _, _ in some]
                columns = [[a for _, a, _, _, _ in some], [n for _, _, n, _, _ in some], [zlib.crc32(x) for x in ids], [lengths[p[0]] for p in some], [sequence + p[3] for p in some], [p[4] for p in some], [sizes[p[3]] for p in some]]
                arrays = [pa.array(c, pa.int64()) for c in columns]
                yield pa.RecordBatch.from_arrays([all_rows.take(pa.array([p[0] for p in some], pa.int64())), *arrays, pa.array(ids if with_ids else [None] * len(some), pa.binary())], names=NAMES)
            sequence += len(sizes)

        for batch in batches:
            low = 0
            encoded = (ids for some in grouped(texts(batch.column(0)), len, 4 << 20) for ids in tokenizer.encode_all(some))
            for i, ids in enumerate(encoded):
                held.append(ids + end)
                total += len(held[-1]) // 4
                if total >= buffer_tokens:
                    rows.append(batch.column(1).slice(low, i + 1 - low))
                    yield from flush()
                    held, rows, total, low = [], [], 0, i + 1
            if low < batch.num_rows:
                rows.append(batch.column(1).slice(low))
        if held:
            yield from flush()

    row = F.struct(*[F.col(f"`{c}`") for c in rest]).alias("row")
    return docs.select(F.col("text").alias("text"), row).mapInArrow(lean(run), schema)
