"""Best-fit packing of token sequences with a fixed number of open bins.

Each task packs its rows as they come. Open bins sit in lists keyed by free space, and a
bitset over free spaces finds the tightest bin with one shift and its lowest set bit; if
more than the allowed number are open, the fullest closes. Nothing is shuffled, a task's
memory is its open bins, and a lost task packs the same rows into the same bins again.

Defined cases: null or empty text is the end token alone; a document longer than a
sequence is cut into full pieces after a first piece that takes the remainder; repeated rows
are packed each on its own; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from dynreach.llm.common import give_back

#: Bytes of units that a worker keeps (by estimate, UNIT_BYTES for each besides its own), the longest unit kept,
#: and the characters encoded at a time.
CACHE_BYTES, UNIT_BYTES, CACHE_CHARS, GROUP_CHARS, LEARN_UNITS = 384 << 20, 220, 64, 1_000_000, 3_000
#: Rows that a worker takes from a batch at a time, and pieces that it holds before it hands them over.
SLICE_ROWS, FLUSH_PIECES = 500, 1024
#: The same for a worker that runs nothing else: characters, units, rows.
ALONE_CHARS, ALONE_UNITS, ALONE_ROWS = 8_000_000, 50_000, 10_000


class Encoder:
    """Ids of whole texts as little-endian 32-bit bytes, by the tokenizers library.

    A byte-level pattern always parts before a blank that precedes a non-blank, so texts are
    cut there, units are encoded once while they are kept, and their ids are joined. What is kept takes
    cache_bytes at most besides the units of one group of GROUP_CHARS characters; beyond that only units of the group at hand stay.
    """

    def __init__(self, path: str, cache_bytes: int = CACHE_BYTES, shared: bool = True):
        from tokenizers import Tokenizer

        self.group_chars, self.learn_units = (GROUP_CHARS, LEARN_UNITS) if shared else (ALONE_CHARS, ALONE_UNITS)

        self.tokenizer, self.cache_bytes, self.held = Tokenizer.from_file(path), cache_bytes, 0
        self.special = [t.content for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.boundary, self.irregular = re.compile(" (?=\\S)"), re.compile(" (?!\\S)")
        self.kept: dict[str, dict[str, bytes]] = {"": {}, " ": {}}

    def learn(self, units: list[str], lead: str, into: dict[str, bytes]) -> None:
        for k in range(0, len(units), self.learn_units):
            part = units[k : k + self.learn_units]
            for u, e in zip(part, self.tokenizer.encode_batch_fast([lead + u for u in part], add_special_tokens=False)):
                ids = b"".join([i.to_bytes(4, "little") for i in e.ids])
                into[u] = ids
                self.held += self.taken(u, ids)

    @staticmethod
    def taken(unit: str, ids: bytes) -> int:
        return UNIT_BYTES + len(unit) * (1 if unit.isascii() else 4) + len(ids)

    def clear(self) -> None:
        for kept in self.kept.values():
            kept.clear()
        self.held = 0

    def encode(self, texts: list[str | None]) -> Iterator[bytes]:
        group, held = [], 0
        for text in texts:
            group.append(text or "")
            held += len(group[-1])
            if held >= self.group_chars:
                yield from self._group(group)
                group, held = [], 0
        yield from self._group(group)

    def _group(self, texts: list[str]) -> Iterator[bytes]:
        units, new = [], {"": set(), " ": set()}
        for t in texts:
            if any(s in t for s in self.special):
                head, rest = t, []
            else:
                head, *rest = self.boundary.split(t) if self.irregular.search(t) else t.split(" ")
            units.append((head, rest))
            new[""].add(head)
            new[" "].update(rest)
        long = {}
        for lead, kept in self.kept.items():
            missing = new[lead].difference(kept)
            long[lead] = [u for u in missing if len(u) > CACHE_CHARS]
            self.learn(list(missing), lead, kept)
        first, later = self.kept[""], self.kept[" "].__getitem__
        for head, rest in units:
            yield first[head] + b"".join(map(later, rest))
        for lead, kept in self.kept.items():
            for u in long[lead]:
                self.held -= self.taken(u, kept.pop(u))
        if self.held > self.cache_bytes:
            self.kept = {lead: {u: kept[u] for u in new[lead] if u in kept} for lead, kept in self.kept.items()}
            self.held = sum(self.taken(u, ids) for kept in self.kept.values() for u, ids in kept.items())
            if self.held > self.cache_bytes:
                self.clear()


class OpenBins:
    """Online best fit with at most `most` open bins."""

    def __init__(self, capacity: int, most: int):
        self.capacity, self.most = capacity, most
        self.bits, self.by_free = 0, [[] for _ in range(capacity + 1)]
        self.open = self.made = 0

    def _take(self, free: int) -> int:
        bins = self.by_free[free]
        b = bins.pop()
        if not bins:
            self.bits ^= 1 << free
        self.open -= 1
        return b

    def place(self, size: int) -> tuple[int, int]:
        """(bin, offset) of an item; a bin without room closes by itself."""
        rest = self.bits >> size
        if rest:
            free = size + (rest & -rest).bit_length() - 1
            b = self._take(free)
        else:
            free, b = self.capacity, self.made
            self.made += 1
        left = free - size
        if left:
            self.by_free[left].append(b)
            self.bits |= 1 << left
            self.open += 1
            if self.open > self.most:
                self._take((self.bits & -self.bits).bit_length() - 1)
        return b, self.capacity - free


def cut_lengths(n: int, capacity: int) -> list[int]:
    first = n % capacity
    return ([first] if first else []) + [capacity] * (n // capacity)


def pack(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    capacity: int = 1024,
    open_bins: int = 512,
    end_id: int = 2,
    path: str | None = None,
    with_ids: bool = False,
    with_row: bool = False,
    cache_bytes: int = CACHE_BYTES,
    shared: bool = False,
) -> DataFrame:
    """One row per piece: id, piece, start, length, ids_crc32, sequence_id, offset [, ids as binary] [, row_id].

    row_id is a number of the document's row, so that copies of a document can be told apart. shared: a worker frees
    its units when a task ends, as it runs other operators too; by itself it keeps them for its next task.
    """
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    end = end_id.to_bytes(4, "little")
    kinds = {"piece": "int", "start": "long", "length": "long", "ids_crc32": "long", "sequence_id": "long", "offset": "long"}
    kinds |= {"ids": "binary"} if with_ids else {}
    kinds |= {"row_id": "long"} if with_row else {}
    arrow = {"int": pa.int32(), "long": pa.int64(), "binary": pa.binary()}
    schema = f"`{id_col}` {docs.schema[id_col].dataType.simpleString()}, " + ", ".join(f"{n} {k}" for n, k in kinds.items())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if shared:
            give_back()  # what other operators have left
        encoder, base, rows = _encoder(path, cache_bytes, shared), TaskContext.get().partitionId() << 36, 0
        bins, rows_at_once = OpenBins(capacity, open_bins), SLICE_ROWS if shared else ALONE_ROWS

        def made(batch: pa.RecordBatch, source: list[int], out: dict[str, list]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(source, pa.int64())), *(pa.array(out[n], arrow[k]) for n, k in kinds.items())], [id_col, *kinds])

        try:
            for batch in (whole.slice(k, rows_at_once) for whole in batches for k in range(0, whole.num_rows, rows_at_once)):
                source, out = [], {n: [] for n in kinds}
                for row, ids in enumerate(encoder.encode(batch.column(1).to_pylist())):
                    ids, at = ids + end, 0
                    for piece, n in enumerate(cut_lengths(len(ids) // 4, capacity)):
                        part = ids[4 * at : 4 * (at + n)]
                        b, offset = bins.place(n)
                        source.append(row)
                        values = {"piece": piece, "start": at, "length": n, "ids_crc32": zlib.crc32(part), "sequence_id": base + b, "offset": offset, "ids": part, "row_id": base + rows}
                        for name, column in out.items():
                            column.append(values[name])
                        at += n
                        if len(source) >= FLUSH_PIECES:
                            yield made(batch, source, out)
                            source, out = [], {n: [] for n in kinds}
                    rows += 1
                yield made(batch, source, out)
        finally:
            if shared:
                encoder.clear()
                give_back()

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def _encoder(path: str, cache_bytes: int = CACHE_BYTES, shared: bool = False, kept: dict = {}) -> Encoder:  # noqa: B006  one per worker and setting
    key = (path, cache_bytes, shared)
    if key not in kept:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        kept.clear()
        kept[key] = Encoder(path, cache_bytes, shared)
    return kept[key]
