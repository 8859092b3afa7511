"""Packing of tokenized documents into windows by Karmarkar-Karp multiway differencing.

A document's ids are cut at multiples of the window length; each full cut is a window of its own and the rest is an item.
Items are dealt by hash into blocks of bounded count, and each block is solved by differencing: every item starts as a partial
partition of k parts, the two partitions of largest spread are merged with opposing imbalances (largest part to
smallest), and the last one holds k near-equal windows.  Where a window exceeds the capacity, k rises and the block is solved
anew.  Only lengths are moved between executors.

Null and empty texts have the end id alone.  Repeated rows are packed each.  Null document ids pass through.
"""

from __future__ import annotations

import heapq
import json
import re
import unicodedata
import zlib
from array import array
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fieldseg.runtime import cut

CAPACITY = 4096
END_ID = 2
BLOCK_ITEMS = 1500
#: Words whose ids a worker remembers; others are encoded each time.
KNOWN_WORDS = 300_000
_PART = re.compile(rb"([a-z\x80-\xff]+)([!-&(-/:-@\[-`{-~]*)")
_encoders: dict[str, "Encoder"] = {}


def _byte_letters() -> dict[str, int]:
    """The printable letter that byte-level vocabularies write for each byte: itself if printable in Latin-1, else the next free one."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class Encoder(dict):
    """Ids of whole texts as little-endian bytes; the dictionary holds the ids of known words.

    The tokenizer's pre-tokens never cross ASCII white space, so words are encoded by themselves.  A word of letters with ASCII
    marks behind it (no apostrophe, which begins contractions) splits exactly where the tokenizer's pattern splits it; its
    letters are one pre-token.  Where the vocabulary numbers its merges in order and marks word ends, those merges run in a
    faster library on the same table; all other words go through the tokenizer itself.
    """

    def __init__(self, path: str, end_id: int):
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer, self.end = Tokenizer.from_file(path), np.uint32(end_id).tobytes()
        self.merges = self._merge_table(path)

    @staticmethod
    def _merge_table(path: str):
        import tiktoken

        with open(path) as f:
            kind = json.load(f)
        model, letters = kind["model"], _byte_letters()
        normal = json.dumps(kind["normalizer"])
        special = {t["content"] for t in kind["added_tokens"]}
        if model.get("end_of_word_suffix") != "</w>" or model.get("unk_token") or '"Lowercase"' not in normal or '"NFC"' not in normal:
            return None
        ranks = {}
        for token, i in model["vocab"].items():
            if token not in special:
                word = token.removesuffix("</w>")
                ranks[bytes(letters[c] for c in word) + b"\0" * (word != token)] = i
        if len(ranks) != len(model["vocab"].keys() - special) or any(len(x) > 1 for x, i in ranks.items() if i < 256):
            return None
        merged = [tuple(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]]
        if any(model["vocab"][a + b] != 512 + i for i, (a, b) in enumerate(merged)):
            return None
        return tiktoken.Encoding("words", pat_str=r"[^\x00]+\x00", mergeable_ranks=ranks, special_tokens={})

    def _slow(self, word: bytes) -> bytes:
        return np.array(self.tokenizer.encode(word.decode(), add_special_tokens=False).ids, "<u4").tobytes()

    def __missing__(self, word: bytes) -> bytes:
        m = _PART.fullmatch(word) if self.merges else None
        if m and (core := m[1].decode()).isalpha():
            if m[2]:
                ids = self[m[1]] + (self[m[2]] if len(m[2]) < 8 else self._slow(m[2]))
            else:
                if not core.isascii():
                    core = unicodedata.normalize("NFC", core).lower()
                ids = array("I", self.merges.encode_ordinary(core + "\0")).tobytes() if core.isalpha() else self._slow(word)
        else:
            ids = self._slow(word)
        if len(self) < KNOWN_WORDS:
            self[word] = ids
        return ids

    def encode(self, text: bytes) -> bytes:
        """Ids of a text with the end id, four bytes an id."""
        # only A-Z: the tokenizer lower-cases the rest after it has composed characters
        return b"".join(map(self.__getitem__, text.lower().split())) + self.end


def encoder(path: str, end_id: int = END_ID) -> Encoder:
    """The worker's encoder for a vocabulary file (kept between tasks)."""
    key = f"{path}:{end_id}"
    if key not in _encoders:
        _encoders[key] = Encoder(path, end_id)
    return _encoders[key]


def token_pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): full cuts of `capacity` ids and the rest of each document."""

    def run(batches):
        enc = encoder(vocabulary, end_id)
        for rb in batches:
            ids, texts = rb.column(0), rb.column(1)
            rows, start, length, crc, total = [], [], [], [], []
            for i, t in enumerate(texts):
                b = enc.encode((t.as_py() or "").encode())
                m = len(b) // 4
                for s in range(0, m, capacity):
                    e = min(m, s + capacity)
                    rows.append(i)
                    start.append(s)
                    length.append(e - s)
                    crc.append(zlib.crc32(memoryview(b)[4 * s : 4 * e]))
                    total.append(m)
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(rows, pa.int64())), *(pa.array(x, pa.int64()) for x in (start, length, crc, total))], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return own.mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")


def difference(sizes: np.ndarray, k: int) -> np.ndarray:
    """The part (0 to k - 1) of each item, by multiway differencing."""
    n = len(sizes)
    left, right = np.full(2 * n, -1, np.int64), np.full(2 * n, -1, np.int64)
    fresh, tie = count(n), count()
    # a partition is its non-empty parts only, largest first; the others are 0
    heap = [(-int(s), next(tie), np.array([s], np.int64), np.array([i], np.int64)) for i, s in enumerate(sizes)]
    heapq.heapify(heap)
    while len(heap) > 1:
        _, _, s1, n1 = heapq.heappop(heap)
        _, _, s2, n2 = heapq.heappop(heap)
        over = len(s1) + len(s2) - k
        if over > 0:
            # the smallest `over` parts of the first meet the smallest of the second, in opposite order
            a, b = len(s1) - over, len(s2) - over
            made = np.array([next(fresh) for _ in range(over)], np.int64)
            left[made], right[made] = n1[a:], n2[b:][::-1]
            s = np.concatenate([s1[:a], s2[:b], s1[a:] + s2[b:][::-1]])
            nodes = np.concatenate([n1[:a], n2[:b], made])
        else:
            s, nodes = np.concatenate([s1, s2]), np.concatenate([n1, n2])
        order = np.argsort(-s, kind="stable")
        s, nodes = s[order], nodes[order]
        spread = int(s[0]) - (int(s[-1]) if len(s) == k else 0)
        heapq.heappush(heap, (-spread, next(tie), s, nodes))
    part = np.zeros(n, np.int64)
    for p, node in enumerate(heap[0][3].tolist()):
        stack = [node]
        while stack:
            x = stack.pop()
            if x < n:
                part[x] = p
            else:
                stack += (int(left[x]), int(right[x]))
    return part


def near_equal_windows(sizes: np.ndarray, capacity: int = CAPACITY) -> np.ndarray:
    """The window of each item; windows hold at most `capacity` and their count rises until they do."""
    if not len(sizes):
        return np.zeros(0, np.int64)
    k = max(1, -(-int(sizes.sum()) // capacity))
    while True:
        part = difference(sizes, k)
        most = int(np.bincount(part, sizes, minlength=k).max())
        if most <= capacity:
            return part
        k = min(len(sizes), max(k + 1, int(k * (1 + 0.5 * (most / capacity - 1)))))


def pack(pieces: DataFrame, capacity: int = CAPACITY, block_items: int = BLOCK_ITEMS) -> DataFrame:
    """`pieces` (with `doc_id`, `start`, `length` of at most `capacity`) with `sequence_id` and `offset` in it."""
    pieces = cut(pieces)
    items = pieces.where(F.col("length") < capacity)
    n_blocks = max(1, -(-items.count() // block_items))
    kinds = pieces.dtypes
    schema = ", ".join(f"`{c}` {t}" for c, t in kinds) + ", sequence_id long, `offset` long"

    def solve(key, table):
        order = np.lexsort((table["start"].to_numpy(), table["doc_id"].fill_null(-1).to_numpy()))
        table = table.drop_columns(["_fs_block"]).take(pa.array(order))
        sizes = table["length"].to_numpy()
        part = near_equal_windows(sizes, capacity)
        order = np.argsort(part, kind="stable")
        table, sizes, part = table.take(pa.array(order)), sizes[order], part[order]
        at = np.cumsum(sizes) - sizes
        first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]]))
        offset = at - np.repeat(at[first], np.diff(np.concatenate([first, [len(part)]])))
        ids = (np.int64(key[0].as_py()) << 24) + part
        return table.append_column("sequence_id", pa.array(ids)).append_column("offset", pa.array(offset))

    # a third of the rows may be copies of one: the running number in the hash deals them to all blocks
    block = F.pmod(F.xxhash64("doc_id", "start", "ids_crc32", F.monotonically_increasing_id()), F.lit(n_blocks))
    mixed = items.withColumn("_fs_block", block).groupBy("_fs_block").applyInArrow(solve, schema)
    # full cuts follow the blocks in the numbering, each a window of its own
    full = pieces.where(F.col("length") == capacity)
    full = full.withColumns({"sequence_id": F.lit(1 << 62) + F.monotonically_increasing_id(), "offset": F.lit(0).cast("long")})
    return mixed.unionByName(full)


def op10(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    packed = pack(token_pieces(docs, public_tokenizers.path("word_bpe_49k.json")))
    return packed.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
