"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

A pre-token is a doubly linked list of byte symbols. Each adjacent pair that the vocabulary can merge waits in the bucket of its rank;
a two-level bitmap marks the buckets in use, so the lowest waiting rank is two find-first-set steps away whatever the
length of the pre-token. Positions of a bucket are taken left to right. An entry whose pair has changed since it was put in is stale and skipped, so
nothing is ever removed from the middle of a bucket. A pre-token of n bytes costs O(n) bucket operations: very long ones do not degrade.

Defined cases: null text counts as empty and gives no ids; special tokens are ordinary text; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_of

#: Unicode's White_Space, as the pattern's \s is meant; fixed values.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
#: Pre-tokens remembered by a worker in each of two generations: what the younger one has not met again by the time it is full is forgotten.
MEMO = 300_000
#: Texts encoded before their ids are handed on.
ROWS = 512


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


class Encoder:
    def __init__(self, ranks: dict[bytes, int], pattern: str, memo: int = MEMO):
        import regex

        self.most = memo

        self.ranks = ranks
        self.tokens = [b""] * (max(ranks.values(), default=-1) + 1)
        for token, rank in ranks.items():
            self.tokens[rank] = token
        self.byte_id = [ranks.get(bytes([b]), -1) for b in range(256)]
        self.pairs: dict[int, int] = {}  # left << 17 | right -> rank; ids stay under 2 ** 17
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    self.pairs[left << 17 | right] = rank
        if len(self.tokens) >= 1 << 17:
            raise ValueError("the vocabulary has more ids than a pair key holds")
        self.pattern = regex.compile(pattern.replace(r"[^\s", f"[^{WHITE}").replace(r"(?!\S)", f"(?![^{WHITE}])").replace(r"\s", f"[{WHITE}]"))
        self.words = -(-len(self.tokens) // 64)
        self.leaf = [0] * self.words
        self.memo: dict[str, tuple[int, ...]] = {}
        self.older: dict[str, tuple[int, ...]] = {}

    def merge(self, piece: bytes) -> list[int]:
        """Ids of one pre-token."""
        known = self.ranks.get(piece)
        if known is not None:
            return [known]
        find, leaf, n = self.pairs.get, self.leaf, len(piece)
        ids = list(map(self.byte_id.__getitem__, piece))
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        nxt[n - 1] = -1
        root, buckets, at = 0, {}, 0
        for first, second in zip(ids, ids[1:]):
            rank = find(first << 17 | second)
            if rank is not None:
                if rank in buckets:
                    buckets[rank].append(at)
                else:
                    buckets[rank] = [at]
                    word = rank >> 6
                    leaf[word] |= 1 << (rank & 63)
                    root |= 1 << word
            at += 1
        while root:
            word = (root & -root).bit_length() - 1
            bits = leaf[word]
            low = bits & -bits
            rank = (word << 6) + low.bit_length() - 1
            leaf[word] = bits ^ low
            if bits == low:
                root ^= 1 << word
            waiting = buckets.pop(rank)
            if len(waiting) > 1:
                waiting.sort()
            left = len(waiting)
            for at in waiting:
                left -= 1
                right = nxt[at]
                if right < 0 or find(ids[at] << 17 | ids[right]) != rank:
                    continue  # stale
                ids[at], ids[right] = rank, -1
                after = nxt[at] = nxt[right]
                nxt[right] = -1
                lower = False
                if after >= 0:
                    prv[after] = at
                    new = find(rank << 17 | ids[after])
                    if new is not None:
                        lower = new <= rank
                        if new in buckets:
                            buckets[new].append(at)
                        else:
                            buckets[new] = [at]
                            word = new >> 6
                            leaf[word] |= 1 << (new & 63)
                            root |= 1 << word
                before = prv[at]
                if before >= 0:
                    new = find(ids[before] << 17 | rank)
                    if new is not None:
                        lower |= new <= rank
                        if new in buckets:
                            buckets[new].append(before)
                        else:
                            buckets[new] = [before]
                            word = new >> 6
                            leaf[word] |= 1 << (new & 63)
                            root |= 1 << word
                if lower and left:  # a merge of lower rank has appeared: the rest of the bucket waits again
                    rest = waiting[-left:]
                    if rank in buckets:
                        buckets[rank] += rest
                    else:
                        buckets[rank] = rest
                        leaf[rank >> 6] |= 1 << (rank & 63)
                        root |= 1 << (rank >> 6)
                    break
        return [x for x in ids if x >= 0]

    def encode(self, text: str) -> list[int]:
        memo, out = self.memo, []
        for piece in self.pattern.findall(text):
            ids = memo.get(piece)
            if ids is None:
                ids = self.older.get(piece) or tuple(self.merge(piece.encode()))
                if len(piece) < 64:
                    if len(memo) >= self.most:
                        self.older, self.memo = memo, {}
                        memo = self.memo
                    memo[piece] = ids
            out += ids
        return out

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


_WORKER: dict[tuple[str, str, int], Encoder] = {}


def _worker_encoder(vocabulary: str, pattern: str, memo: int, ranks) -> Encoder:
    """The encoder of this Python worker, with what it remembers from task to task."""
    if (vocabulary, pattern, memo) not in _WORKER:
        _WORKER[vocabulary, pattern, memo] = Encoder(ranks.value, pattern, memo)
    return _WORKER[vocabulary, pattern, memo]


def encode_documents(docs: DataFrame, vocabulary: str, pattern: str, *, with_ids: bool = False, memo: int = MEMO, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: doc_id, n_tokens, ids_sha256, decoded_sha256 and, if asked for, the ids themselves and the columns of ``carry``.

    ``memo``: pre-tokens remembered in each of two generations, some 200 bytes each in every Python worker. ``vocabulary``: path of a rank file; it is read on the driver and sent to the tasks (its size is that of a vocabulary).
    """
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(vocabulary))
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _worker_encoder(vocabulary, pattern, memo, ranks)
        digits = [str(i) for i in range(len(encoder.tokens))]
        for batch in (whole.slice(k, ROWS) for whole in batches for k in range(0, whole.num_rows, ROWS)):
            counts, hashes, decoded, lists = [], [], [], []
            for text in batch.column(1).to_pylist():
                ids = encoder.encode(text)
                counts.append(len(ids))
                hashes.append(hashlib.sha256(" ".join(map(digits.__getitem__, ids)).encode()).hexdigest())
                decoded.append(hashlib.sha256(encoder.decode(ids)).hexdigest())
                if with_ids:
                    lists.append(np.array(ids, np.int32))
            cols = [batch.column(0), pa.array(counts, pa.int64()), pa.array(hashes, pa.string()), pa.array(decoded, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if with_ids:
                cols, names = [*cols, pa.array(lists, pa.list_(pa.int32()))], [*names, "ids"]
            yield pa.RecordBatch.from_arrays([*cols, *batch.columns[2:]], [*names, *carry])

    schema = f"doc_id {id_type}, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if with_ids else "")
    schema += "".join(f", {c} {docs.schema[c].dataType.simpleString()}" for c in carry)
    return docs.select("doc_id", text_of().alias("text"), *carry).mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, vocabulary: str) -> DataFrame:
    """doc_id and text (invalid UTF-8 replaced) of the rows of ``encode_documents(..., with_ids=True)``; null ids give an empty text."""
    ranks = encoded.sparkSession.sparkContext.broadcast(read_ranks(vocabulary))
    id_type = encoded.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = {rank: token for token, rank in ranks.value.items()}
        for batch in batches:
            texts = [b"".join(map(tokens.__getitem__, ids or ())).decode("utf-8", "replace") for ids in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, f"doc_id {id_type}, text string")
