"""Byte-level BPE with a hierarchical-bitmap rank queue.

A pre-token is a linked list of symbols. Every adjacent pair that has a merge rank sits in the bucket of that rank;
a two-level bitmap says which buckets hold something, so the next rank is two find-first-set steps away whatever
the length of the pre-token. The lists of many pre-tokens lie behind each other and share the queue, so a bucket is
emptied for all of them at a time. Entries are never removed when a neighbour changes: a popped position whose current
rank differs from its bucket's is stale and skipped. Work is near linear in the pre-tokens, so texts without any
white space cost the same per byte as ordinary prose.

Defined cases: a null text encodes as the empty text (no ids); repeated rows and repeated or null doc_ids give one
result per row; an empty table gives an empty result; other input columns are ignored or, on request, carried along.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from bisect import insort
from collections.abc import Iterator
from itertools import chain
from operator import neg

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from lowrank_spark.runtime import ship_package

#: Bytes, about, of one generation of a memo; a memo holds two (memos only: results do not depend on them).
MEMO_BYTES = 64 << 20
#: Characters, about, of the texts that are encoded together.
GROUP = 1 << 22
#: Characters that count as white space for some engine; beside a space they rule out the cut at spaces.
_BLANKS = "\t\n\x0b\x0c\r\x1c\x1d\x1e\x1f\x85\xa0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000 "


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class RankQueue:
    """Buckets of positions by merge rank; a bitmap of 256-way words, and one word over those, says which are filled.

    A bucket is None, one position, or a heap of positions. `merged` of ByteBpe works on these fields directly; its buckets
    are lists, which it sorts when their turn comes.
    """

    WAYS = 8

    def __init__(self, n_ranks: int):
        self.leaf = [0] * ((n_ranks >> self.WAYS) + 1)
        self.top = 0
        self.buckets: list[None | int | list[int]] = [None] * n_ranks

    def push(self, rank: int, pos: int) -> None:
        b = self.buckets[rank]
        if b is None:
            self.buckets[rank] = pos
            self.leaf[rank >> 8] |= 1 << (rank & 255)
            self.top |= 1 << (rank >> 8)
        elif b.__class__ is list:
            heapq.heappush(b, pos)
        else:
            self.buckets[rank] = [b, pos] if b <= pos else [pos, b]

    def pop(self) -> tuple[int, int] | None:
        """The lowest rank's leftmost position, or None when nothing is left."""
        t = self.top
        if not t:
            return None
        w = (t & -t).bit_length() - 1
        y = self.leaf[w]
        rank = (w << 8) | ((y & -y).bit_length() - 1)
        b = self.buckets[rank]
        if b.__class__ is list:
            pos = heapq.heappop(b)
            if len(b) == 1:
                self.buckets[rank] = b[0]
            return rank, pos
        self.buckets[rank] = None
        y &= y - 1
        self.leaf[w] = y
        if not y:
            self.top = t & (t - 1)
        return rank, b


class Memo:
    """Two generations of remembered ids, bounded in bytes: what the older one still answers moves to the younger one."""

    def __init__(self, limit: int = MEMO_BYTES):
        self.limit = limit
        self.forget()

    def forget(self) -> None:
        self.young: dict[str, tuple[int, ...]] = {}
        self.old: dict[str, tuple[int, ...]] = {}
        self.size = 0

    def put(self, key: str, ids: tuple[int, ...]) -> None:
        if self.size >= self.limit:
            self.old, self.young, self.size = self.young, {}, 0
        self.young[key] = ids
        self.size += 200 + 4 * len(key) + 8 * len(ids)

    def again(self, key: str) -> tuple[int, ...] | None:
        """For a key that the younger generation lacks."""
        ids = self.old.get(key)
        if ids is not None:
            self.put(key, ids)
        return ids


class ByteBpe:
    """Encoder and decoder of one rank file and one pre-token pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.find = regex.compile(pattern).findall
        n = max(ranks.values(), default=0) + 1
        self.queue = RankQueue(n)
        self.bits = [1 << i for i in range(max(256, (n >> 8) + 1))]
        self.table = {i: b for b, i in ranks.items()}
        self.names = pa.array([b" %d" % i for i in range(n)], pa.large_binary())
        self.bytes_of = pa.array([self.table.get(i) for i in range(n)], pa.large_binary())
        self.single = [ranks.get(bytes([i])) for i in range(256)]
        # by left symbol: right symbol -> rank of the pair
        self.pairs: list[dict[int, int]] = [{} for _ in range(n)]
        for token, r in ranks.items():
            for cut in range(1, len(token)):
                a, b = ranks.get(token[:cut]), ranks.get(token[cut:])
                if a is not None and b is not None:
                    self.pairs[a][b] = r
        # by left byte: rank of the pair with each right byte, -1 for none
        get = lambda c, d: self.pairs[c].get(d, -1) if c is not None and d is not None else -1
        self.starts = np.array([[get(c, d) for d in self.single] for c in self.single], np.int64)
        self.single = np.array(self.single, np.int64)
        self.piece_memo, self.chunk_memo = Memo(), Memo()
        # the cut at spaces holds for patterns that take at most one space, and only before other characters
        self.cuts = " ?" in pattern
        # a space and letters are one pre-token if no alternative before that one can start there
        head, words, _ = pattern.partition(r"| ?\p{L}+|")
        self.words = bool(words) and all(x.startswith("'") for x in head.split("|"))

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one pre-token."""
        return self.merge_all([piece])[0]

    def merge_all(self, pieces: list[bytes]) -> list[tuple[int, ...]]:
        """Ids of each pre-token.

        Those that are no token lie behind each other in one list of symbols, without pairs across their borders, so a bucket
        holds the positions of its rank in all of them and the bitmap is asked once a bucket. The queue's push and pop are
        written out here: this is the inner loop. A pair of a lower rank than the bucket's goes first; only the last merge can have made it.
        """
        out: list = [self.ranks.get(p) for p in pieces]
        todo = [k for k, whole in enumerate(out) if whole is None]
        sizes = np.array([len(pieces[k]) for k in todo], np.int64)
        ends = np.cumsum(sizes)
        data = np.frombuffer(b"".join([pieces[k] for k in todo]), np.uint8)
        ids, n = self.merged(data, ends), len(data)
        stay = ids >= 0
        flat = ids[stay].tolist()
        cut = np.concatenate([[0], np.cumsum(stay)])[ends].tolist() if n else [0] * len(todo)
        lo = 0
        for k, hi in zip(todo, cut, strict=True):
            out[k] = tuple(flat[lo:hi])
            lo = hi
        return [x if x.__class__ is tuple else (x,) for x in out]

    def merged(self, data: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """A symbol or -1 for every byte: the ids of pre-tokens that lie behind each other and end before `ends`."""
        n = len(data)
        if not n:
            return np.empty(0, np.int64)
        rank = np.full(n, -1, np.int64)  # rank of the pair that starts here
        rank[:-1] = self.starts[data[:-1], data[1:]]
        rank[ends[ends > 0] - 1] = -1
        first = np.flatnonzero(rank >= 0)
        first = first[np.argsort(rank[first], kind="stable")]
        bits, pairs, push, pop = self.bits, self.pairs, heapq.heappush, heapq.heappop
        leaf, buckets, top = self.queue.leaf, self.queue.buckets, 0
        filled, lo = np.unique(rank[first], return_index=True)
        places = first.tolist()
        for r, i, j in zip(filled.tolist(), lo.tolist(), [*lo[1:].tolist(), len(first)], strict=False):  # none without pairs
            buckets[r] = places[i:j]
            leaf[r >> 8] |= bits[r & 255]
            top |= bits[r >> 8]
        at, ids = rank.tolist(), self.single[data].tolist()
        nxt = list(range(1, n + 1))  # start of the following symbol
        prv = list(range(-1, n - 1))
        low: list[tuple[int, int]] = []  # pairs of a lower rank than the bucket's
        nxt.append(n)
        at.append(-1)
        ids.append(-1)
        for e in ends.tolist():  # no symbol follows the last one of a pre-token, none comes before the first
            nxt[e - 1] = n
            if e < n:
                prv[e] = -1
        while top:
            g = (top & -top).bit_length() - 1
            y = leaf[g]
            rank_of = (g << 8) | ((y & -y).bit_length() - 1)
            q = buckets[rank_of]
            q.sort(reverse=True)
            while q or low:
                if low:
                    r, i = pop(low)
                else:
                    r, i = rank_of, q.pop()
                if at[i] != r:
                    continue  # stale: a neighbour has merged since
                j = nxt[i]
                k = nxt[j]
                nxt[i] = k
                ids[i] = r
                at[j] = ids[j] = at[i] = -1
                if k < n:
                    prv[k] = i
                    v = pairs[r].get(ids[k])
                    if v is not None:
                        at[i] = v
                        if v > rank_of:
                            b = buckets[v]
                            if b is None:
                                buckets[v] = [i]
                                leaf[v >> 8] |= bits[v & 255]
                                top |= bits[v >> 8]
                            else:
                                b.append(i)
                        elif v == rank_of:
                            insort(q, i, key=neg)
                        else:
                            push(low, (v, i))
                h = prv[i]
                if h >= 0:
                    v = pairs[ids[h]].get(r)
                    if v is None:
                        at[h] = -1
                    elif at[h] != v:
                        at[h] = v
                        if v > rank_of:
                            b = buckets[v]
                            if b is None:
                                buckets[v] = [h]
                                leaf[v >> 8] |= bits[v & 255]
                                top |= bits[v >> 8]
                            else:
                                b.append(h)
                        elif v == rank_of:
                            insort(q, h, key=neg)
                        else:
                            push(low, (v, h))
            buckets[rank_of] = None
            y = leaf[g] ^ bits[rank_of & 255]
            leaf[g] = y
            if not y:
                top ^= bits[g]
        return np.array(ids[:n], np.int64)

    def forget(self) -> None:
        """Frees the memos; the tables stay."""
        self.piece_memo.forget()
        self.chunk_memo.forget()

    def encode(self, text: str) -> list[int]:
        """Ids of a text."""
        return self.encode_all([text])[1].tolist()

    def encode_all(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(offsets, ids) of the texts behind each other; what is new in all of them is merged at once.

        Where a single space stands between two characters that are no white space, a pre-token starts at the space
        whatever comes before, so the parts between such spaces can be encoded, and remembered, on their own. Each
        different part is looked up once.
        """
        heads, plain = [], []  # what no space comes before, by the pattern; and the texts that are cut
        for text in texts:
            whole = not self.cuts or "  " in text or any(b in text and (f" {b}" in text or f"{b} " in text) for b in (_BLANKS[:9] if text.isascii() else _BLANKS[:-1]))
            heads.append(self.find(text if whole else text.partition(" ")[0]))
            plain.append("" if whole else text)
        cut = pc.split_pattern(pa.array(plain, pa.string()), " ")
        at = cut.offsets.to_numpy().astype(np.int64)
        tail = np.ones(at[-1], bool)
        tail[at[:-1]] = False
        parts = cut.values.filter(pa.array(tail)).dictionary_encode()
        chunks = parts.dictionary.to_pylist()
        which = np.empty(len(tail), np.int64)
        which[tail] = parts.indices.to_numpy()
        which[at[:-1]] = len(chunks) + np.arange(len(texts))
        found = self._known(chunks, heads)
        size = np.fromiter(map(len, found), np.int64, len(found))
        flat = np.fromiter(chain.from_iterable(found), np.int64, int(size.sum()))
        n = size[which]
        ends = np.concatenate([[0], np.cumsum(n)])
        first = np.concatenate([[0], np.cumsum(size)])[which]
        return ends[at], flat[np.repeat(first - ends[:-1], n) + np.arange(ends[-1])]

    def _known(self, chunks: list[str], heads: list[list[str]]) -> list[tuple[int, ...]]:
        """Ids of each chunk behind a space, then of each list of pre-tokens."""
        memo, pieces, words = self.chunk_memo, self.piece_memo, self.words
        ids_of = [memo.young.get(c) or memo.again(c) for c in chunks]
        new = [k for k, ids in enumerate(ids_of) if ids is None]
        # Latin letters alone are letters in every version of Unicode; they need no pattern
        cut = [[" " + c] if words and c.isalpha() and (c.isascii() or max(c) < "\u0250") else self.find(" " + c) for c in map(chunks.__getitem__, new)]
        # the memo may drop a generation meanwhile: what these texts need is held here
        have: dict[str, tuple[int, ...] | None] = dict.fromkeys(chain.from_iterable(chain(heads, cut)))
        for p in have:
            have[p] = pieces.young.get(p) or pieces.again(p)
        left = [p for p, ids in have.items() if ids is None]
        for p, ids in zip(left, self.merge_all([p.encode("utf-8", "surrogatepass") for p in left]), strict=True):
            have[p] = ids
            # a pre-token that is a whole chunk is remembered as such
            if len(p) <= 64 and p[0] != " ":
                pieces.put(p, ids)
        join = lambda found: have[found[0]] if len(found) == 1 else tuple(chain.from_iterable([have[p] for p in found]))
        for k, found in zip(new, cut, strict=True):
            ids_of[k] = ids = join(found)
            if len(chunks[k]) <= 64:
                memo.put(chunks[k], ids)
        return ids_of + [join(found) for found in heads]

    def decode(self, ids) -> bytes:
        return b"".join(map(self.table.__getitem__, ids))

    def decode_all(self, ids: np.ndarray) -> tuple[np.ndarray, memoryview]:
        """(offsets, bytes) of the decoded ids behind each other."""
        return self._written(self.bytes_of, ids)

    def names_all(self, ids: np.ndarray) -> tuple[np.ndarray, memoryview]:
        """(offsets, bytes) of the decimal ids behind each other, each behind a space."""
        return self._written(self.names, ids)

    @staticmethod
    def _written(what: pa.Array, ids: np.ndarray) -> tuple[np.ndarray, memoryview]:
        """Places and bytes of what stands for each id, one behind the other."""
        got = what.take(pa.array(ids))
        _, at, data = got.buffers()
        return np.frombuffer(at, np.int64, len(got) + 1, got.offset * 8), memoryview(data) if data is not None else memoryview(b"")


_LIVE: dict[tuple[str, str], ByteBpe] = {}


def live(vocab_path: str, pattern: str) -> ByteBpe:
    """This process's encoder: its tables outlive a task, its memos do not."""
    if (vocab_path, pattern) not in _LIVE:
        _LIVE[vocab_path, pattern] = ByteBpe(load_ranks(vocab_path), pattern)
    return _LIVE[vocab_path, pattern]


def _groups(texts: pa.Array) -> Iterator[list[str]]:
    """The texts in groups of about GROUP characters, the last one of each whole; nulls are empty."""
    held, size = [], 0
    for v in texts:
        held.append(v.as_py() or "")
        size += len(held[-1])
        if size >= GROUP:
            yield held
            held, size = [], 0
    yield held


FIELDS = {
    "token_ids": (pa.list_(pa.int32()), T.ArrayType(T.IntegerType())),
    "n_tokens": (pa.int64(), T.LongType()),
    "ids_sha256": (pa.string(), T.StringType()),
    "decoded_text": (pa.string(), T.StringType()),
    "decoded_sha256": (pa.string(), T.StringType()),
}


def encode_documents(docs: DataFrame, vocab_path: str, pattern: str, outputs: list[str], text_col: str = "text", carry: list[str] = ("doc_id",)) -> DataFrame:
    """Encode (and decode again) every text; `outputs` picks from FIELDS. One narrow pass, no shuffle.

    Each worker builds its tables from `vocab_path`, a bounded file that every node has.
    """
    ship_package(docs.sparkSession)
    carry = list(carry)
    schema = T.StructType([docs.schema[c] for c in carry] + [T.StructField(o, FIELDS[o][1]) for o in outputs])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = live(vocab_path, pattern)
        need_raw = "decoded_text" in outputs or "decoded_sha256" in outputs
        try:
            for batch in batches:
                cols = {o: [] for o in outputs}
                for texts in _groups(batch.column(len(carry))):
                    at, ids = bpe.encode_all(texts)
                    spans = list(zip(at[:-1].tolist(), at[1:].tolist(), strict=True))
                    raw_at, raw = bpe.decode_all(ids) if need_raw else (at, b"")
                    cut = list(zip(raw_at[at[:-1]].tolist(), raw_at[at[1:]].tolist(), strict=True)) if need_raw else []
                    for o, c in cols.items():
                        if o == "token_ids":
                            c += [ids[i:j] for i, j in spans]
                        elif o == "n_tokens":
                            c += np.diff(at).tolist()
                        elif o == "ids_sha256":
                            name_at, names = bpe.names_all(ids)
                            c += [hashlib.sha256(names[i + 1 : j]).hexdigest() for i, j in zip(name_at[at[:-1]].tolist(), name_at[at[1:]].tolist(), strict=True)]
                        elif o == "decoded_text":
                            c += [str(raw[i:j], "utf-8", "replace") for i, j in cut]
                        else:
                            c += [hashlib.sha256(raw[i:j]).hexdigest() for i, j in cut]
                yield pa.RecordBatch.from_arrays([batch.column(i) for i in range(len(carry))] + [pa.array(cols[o], FIELDS[o][0]) for o in outputs], names=carry + outputs)
        finally:
            bpe.forget()

    return docs.select(*carry, docs[text_col].alias("_bpe_text")).mapInArrow(run, schema)


def op6_byte_bpe(spark, sf_dir: str) -> DataFrame:
    """Every whole document through the public 50k byte-level vocabulary and back."""
    import public_tokenizers as P

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return encode_documents(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, ["n_tokens", "ids_sha256", "decoded_sha256"])
