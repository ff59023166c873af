"""SentencePiece encoding and decoding with a batched Viterbi search in numpy.

Words of equal length, or long ones of nearly equal length, advance together, one end position at a
time: hashes of all substrings that end there, from running prefix hashes, are looked up among the sorted keys of the pieces, and the
best predecessor of each word is stored as a backpointer.

What is best depends on the model.  A unigram model's search takes the largest sum of scores.  A
merge model (BPE) has no such sum, but of the pieces that can end a prefix exactly one continues the
prefix's own encoding: the one whose merges with the piece before it would end in just these two.
The search then takes the longest piece that passes this test, with the same tables and
backpointers, and gives the ids that the merges give.

Characters without a piece become bytes where the model has them, else the unknown id.  Null and
empty texts have no ids.  Only words seen for the first time by a worker are searched.
"""

from __future__ import annotations

import re
import struct
from array import array
from collections.abc import Iterator
from functools import lru_cache
from math import inf

import numpy as np

SPACE = "▁"
UNIGRAM, MERGES = 1, 2
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
_P = 0x9E3779B97F4A7C15
MOST_WORDS = 400_000
MOST_PAIRS = 1_500_000
#: Characters, padding included, of the words that are searched together.
BATCH_CHARACTERS = 1 << 19
#: Positions whose matches are held at once.
WINDOW = 1 << 15
#: Longer words are not remembered.
LONGEST_KNOWN = 48


def _fields(data: bytes) -> Iterator[tuple[int, object]]:
    """Numbers and values of a serialized protocol buffer message."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        elif kind == 2:
            n = varint()
            yield key >> 3, data[at : at + n]
            at += n
        else:
            n = 8 if kind == 1 else 4
            yield key >> 3, data[at : at + n]
            at += n


class Pieces:
    def __init__(self, path: str):
        with open(path, "rb") as f:
            message = f.read()
        self.text: list[str] = []
        self.scores, kinds, trainer, cleaning = [], [], {}, {}
        for number, value in _fields(message):
            if number == 1:
                piece = dict(_fields(value))
                self.text.append(piece[1].decode())
                self.scores.append(struct.unpack("<f", piece.get(2, b"\0" * 4))[0])
                kinds.append(piece.get(3, NORMAL))
            elif number == 2:
                trainer = dict(_fields(value))
            elif number == 3:
                cleaning = dict(_fields(value))
        self.kind = trainer.get(3, UNIGRAM)
        if self.kind not in (UNIGRAM, MERGES):
            raise ValueError("only unigram and merge models have a search")
        self.prefix, self.squeeze = bool(cleaning.get(3, 1)), bool(cleaning.get(4, 1))
        self.library = None
        if cleaning.get(2) or self.squeeze or not cleaning.get(5, 1) or trainer.get(24):
            import sentencepiece

            self.library = sentencepiece.SentencePieceProcessor(model_file=path)
        self.unknown = kinds.index(UNKNOWN)
        self.bytes = {int(self.text[k][3:5], 16): k for k, x in enumerate(kinds) if x == BYTE}
        self.byte_of = {k: b for b, k in self.bytes.items()}
        self.control = {k for k, x in enumerate(kinds) if x == CONTROL}
        self.special = np.array([k in self.byte_of or k in self.control or k == self.unknown for k in range(len(kinds))])
        self.id = {self.text[k]: k for k, x in enumerate(kinds) if x in (NORMAL, USER)}
        self.longest = max(map(len, self.id), default=1)
        least = min((self.scores[k] for k in self.id.values()), default=0.0)
        self.unknown_score = np.float32(least - 10)
        self.score = np.array([*self.scores, self.unknown_score], np.float32)  # the last: a character without a piece
        self.none = len(self.text)
        self.powers = [pow(_P, k, 1 << 64) for k in range(self.longest + 1)]
        if self.kind == MERGES:
            made = {k for t, k in self.id.items() if len(t) == 1 or self.merge(t) == [k]}
            self.usable = np.array([k in made for k in range(self.none)] + [True])
        else:
            self.usable = np.ones(self.none + 1, bool)
        inner = any(SPACE in t.lstrip(SPACE) for t in self.id)
        alone = "".join(re.escape(c) for c in map(chr, range(33)) if not any(c in t for t in self.id if len(t) > 1))
        self.cut = None if inner else re.compile(f"[{alone}]|{SPACE}*[^{SPACE}{alone}]+|{SPACE}+") if alone else re.compile(f"{SPACE}*[^{SPACE}]+|{SPACE}+")
        self._hash_pieces()
        self.pairs = np.empty(0, np.int64)
        self.pair_fits = np.empty(0, bool)
        self.pair_known: dict[int, bool] = {}
        self.merge_at = 4096
        self.known: dict[str, bytes] = {}

    # --- tables

    def _hash_pieces(self) -> None:
        """Sorted keys of all beginnings of pieces, with the piece that each is, or -1."""
        found: dict[int, int] = {}
        starts: dict[int, str] = {}
        for t, k in self.id.items():
            h = 0
            for n, c in enumerate(t, 1):
                h = (h * _P + self._value(ord(c))) & (1 << 64) - 1
                if starts.setdefault(h, t[:n]) != t[:n]:
                    raise ValueError("two beginnings have one key")
                found.setdefault(h, -1)
            found[h] = k
        keys = np.array(list(found), np.uint64)
        order = np.argsort(keys)
        self.keys, self.ids = keys[order], np.array(list(found.values()), np.int32)[order]

    @staticmethod
    def _value(code):
        """A 64-bit value for a code point, of ints and arrays alike."""
        if isinstance(code, int):
            x = code * 0xD6E8FEB86659FD93 & (1 << 64) - 1
            return (x ^ x >> 32) * 0xA0761D6478BD642F & (1 << 64) - 1
        x = code.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
        return (x ^ (x >> np.uint64(32))) * np.uint64(0xA0761D6478BD642F)

    def merge(self, text: str, border: int = 0) -> list[int]:
        """Ids by merging the best-scored neighbours first, the leftmost of equals; for short strings.

        With ``border``, a place in the text, no ids are given (an empty list) once two parts merge across it.
        """
        parts, of, scores = list(text), self.id.get, self.scores
        ends = list(range(1, len(parts)))  # where each part but the last ends
        costs = [inf if (k := of(p + q)) is None else -scores[k] for p, q in zip(parts, parts[1:])]
        while costs and (least := min(costs)) != inf:
            k = costs.index(least)
            if ends[k] == border:
                return []
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
            del costs[k], ends[k]
            for j in (k - 1, k):
                if 0 <= j < len(costs):
                    costs[j] = inf if (m := of(parts[j] + parts[j + 1])) is None else -scores[m]
        return [of(p, self.none) for p in parts]

    def _fit(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Whether each pair of pieces is its own encoding."""
        key = left * (self.none + 1) + right
        at = np.searchsorted(self.pairs, key)
        known = self.pairs[np.minimum(at, len(self.pairs) - 1)] == key if len(self.pairs) else np.zeros(len(key), bool)
        out = np.zeros(len(key), bool)
        out[known] = self.pair_fits[at[known]]
        todo = np.flatnonzero(~known)
        if len(todo):
            wanted, back = np.unique(key[todo], return_inverse=True)
            out[todo] = np.array([self._fits(*divmod(k, self.none + 1)) for k in wanted.tolist()])[back]
            if len(self.pair_known) > self.merge_at:  # what is in the dictionary goes to the sorted arrays now and then
                both = np.array(list(self.pair_known.items()), np.int64)
                order = np.argsort(both[:, 0])
                self.pairs, self.pair_fits, self.merge_at = both[order, 0], both[order, 1].astype(bool), 2 * len(both)
        return out

    def _pair(self, key: int) -> bool:
        a, b = divmod(key, self.none + 1)
        both = self.text[a] + self.text[b]
        return both not in self.id and self.merge(both, len(self.text[a])) == [a, b]  # what is a piece would be merged

    # --- search

    def _matches(self, prefix: np.ndarray, low: int, high: int) -> np.ndarray:
        """The piece of each (length, start, word), or -1, for starts from ``low`` to ``high``; only what is the beginning of a piece is made longer."""
        n, n_words = len(prefix) - 1, prefix.shape[1]
        match = np.full((min(self.longest, n - low) + 1, high - low, n_words), -1, np.int32)
        start, word = (x.reshape(-1) for x in np.indices((high - low, n_words), np.int32))
        start = start + low
        for size in range(1, len(match)):
            inside = start + size <= n
            start, word = start[inside], word[inside]
            h = prefix[start + size, word] - prefix[start, word] * np.uint64(self.powers[size])
            at = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            hit = self.keys[at] == h
            start, word, at = start[hit], word[hit], at[hit]
            match[size, start - low, word] = self.ids[at]
        match[1][match[1] < 0] = self.none
        return match

    def search(self, words: list[str]) -> list[list[int]]:
        """Piece ids (``none`` for a character without one) of words, which advance together; shorter ones stop at their ends."""
        n_words, n = len(words), max(map(len, words))
        lens = np.array([len(w) for w in words])
        codes = np.frombuffer("".join(w.ljust(n, "\0") for w in words).encode("utf-32-le", "surrogatepass"), "<u4").reshape(n_words, n)
        values = self._value(codes)
        prefix = np.zeros((n + 1, n_words), np.uint64)
        for k in range(n):
            prefix[k + 1] = prefix[k] * np.uint64(_P) + values[:, k]
        best = np.full((n + 1, n_words), -np.inf, np.float32)
        best[0] = 0
        back = np.zeros((n + 1, n_words), np.int64)
        last = np.full((n + 1, n_words), self.none, np.int64)
        even = (lens == n).all()
        for begin in range(0, n, WINDOW):
            low, high = max(0, begin - self.longest), min(n, begin + WINDOW)
            match = self._matches(prefix, low, high)
            some = (match >= 0).any(2)
            for e in range(begin + 1, high + 1):
                open_ = np.ones(n_words, bool) if even else lens >= e
                for size in range(min(self.longest, e, len(match) - 1), 0, -1):
                    s = e - size
                    if not some[size, s - low]:
                        continue
                    piece = match[size, s - low]
                    rows = np.flatnonzero((piece >= 0) & open_)
                    rows = rows[self.usable[piece[rows]]]
                    if self.kind == UNIGRAM:
                        total = best[s][rows] + self.score[piece[rows]]
                        better = total > best[e][rows]
                        rows = rows[better]
                        best[e][rows] = total[better]
                    else:
                        if s:
                            rows = rows[self._fit(last[s][rows], piece[rows].astype(np.int64))]
                        open_[rows] = False
                    back[e][rows] = s
                    last[e][rows] = piece[rows]
        out: list[list[int]] = [[] for _ in words]
        where = lens.copy()
        rows = np.arange(n_words)
        while len(rows):
            for r, p in zip(rows.tolist(), last[where[rows], rows].tolist(), strict=True):
                out[r].append(p)
            where[rows] = back[where[rows], rows]
            rows = rows[where[rows] > 0]
        return [x[::-1] for x in out]

    def _fits(self, a: int, b: int) -> bool:
        if self.none in (a, b):
            return True
        key = a * (self.none + 1) + b
        if key not in self.pair_known:
            if len(self.pair_known) > MOST_PAIRS:
                self.pair_known.clear()
                self.pairs, self.pair_fits, self.merge_at = self.pairs[:0], self.pair_fits[:0], 4096
            self.pair_known[key] = self._pair(key)
        return self.pair_known[key]

    # --- texts

    def normalized(self, text: str) -> str:
        if self.library is not None:
            return self.library.normalize(text)
        return (SPACE if self.prefix else "") + text.replace(" ", SPACE)

    def _with_bytes(self, word: str, pieces: list[int]) -> bytes:
        """Final ids; what has no piece becomes bytes or, once for a run, the unknown id."""
        if self.none not in pieces:
            return array("I", pieces).tobytes()
        out, at = [], 0
        for p in pieces:
            n = len(self.text[p]) if p != self.none else 1
            if p != self.none:
                out.append(p)
            elif self.bytes:
                out += [self.bytes[b] for b in word[at : at + 1].encode("utf-8", "surrogatepass")]
            elif not out or out[-1] != self.unknown:
                out.append(self.unknown)
            at += n
        return array("I", out).tobytes()

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        cut = []
        for t in texts:
            s = self.normalized(t) if t else ""
            cut.append(self.cut.findall(s) if self.cut and s else [s] if s else [])
        if len(self.known) > MOST_WORDS:
            self.known.clear()
        new = set().union(*cut).difference(self.known)
        found = {}
        for some in self._batches(new):
            found |= {w: self._with_bytes(w, p) for w, p in zip(some, self.search(some), strict=True)}
        self.known.update(found)
        out = [b"".join(map(self.known.__getitem__, words)) for words in cut]
        for w in found:
            if len(w) > LONGEST_KNOWN:
                del self.known[w]
        return out

    @staticmethod
    def _batches(words: set[str]) -> Iterator[list[str]]:
        """Words of one length, or of nearly one if they are long, as many as BATCH_CHARACTERS hold."""
        some: list[str] = []
        for w in sorted(words, key=len):
            if some and (len(w) * (len(some) + 1) > BATCH_CHARACTERS or len(w) > max(len(some[0]), len(some[0]) * 5 // 4 if len(some[0]) > 24 else 0)):
                yield some
                some = []
            some.append(w)
        if some:
            yield some

    def decode(self, ids: np.ndarray) -> str:
        out, pending, at = [], bytearray(), 0
        for special in [*np.flatnonzero(self.special[ids]).tolist(), len(ids)]:
            if special > at:
                if pending:
                    out.append(pending.decode("utf-8", "replace"))
                    pending.clear()
                out += map(self.text.__getitem__, ids[at:special].tolist())
            at = special + 1
            if special == len(ids):
                break
            k = int(ids[special])
            if k in self.byte_of:
                pending.append(self.byte_of[k])
                continue
            if pending:
                out.append(pending.decode("utf-8", "replace"))
                pending.clear()
            if k not in self.control:
                out.append(" ⁇ ")
        if pending:
            out.append(pending.decode("utf-8", "replace"))
        text = "".join(out)
        return (text[1:] if self.prefix and text.startswith(SPACE) else text).replace(SPACE, " ")


@lru_cache(maxsize=2)
def pieces(path: str) -> Pieces:
    """One for each worker process and model."""
    return Pieces(path)


def encode(docs, model: str, id_col: str = "doc_id", text_col: str = "text"):
    """doc_id and ids (array of int) of every row."""
    from .common import with_columns_of_text

    def make():
        import pyarrow as pa

        from allpairs.llm.pieces import pieces as shared

        own = shared(model)

        def columns_of(texts):
            ids = own.encode(texts)
            flat = np.frombuffer(b"".join(ids), "<i4")
            return [pa.ListArray.from_arrays(pa.array(np.cumsum([0, *(len(x) // 4 for x in ids)], dtype=np.int32)), pa.array(flat))]

        return columns_of

    return with_columns_of_text(docs.select(docs[id_col].alias("doc_id"), docs[text_col].alias("text")), "text", "ids array<int>", make).drop("text")


def decode(encoded, model: str, ids_col: str = "ids"):
    """All columns, and decoded: the text of the ids."""
    from pyspark.sql.types import StringType, StructType

    from .common import ship

    ship(encoded.sparkSession)
    at = encoded.columns.index(ids_col)
    schema = StructType([*encoded.schema.fields]).add("decoded", StringType())

    def run(batches):
        import pyarrow as pa

        from allpairs.llm.pieces import pieces as shared

        own = shared(model)
        for batch in batches:
            texts = [None if not x.is_valid else own.decode(np.asarray(x.values)) for x in batch.column(at)]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string())], [f.name for f in schema])

    return encoded.mapInArrow(run, schema)


def round_trips(docs, model: str, id_col: str = "doc_id", text_col: str = "text"):
    """doc_id, n_tokens, ids_crc32 and exact (decoding gives the text again), with ids and texts leaving no worker."""
    import zlib

    from .common import with_columns_of_text

    def make():
        import pyarrow as pa

        from allpairs.llm.pieces import pieces as shared

        own = shared(model)

        def columns_of(texts):
            ids = own.encode(texts)
            exact = [own.decode(np.frombuffer(x, "<u4")) == (t or "") for x, t in zip(ids, texts, strict=True)]
            return [pa.array([len(x) // 4 for x in ids], pa.int64()), pa.array([zlib.crc32(x) for x in ids], pa.int64()), pa.array(exact)]

        return columns_of

    return with_columns_of_text(docs.select(docs[id_col].alias("doc_id"), docs[text_col].alias("text")), "text", "n_tokens long, ids_crc32 long, exact boolean", make).drop("text")
