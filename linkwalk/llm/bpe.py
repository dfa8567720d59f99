"""Byte-level BPE: vectorised pre-tokenisation, cached pair merging, decoding by offsets.

Pre-tokenisation works on arrays of code-point classes (letter, number, white space, other). Where a token may start depends
on neighbouring classes, and on whether the place lies inside a contraction such as ``'ll``; the latter is a small automaton
whose transition functions are composed by an associative scan. No regular expression is run.
"""

from __future__ import annotations

import base64
import hashlib
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import names_out
from .words import kept_by_worker

OTHER, LETTER, NUMBER, SPACE = range(4)
#: Code points of the White_Space property.
WHITE = [*range(0x09, 0x0E), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]


def classes() -> np.ndarray:
    return kept_by_worker("classes", _classes)


def _classes() -> np.ndarray:
    out = np.zeros(0x110000, np.uint8)
    kind = {"L": LETTER, "N": NUMBER}
    for at in range(0x110000):
        out[at] = kind.get(unicodedata.category(chr(at))[0], OTHER)
    out[WHITE] = SPACE
    return out


def _compose() -> np.ndarray:
    return kept_by_worker("compose", _composed)


def _composed() -> np.ndarray:
    """``table[f, g]``: first f, then g, for functions of three states packed in six bits."""
    f = np.arange(64)
    parts = np.stack([f & 3, f >> 2 & 3, f >> 4 & 3], 1)
    then = parts[:, np.minimum(parts, 2)]  # then[g, f, s] = g(f(s))
    packed = then[..., 0] | then[..., 1] << 2 | then[..., 2] << 4
    return packed.T.astype(np.uint8)


def scan(codes: np.ndarray, width: int = 256) -> np.ndarray:
    """State before each place, from state 0 on: prefix composition inside rows of ``width``, then over the rows."""
    table, n = _compose(), len(codes)
    rows = -(-n // width) or 1
    grid = np.full(rows * width, 36, np.uint8)  # 36 is the identity: 0, 1, 2
    grid[:n] = codes
    grid = np.ascontiguousarray(grid.reshape(rows, width).T)
    for j in range(1, width):
        grid[j] = table[grid[j - 1], grid[j]]
    before = np.zeros(rows, np.uint8)
    state = 0
    for i, f in enumerate(grid[-1].tolist()):
        before[i] = state
        state = f >> (2 * state) & 3
    after = (grid >> (2 * before)[None, :]) & 3
    flat = after.T.ravel()[:n]
    out = np.zeros(n, np.uint8)
    out[1:] = flat[:-1]
    return out


def token_starts(points: np.ndarray, firsts: np.ndarray) -> np.ndarray:
    """Sorted places where a pre-token starts; ``firsts`` are the places where documents start."""
    n = len(points)
    kind = classes()[points]
    head = np.zeros(n + 1, bool)
    head[firsts] = True
    head[n] = True
    gap = kind == SPACE
    blank = points == 0x20
    ahead = lambda a, k=1: np.concatenate([a[k:], np.zeros(k, a.dtype)])
    back = lambda a: np.concatenate([np.zeros(1, a.dtype), a[:-1]])
    last = head[1:]  # last place of a document
    joined = blank & ~ahead(gap) & ~last  # a blank that the next token takes along
    fresh = head[:n]
    # Contractions: an apostrophe that starts a token, before s, t, m, d or re, ve, ll.
    quote = np.flatnonzero(points == 0x27)
    codes = np.full(n, 16, np.uint8)  # states 0, 1, 2 go to 0, 0, 1: plain text and the rest of a contraction
    if len(quote):
        prior = np.maximum(quote - 1, 0)
        opens = fresh[quote] | ((kind[prior] != OTHER) & ~joined[prior])
        quote = quote[opens]
        pad = np.concatenate([points, np.zeros(2, points.dtype)])
        stop = np.concatenate([head, np.ones(2, bool)])
        one, two = pad[quote + 1], pad[quote + 2]
        in1, in2 = ~stop[quote + 1], ~stop[quote + 1] & ~stop[quote + 2]
        short = in1 & np.isin(one, [ord(c) for c in "stmd"])
        long_ = in2 & (((one == ord("r")) & (two == ord("e"))) | ((one == ord("v")) & (two == ord("e"))) | ((one == ord("l")) & (two == ord("l"))))
        codes[quote[short]] = 1 | 16  # state 0 goes to 1: one place more belongs here
        codes[quote[long_]] = 2 | 16
    inside = scan(codes) > 0
    ended = np.zeros(n, bool)
    ended[1:] = inside[:-1] & ~inside[1:]
    new = (kind != back(kind)) | ended | fresh
    before = back(joined)
    before[fresh] = False
    starts = np.where(gap, new | (~ahead(gap) & ~last), new & ~before) & ~inside
    return np.flatnonzero(starts | fresh)


class Vocabulary:
    """Ranks of a public vocabulary file, with a table of the pairs that merge."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.bytes = {i: t for t, i in self.ranks.items()}
        self.single = np.array([self.ranks[bytes([i])] for i in range(256)], np.int64)
        pairs = {}
        for token, rank in self.ranks.items():
            for k in range(1, len(token)):
                a, b = self.ranks.get(token[:k]), self.ranks.get(token[k:])
                if a is not None and b is not None:
                    pairs[a << 20 | b] = rank
        self.bits = 21
        size = 1 << self.bits
        self.keys, self.values = np.full(size, -1, np.int64), np.full(size, 1 << 40, np.int64)
        left = np.array(list(pairs), np.int64)
        rank = np.array(list(pairs.values()), np.int64)
        slot = self._slot(left)
        while len(left):  # each round settles one key for each free slot; the rest move on by one
            free = self.keys[slot] == -1
            at, which = np.unique(slot[free], return_index=True)
            chosen = np.flatnonzero(free)[which]
            self.keys[at], self.values[at] = left[chosen], rank[chosen]
            rest = np.ones(len(left), bool)
            rest[chosen] = False
            left, rank, slot = left[rest], rank[rest], (slot[rest] + 1) & (size - 1)
        self.steps = 1
        while True:
            all_keys = np.array(list(pairs), np.int64)
            if (self.rank(all_keys) < 1 << 40).all():
                break
            self.steps += 1

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def rank(self, key: np.ndarray) -> np.ndarray:
        """Rank of each pair ``a << 20 | b``; 2**40 where it does not merge."""
        shape, key = key.shape, key.ravel()
        slot = self._slot(key)
        held = self.keys[slot]
        out = np.where(held == key, self.values[slot], 1 << 40)
        # Only keys whose slot another key took go on to the next slot.
        todo = np.flatnonzero((held != key) & (held != -1))
        for _ in range(1, self.steps):
            if not len(todo):
                break
            slot = (slot + 1) & (len(self.keys) - 1)
            held = self.keys[slot[todo]]
            found = held == key[todo]
            out[todo[found]] = self.values[slot[todo[found]]]
            todo = todo[~found & (held != -1)]
        return out.reshape(shape)

    def merge(self, pieces: list[bytes]) -> list[list[int]]:
        """Token ids of each piece: in every round each piece merges its leftmost pair of least rank."""
        out: list[list[int]] = [[] for _ in pieces]
        todo = [i for i, p in enumerate(pieces) if p]
        for i in list(todo):
            if (whole := self.ranks.get(pieces[i])) is not None:
                out[i] = [whole]
        todo = [i for i in todo if not out[i]]
        long_ = [i for i in todo if len(pieces[i]) > 400]
        for i in long_:
            out[i] = self._merge_long(pieces[i])
        todo = sorted((i for i in todo if not out[i]), key=lambda i: len(pieces[i]))
        for lo in range(0, len(todo), 8192):
            some = todo[lo : lo + 8192]
            n = np.array([len(pieces[i]) for i in some])
            w = int(n.max())
            ids = np.full((len(some), w), -1, np.int64)
            ids[np.arange(w)[None, :] < n[:, None]] = self.single[np.frombuffer(b"".join(pieces[i] for i in some), np.uint8)]
            live = np.arange(len(some))
            done: dict[int, list[int]] = {}
            while len(live):
                key = ids[:, :-1] << 20 | ids[:, 1:]
                rank = np.where(ids[:, 1:] >= 0, self.rank(np.maximum(key, 0)), 1 << 40) if w > 1 else np.full((len(live), 1), 1 << 40)
                at = rank.argmin(axis=1)
                best = rank[np.arange(len(live)), at]
                still = best < 1 << 40
                for j in np.flatnonzero(~still):
                    row = ids[j]
                    done[int(live[j])] = row[row >= 0].tolist()
                live, ids, at, best = live[still], ids[still], at[still], best[still]
                if not len(live):
                    break
                cols = np.arange(w)[None, :]
                src = np.minimum(cols + (cols > at[:, None]), w - 1)
                ids = np.where((cols == w - 1) & (cols + (cols > at[:, None]) > w - 1), -1, np.take_along_axis(ids, src, 1))
                ids[np.arange(len(live)), at] = best
            for j, i in enumerate(some):
                out[i] = done[j]
        return out

    def _merge_long(self, piece: bytes) -> list[int]:
        """One piece by a heap over a linked list: time n log n however long the piece is."""
        import heapq

        ids = self.single[np.frombuffer(piece, np.uint8)].tolist()
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        rank = self.rank(np.array(ids[:-1], np.int64) << 20 | np.array(ids[1:], np.int64)).tolist()
        heap = [(r, i, ids[i], ids[i + 1]) for i, r in enumerate(rank) if r < 1 << 40]
        heapq.heapify(heap)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = after[i] if ids[i] >= 0 else n
            if ids[i] != a or j >= n or ids[j] != b:
                continue
            ids[i], ids[j] = r, -1
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y < n:
                    q = int(self.rank(np.array([ids[x] << 20 | ids[y]]))[0])
                    if q < 1 << 40:
                        heapq.heappush(heap, (q, x, ids[x], ids[y]))
        return [x for x in ids if x >= 0]


class Encoder:
    """Encodes texts; remembers up to ``room`` pieces."""

    def __init__(self, path: str, room: int = 400_000):
        self.vocabulary, self.room = Vocabulary(path), room
        self.known: dict[bytes, tuple[bytes, bytes]] = {}

    def pieces(self, texts: list[str]) -> tuple[list[bytes], np.ndarray]:
        """Pre-tokens as UTF-8 slices, and the number of pre-tokens before each text."""
        whole = "".join(texts)
        points = np.frombuffer(whole.encode("utf-32-le"), np.uint32)
        bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts])]).astype(np.int64)
        if not len(points):
            return [], np.zeros(len(bounds), np.int64)
        firsts = np.unique(bounds[:-1][np.diff(bounds) > 0])
        starts = token_starts(points, firsts)
        size = (1 + (points > 0x7F).astype(np.int64) + (points > 0x7FF) + (points > 0xFFFF)).cumsum()
        at = np.append(np.where(starts > 0, size[starts - 1], 0), size[-1]).tolist()
        raw = whole.encode()
        return [raw[a:b] for a, b in zip(at, at[1:], strict=False)], np.searchsorted(starts, bounds)

    def encode(self, texts: list[str]):
        """For each text: its ids as decimal text with a comma after each, and the bytes that the ids decode to."""
        pieces, where = self.pieces(texts)
        known = self.known
        fresh = list({p for p in pieces if p not in known})
        if len(known) + len(fresh) > self.room:
            known.clear()
            fresh = list(set(pieces))
        for piece, ids in zip(fresh, self.vocabulary.merge(fresh), strict=True):
            known[piece] = ("".join(f"{i}," for i in ids).encode(), b"".join(map(self.vocabulary.bytes.__getitem__, ids)))
        got = list(map(known.__getitem__, pieces))
        for a, b in zip(where.tolist(), where[1:].tolist(), strict=False):
            part = got[a:b]
            yield b"".join([x[0] for x in part]), b"".join([x[1] for x in part])

    def ids(self, text: str) -> list[int]:
        return [int(x) for x in next(iter(self.encode([text])))[0].split(b",")[:-1]]

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.vocabulary.bytes.__getitem__, ids)).decode(errors="replace")

    def offsets(self, ids: list[int]) -> list[int]:
        """Byte offset of each token in the decoded bytes."""
        return np.cumsum([0, *(len(self.vocabulary.bytes[i]) for i in ids)])[:-1].tolist()


def groups(texts: list[str], limit: int = 1 << 20):
    """Slices of about ``limit`` characters."""
    held, size = [], 0
    for t in texts:
        held.append(t)
        size += len(t)
        if size >= limit:
            yield held
            held, size = [], 0
    if held:
        yield held


def encode_documents(docs: DataFrame, vocabulary: str, text_col: str = "text", with_ids: bool = True) -> DataFrame:
    """Input columns plus ``n_tokens``, ``ids_sha256``, ``decoded_sha256`` and, if asked, ``ids`` (array of int).

    ``vocabulary`` is the path of a rank file that every executor can read. Null counts as empty and has no token. Rows are
    handled one by one, so null ids, repeated rows and empty tables need no rule; input columns with the name of an added one
    come back with ``_in`` appended.
    """
    given = docs.columns
    own = docs.select(*[F.col(f"`{c}`").alias(f"in_{i}") for i, c in enumerate(given)])
    text_at = given.index(text_col)
    send = own if with_ids else own.select(*[c for c in own.columns if c != f"in_{text_at}"], f"in_{text_at}")
    names = [c for c in send.columns if with_ids or c != f"in_{text_at}"]
    where = send.columns.index(f"in_{text_at}")

    def run(batches):
        encoder = kept_by_worker(f"encoder:{vocabulary}", lambda: Encoder(vocabulary))
        for batch in batches:
            texts = [t or "" for t in batch.column(where).to_pylist()]
            n, ids, a, b = [], [], [], []
            for part in groups(texts):
                for listed, decoded in encoder.encode(part):
                    n.append(listed.count(b","))
                    a.append(hashlib.sha256(listed[:-1]).hexdigest())
                    b.append(hashlib.sha256(decoded).hexdigest())
                    if with_ids:
                        ids.append([int(x) for x in listed.split(b",")[:-1]])
            made = [pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())] + ([pa.array(ids, pa.list_(pa.int32()))] if with_ids else [])
            columns = [c for c, name in zip(batch.columns, batch.schema.names, strict=True) if name in names]
            yield pa.RecordBatch.from_arrays(columns + made, names=names + ["n_tokens", "ids_sha256", "decoded_sha256", "ids"][: len(made)])

    kinds = ", ".join(f"{c} {t}" for c, t in send.dtypes if c in names)
    out = send.mapInArrow(run, f"{kinds}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids)
    keep = [F.col(f"in_{i}").alias(c) for i, c in enumerate(names_out(given, ["n_tokens", "ids_sha256", "decoded_sha256", "ids"])) if f"in_{i}" in names]
    return out.select(*keep, "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids)
