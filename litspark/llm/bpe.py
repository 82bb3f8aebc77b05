"""Byte-level BPE: encoding with a segment tree over adjacent pair ranks, and decoding.

A piece (pre-token) is a row of byte symbols.  Leaf i of a segment tree holds
``rank * size + i`` of the pair that starts at symbol i, so the minimum at the
root is the leftmost lowest-rank merge; applying it changes three leaves, each
update climbs the height of the tree, and the piece is done when no mergeable
pair is left.  Short pieces of a batch share one array of trees and merge in
step; a long piece has a tree of its own.  Results of pieces are remembered in
a table of bounded size.

Special strings inside a text become their own id, as the tokenizers library
does by default; texts are never truncated or padded.

Edge cases: a null or empty text has no ids and decodes to the empty text;
other columns are ignored; any row order and repeated rows give the same row
results; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.llm.common import text_batches

#: Pieces remembered by one Python worker; the table starts anew when full.
PIECE_MEMORY = 250_000
#: Rows encoded in one go.
ROWS = 160
NONE = np.int64(2**62)
# The pattern that cuts text into pieces, with white space as Unicode defines it.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"


def _byte_letters() -> dict[str, int]:
    """The letter that stands for each byte in vocabulary files: printable Latin-1 as itself, others from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = [b for b in range(256) if b not in set(own)]
    return {chr(b): b for b in own} | {chr(256 + i): b for i, b in enumerate(others)}


class Vocabulary:
    """Tables of one vocabulary file in the JSON form of the tokenizers library."""

    def __init__(self, source: str):
        spec = json.loads(source)
        letters = _byte_letters()
        ids = spec["model"]["vocab"]
        self.bytes_of: dict[int, bytes] = {i: bytes(letters[c] for c in t) for t, i in ids.items()}
        self.special: dict[str, int] = {t["content"]: t["id"] for t in spec.get("added_tokens", ()) if t["special"]}
        self.bytes_of |= {i: t.encode() for t, i in self.special.items()}
        self.base = np.zeros(256, np.int64)
        for b, i in ((letters[t], i) for t, i in ids.items() if len(t) == 1):
            self.base[b] = i
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.made = np.array([ids[a + b] for a, b in pairs] or [0], np.int64)
        self.rank = {(ids[a] << 20) | ids[b]: r for r, (a, b) in enumerate(pairs)}
        self.keys, self.ranks = np.array(sorted(self.rank) or [-1], np.int64), None
        self.ranks = np.array([self.rank.get(int(k), 0) for k in self.keys], np.int64)
        self._cut = regex.compile(PATTERN)
        self._special = regex.compile("|".join(map(regex.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None

    def pieces(self, text: str) -> list[str]:
        """The pieces of a text in order; a special string is a piece of its own."""
        if not self._special or not any(s in text for s in self.special):
            return self._cut.findall(text)
        out, at = [], 0
        for m in self._special.finditer(text):
            out += self._cut.findall(text[at : m.start()])
            out.append(m.group())
            at = m.end()
        return out + self._cut.findall(text[at:])

    def merge(self, raw: bytes) -> list[int]:
        """Ids of one piece with a tree of its own."""
        n = len(raw)
        if n < 2:
            return [int(self.base[b]) for b in raw]
        rank, made = self.rank, self.made
        size = 1 << (n - 1).bit_length()
        none = 1 << 62
        symbols = [int(self.base[b]) for b in raw]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        tree = [none] * (2 * size)
        for i in range(n - 1):
            r = rank.get(symbols[i] << 20 | symbols[i + 1])
            if r is not None:
                tree[size + i] = r * size + i
        for node in range(size - 1, 0, -1):
            tree[node] = min(tree[2 * node], tree[2 * node + 1])

        def put(i: int, value: int) -> None:
            node = size + i
            tree[node] = value
            while node > 1:
                node >>= 1
                low = min(tree[2 * node], tree[2 * node + 1])
                if tree[node] == low:
                    return
                tree[node] = low

        def value(i: int, j: int) -> int:
            r = rank.get(symbols[i] << 20 | symbols[j])
            return none if r is None else r * size + i

        while tree[1] < none:
            r, i = divmod(tree[1], size)
            gone = after[i]
            symbols[i] = int(made[r])
            symbols[gone] = -1
            after[i] = j = after[gone]
            put(gone, none)
            if j < n:
                before[j] = i
                put(i, value(i, j))
            else:
                put(i, none)
            if before[i] >= 0:
                put(before[i], value(before[i], i))
        return [s for s in symbols if s >= 0]

    def _values(self, left: np.ndarray, right: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
        """Leaf values of pairs; a negative symbol means that there is no pair."""
        key = (left << 20) | right
        spot = np.searchsorted(self.keys, key)
        spot[spot == len(self.keys)] = 0
        return np.where((self.keys[spot] == key) & (left >= 0) & (right >= 0), self.ranks[spot] * size + at, NONE)

    def _merge_alike(self, raws: list[bytes], size: int) -> list[list[int]]:
        """Ids of pieces of at most ``size`` bytes, with one array of trees."""
        count, height = len(raws), size.bit_length() - 1
        lengths = np.fromiter(map(len, raws), np.int64, count)
        flat = np.frombuffer(b"".join(r.ljust(size, b"\0") for r in raws), np.uint8).reshape(count, size)
        places = np.arange(size)
        # one spare column at the end stands for "no neighbour"
        symbols = np.full((count, size + 1), -1, np.int64)
        symbols[:, :size] = np.where(places < lengths[:, None], self.base[flat], -1)
        after = np.minimum(np.tile(places + 1, (count, 1)), lengths[:, None])
        after = np.where(after >= lengths[:, None], size, after)
        before = np.full((count, size + 1), size, np.int64)
        before[:, 1:size] = places[:-1]
        tree = np.full((count, 2 * size), NONE, np.int64)
        tree[:, size : 2 * size - 1] = self._values(symbols[:, : size - 1].ravel(), symbols[:, 1:size].ravel(), np.tile(places[:-1], count), size).reshape(count, size - 1)
        for level in range(height - 1, -1, -1):
            nodes = slice(1 << level, 2 << level)
            children = tree[:, 2 << level : 4 << level]
            tree[:, nodes] = np.minimum(children[:, ::2], children[:, 1::2])

        def put(rows: np.ndarray, at: np.ndarray, values: np.ndarray) -> None:
            node = at + size
            tree[rows, node] = values
            for _ in range(height):
                node = node >> 1
                tree[rows, node] = np.minimum(tree[rows, 2 * node], tree[rows, 2 * node + 1])

        rows = np.arange(count)
        while True:
            root = tree[rows, 1]
            live = root < NONE
            rows, root = rows[live], root[live]
            if not len(rows):
                break
            at = root % size
            gone = after[rows, at]
            made = self.made[root // size]
            symbols[rows, at] = made
            symbols[rows, gone] = -1
            right = after[rows, gone]
            after[rows, at] = right
            before[rows, right] = at
            put(rows, gone, np.full(len(rows), NONE))
            put(rows, at, self._values(made, symbols[rows, right], at, size))
            left = before[rows, at]
            has = left < size
            if has.any():
                r, lo = rows[has], left[has]
                put(r, lo, self._values(symbols[r, lo], made[has], lo, size))
        kept = symbols >= 0
        ends = np.cumsum(kept.sum(axis=1)).tolist()
        ids = symbols[kept].tolist()
        return [ids[a:b] for a, b in zip([0, *ends], ends)]

    def merge_all(self, raws: list[bytes]) -> list[list[int]]:
        """Ids of many pieces."""
        out: list[list[int]] = [[]] * len(raws)
        by: dict[int, list[int]] = {}
        for i, raw in enumerate(raws):
            by.setdefault(max(8, 1 << (len(raw) - 1).bit_length()) if len(raw) > 1 else 1, []).append(i)
        for size, which in by.items():
            if size == 1 or size > 64 or len(which) < 16:
                for i in which:
                    out[i] = self.merge(raws[i])
            else:
                for at in range(0, len(which), 20_000):
                    part = which[at : at + 20_000]
                    for i, ids in zip(part, self._merge_alike([raws[i] for i in part], size)):
                        out[i] = ids
        return out

    def encode_pieces(self, pieces: list[str]) -> list[list[int]]:
        special = self.special
        plain = [p for p in pieces if p not in special]
        done = dict(zip(plain, self.merge_all([p.encode("utf-8", "surrogatepass") for p in plain])))
        return [[special[p]] if p in special else done[p] for p in pieces]

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


_loaded: dict[int, Vocabulary] = {}


def vocabulary(source: str) -> Vocabulary:
    """The tables of a file's content, built once in each process; one is held at a time."""
    key = hash(source)
    if key not in _loaded:
        _loaded.clear()
        _loaded[key] = Vocabulary(source)
    return _loaded[key]


def vocabulary_file(path: str | None = None) -> str:
    """Content of a vocabulary file; by default the public 50k byte-level one."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as file:
        return file.read()


def sliced(rows: Iterator[pa.RecordBatch], size: int = ROWS) -> Iterator[pa.RecordBatch]:
    """Batches of at most ``size`` rows."""
    for batch in rows:
        for at in range(0, batch.num_rows, size):
            yield batch.slice(at, size)


class Encoder:
    """Encodes groups of texts; remembers for each piece its ids (as text) and its decoded bytes."""

    def __init__(self, vocab: Vocabulary, memory: int = PIECE_MEMORY):
        self.vocab, self.memory = vocab, memory
        self.ids: dict[str, str] = {}
        self.raw: dict[str, bytes] = {}

    def group(self, texts: list[str]) -> Iterator[tuple[str, bytes]]:
        """For each text its ids joined by commas and the decoded bytes."""
        cut = [self.vocab.pieces(t) for t in texts]
        wanted = set().union(*cut)
        new = [p for p in wanted if p not in self.ids]
        if len(self.ids) + len(new) > self.memory:
            self.ids.clear()
            self.raw.clear()
            new = list(wanted)
        for piece, ids in zip(new, self.vocab.encode_pieces(new)):
            self.ids[piece] = ",".join(map(str, ids))
            self.raw[piece] = self.vocab.decode(ids)
        for pieces in cut:
            yield ",".join(map(self.ids.__getitem__, pieces)), b"".join(map(self.raw.__getitem__, pieces))


def _encoded(rows: Iterator[pa.RecordBatch], source: str, with_ids: bool) -> Iterator[pa.RecordBatch]:
    encoder = Encoder(vocabulary(source))
    for batch in sliced(rows):
        counts, ids_sha, text_sha, lists = [], [], [], []
        for joined, raw in encoder.group([t or "" for t in batch.column("text").to_pylist()]):
            counts.append(joined.count(",") + 1 if joined else 0)
            ids_sha.append(hashlib.sha256(joined.encode()).hexdigest())
            text_sha.append(hashlib.sha256(raw.decode("utf-8", "replace").encode()).hexdigest())
            if with_ids:
                lists.append(np.array(joined.split(",") if joined else [], np.int32))
        columns = [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(ids_sha), pa.array(text_sha)]
        names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
        if with_ids:
            columns.append(pa.array(lists, pa.list_(pa.int32())))
            names.append("ids")
        yield pa.RecordBatch.from_arrays(columns, names)


def bpe_encode(docs: DataFrame, path: str | None = None, with_ids: bool = True) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_tokens, ids_sha256, decoded_sha256 and the ids."""
    text_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary_file(path))
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return source.mapInArrow(lambda rows: _encoded(rows, shared.value, with_ids), schema)


def bpe_decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """``encoded(doc_id, ids)`` -> doc_id, text; null ids give the empty text, unknown ids raise."""
    shared = encoded.sparkSession.sparkContext.broadcast(vocabulary_file(path))

    def decoded(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(shared.value)
        for batch in rows:
            texts = [vocab.decode(i or ()).decode("utf-8", "replace") for i in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(decoded, "doc_id long, text string")
