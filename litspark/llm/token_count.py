"""Token counts by a compiled finite-state tokenizer.

The tokenizer of a vocabulary is a deterministic transducer over bytes.  Its
state is the set of *open* tokens: for every suffix of the piece read so far
that some token may still extend, the place in the token tree, the token before
it, and how the count there differs from the count here.  A byte moves every
open token one step; exactly one token that closes fits its predecessor (the
pair encodes to itself), which fixes the count of the longer prefix, and the
transition is annotated with the change of the count.  States are compiled when
first reached and kept in a table of bounded size.

A long text is cut into chunks of about ``CHUNK`` bytes, inside a piece where one
is longer than that.  Each chunk becomes a *state map*: from the state in which it
may be entered to the state that it leaves and the tokens that it emits.  At the
start of a piece the state is the first one; inside a long piece it is open, so
the map is made for the states that were seen, which soon run together, and is
extended by a state when that is met.  Maps compose associatively, and a parallel
prefix scan over the chunks gives the state and the count up to every chunk.

Edge cases: null and empty texts have 0 tokens and 0 bytes; special strings in a
text count as one token each; very long texts and pieces are counted whole;
other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from litspark.llm.bpe import Vocabulary, sliced, vocabulary, vocabulary_file
from litspark.llm.common import text_batches

CHUNK = 16_384
#: Compiled transitions and remembered pieces and pairs of one worker; a full table starts anew.
TRANSITIONS = 1_000_000
PIECE_MEMORY = 300_000
#: Bytes after which runs from several states are compared, and states that the map of an open chunk is made for at first.
STRIDE, SEEN = 16, 64
LIMIT = 1024

class Transducer:
    """Counts the tokens of a piece while it reads the bytes."""

    def __init__(self, vocab: Vocabulary, limit: int = TRANSITIONS):
        self.vocab, self.limit = vocab, limit
        words = {i: b for i, b in vocab.bytes_of.items() if i not in set(vocab.special.values())}
        ids = list(words)
        own = [i for i, made in zip(ids, vocab.merge_all([words[i] for i in ids])) if made == [i]]
        self.child: dict[int, int] = {}
        self.token: list[int] = [-1]
        self.inner: list[bool] = [True]
        for i in own:
            node = 0
            for b in words[i]:
                self.inner[node] = True
                step = self.child.get(node << 8 | b)
                if step is None:
                    step = self.child[node << 8 | b] = len(self.token)
                    self.token.append(-1)
                    self.inner.append(False)
                node = step
            self.token[node] = i
        self.fits: dict[tuple[int, int], bool] = {}
        self._restart()

    def _restart(self) -> None:
        start = ((0, -1, 0),)
        self.states = [start]
        self.number = {start: 0}
        self.moves: dict[int, int] = {}

    def _follows(self, before: int, token: int) -> bool:
        """Whether ``token`` may stand after ``before`` in an encoding."""
        if before < 0:
            return True
        known = self.fits.get((before, token))
        if known is None:
            if len(self.fits) >= self.limit:
                self.fits.clear()
            raw = self.vocab.bytes_of
            known = self.fits[before, token] = self.vocab.merge(raw[before] + raw[token]) == [before, token]
        return known

    def _compile(self, state: int, byte: int) -> int:
        """The transition as ``next << 8 | 128 + change of the count``."""
        opened, best = [], None
        for node, before, behind in self.states[state]:
            step = self.child.get(node << 8 | byte)
            if step is None:
                continue
            if best is None and self.token[step] >= 0 and self._follows(before, self.token[step]):
                best = self.token[step], behind + 1
            if self.inner[step]:
                opened.append((step, before, behind))
        last, change = best
        items = (*((node, before, behind - change) for node, before, behind in opened), (0, last, 0))
        number = self.number.get(items)
        if number is None:
            number = self.number[items] = len(self.states)
            self.states.append(items)
        move = self.moves[state << 8 | byte] = number << 8 | (128 + change)
        return move

    def trim(self) -> None:
        """Start the table of transitions anew once it is full; numbers of states that were handed out end there."""
        if len(self.moves) > self.limit:
            self._restart()

    def count(self, raw: bytes) -> int:
        self.trim()
        return self.run(0, raw)[1]

    def run(self, state: int, raw: bytes) -> tuple[int, int]:
        """The state after ``raw`` and the tokens emitted on the way, from ``state``."""
        moves, total = self.moves, 0
        for byte in raw:
            move = moves.get(state << 8 | byte)
            if move is None:
                move = self._compile(state, byte)
            state = move >> 8
            total += (move & 255) - 128
        return state, total

    def run_all(self, states: list[int], raw: bytes) -> dict[int, tuple[int, int]]:
        """``run`` from several states; runs that reach the same state go on as one."""
        groups = {s: [(s, 0)] for s in states}
        for at in range(0, len(raw), STRIDE):
            merged: dict[int, list[tuple[int, int]]] = {}
            for state, members in groups.items():
                end, more = self.run(state, raw[at : at + STRIDE])
                merged.setdefault(end, []).extend((s, n + more) for s, n in members)
            groups = merged
        return {s: (end, n) for end, members in groups.items() for s, n in members}


class ChunkMap:
    """(state left, tokens emitted) for the states in which a chunk may be entered; ``find`` makes the entry of another one."""

    def __init__(self, known: dict[int, tuple[int, int]], find: Callable[[int], tuple[int, int]]):
        self.known, self.find = known, find

    def __call__(self, state: int) -> tuple[int, int]:
        found = self.known.get(state)
        if found is None:
            found = self.known[state] = self.find(state)
        return found


def compose(a: ChunkMap, b: ChunkMap) -> ChunkMap:
    """The map of both chunks read one after the other."""

    def through(state: int) -> tuple[int, int]:
        middle, first = a(state)
        end, more = b(middle)
        return end, first + more

    return ChunkMap({s: through(s) for s in a.known}, through)


class Counter:
    """Counts of pieces, and of long texts by state maps."""

    def __init__(self, vocab: Vocabulary, memory: int = PIECE_MEMORY):
        self.vocab, self.memory = vocab, memory
        self.transducer = Transducer(vocab)
        self.known: dict[str, int] = {}

    def _piece(self, piece: str) -> int:
        n = self.known.get(piece)
        if n is None:
            if len(self.known) >= self.memory:
                self.known.clear()
            n = self.known[piece] = 1 if piece in self.vocab.special else self.transducer.run(0, piece.encode("utf-8", "surrogatepass"))[1]
        return n

    def count(self, text: str) -> int:
        """Tokens of a text, piece by piece."""
        self.transducer.trim()
        pieces = self.vocab.pieces(text)
        try:
            return sum(map(self.known.__getitem__, pieces))
        except KeyError:
            return sum(map(self._piece, pieces))

    def _closed(self, pieces: list[str]) -> ChunkMap:
        """Whole pieces: entered and left in the first state."""
        n = sum(map(self._piece, pieces))
        return ChunkMap({0: (0, n)}, lambda state: (0, n))

    def _open(self, raw: bytes, last: bool) -> ChunkMap:
        """A part of a piece; behind its last one the first state follows."""
        leave = (lambda found: (0, found[1])) if last else (lambda found: found)
        machine = self.transducer
        seen = list(range(max(0, len(machine.states) - SEEN), len(machine.states)))
        return ChunkMap({s: leave(f) for s, f in machine.run_all(sorted({0, *seen}), raw).items()}, lambda state: leave(machine.run(state, raw)))

    def maps(self, text: str, chunk: int) -> list[ChunkMap]:
        """State maps of the chunks of a text, in order."""
        out, held, size = [], [], 0
        self.transducer.trim()  # not later: states keep their numbers while maps refer to them
        for piece in self.vocab.pieces(text):
            if len(piece) > chunk and piece not in self.vocab.special:
                if held:
                    out.append(self._closed(held))
                    held, size = [], 0
                raw = piece.encode("utf-8", "surrogatepass")
                self.transducer.run(0, raw[:chunk])  # states that the parts may be entered in
                out += [self._open(raw[at : at + chunk], at + chunk >= len(raw)) for at in range(0, len(raw), chunk)]
                continue
            held.append(piece)
            size += len(piece)
            if size >= chunk:
                out.append(self._closed(held))
                held, size = [], 0
        return [*out, self._closed(held)] if held else out

    def text(self, text: str, chunk: int = CHUNK) -> int:
        """Tokens of a whole text."""
        if len(text) <= chunk:
            return self.count(text)
        return prefix_scan(self.maps(text, chunk), compose)[-1](0)[1]


def prefix_scan(items: list, compose: Callable) -> list:
    """Inclusive scan by halving: pairs are composed, their scan is scanned, the rest follows from it."""
    if len(items) < 2:
        return list(items)
    pairs = [compose(items[i], items[i + 1]) for i in range(0, len(items) - 1, 2)]
    scanned = prefix_scan(pairs, compose)
    out = [items[0]]
    for i in range(1, len(items)):
        out.append(scanned[i // 2] if i % 2 else compose(scanned[i // 2 - 1], items[i]))
    return out


def _counted(rows: Iterator[pa.RecordBatch], source: str, limit: int) -> Iterator[pa.RecordBatch]:
    counter = Counter(vocabulary(source))
    for batch in sliced(rows):
        counts = [counter.text(t or "") for t in batch.column("text").to_pylist()]
        yield pa.RecordBatch.from_arrays(
            [batch.column("doc_id"), batch.column("n_bytes"), pa.array(counts, pa.int64()), pa.array([c > limit for c in counts], pa.bool_())],
            ["doc_id", "n_bytes", "n_tokens", "over_limit"],
        )


def token_counts(docs: DataFrame, path: str | None = None, limit: int = LIMIT) -> DataFrame:
    """One row per row of ``docs(doc_id, text)``: doc_id, n_bytes, n_tokens, over_limit."""
    text_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(vocabulary_file(path))
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.octet_length(text).cast("long").alias("n_bytes"), text.alias("text"))
    return source.mapInArrow(lambda rows: _counted(rows, shared.value, limit), "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
