"""A linear-chain conditional random field over the leaf blocks of a page: main text or not.

Features of a block are its ancestors' tags and the words of their classes and
ids, and shapes of its text.  Training maximises the conditional likelihood of
labelled pages by stochastic gradients from forward-backward sums; decoding is
Viterbi.  The weights are plain numbers in ``html_crf.json``.
"""

from __future__ import annotations

import json
import math
import random
from pathlib import Path

from litspark.llm.html_blocks import Block

FILE = Path(__file__).with_name("html_crf.json")
EPOCHS, RATE, DECAY, SEED = 12, 0.3, 2e-5, 11


def features(blocks: list[Block]) -> list[list[str]]:
    """Names of the features that hold for each block."""
    out = []
    for i, b in enumerate(blocks):
        tags = [t for t, _ in b.path]
        own = ["bias", f"tag={tags[-1] if tags else ''}"]
        own += [f"in={t}" for t in dict.fromkeys(tags)]
        own += [f"name={w}" for w in dict.fromkeys(w for _, words in b.path for w in words)]
        shells = [t for t in tags if t in ("article", "main", "nav", "header", "footer", "aside", "form", "section")]
        own.append(f"shell={shells[-1] if shells else ''}>{tags[-1] if tags else ''}")
        heading = bool(tags) and tags[-1] in ("h1", "h2", "h3", "h4", "h5", "h6")
        if heading and b.title and (b.text == b.title or b.text in b.title):
            own.append("heading=title")
        words = b.text.split(" ")
        own.append(f"words={min(6, int(math.log2(len(words))))}")
        own.append(f"links={min(3, int(4 * b.linked / max(1, len(b.text))))}")
        own.append(f"stops={min(3, sum(w[-1] in '.!?' for w in words))}")
        if any(c in b.text for c in "©®"):
            own.append("mark")
        if "article" in tags or "main" in tags:
            own.append("body=" + (tags[-1] if tags[-1] in ("p", "li", "td", "blockquote", "pre", "article", "main") else "other"))
        if i == 0:
            own.append("first")
        out.append(own)
    return out


class Field:
    """Weights of the field; label 1 is main text."""

    def __init__(self, weights: dict[str, float] | None = None, moves: list[list[float]] | None = None):
        self.weights = weights or {}
        self.moves = moves or [[0.0, 0.0], [0.0, 0.0]]

    def scores(self, names: list[list[str]]) -> list[float]:
        get = self.weights.get
        return [sum(get(f, 0.0) for f in own) for own in names]

    def decode(self, names: list[list[str]]) -> list[int]:
        """The most probable labels (Viterbi); a tie goes to label 0."""
        (a00, a01), (a10, a11) = self.moves
        zero = one = 0.0
        back = []
        for i, s in enumerate(self.scores(names)):
            if not i:
                zero, one = 0.0, s
                continue
            from0, from1 = (0, zero + a00) if zero + a00 >= one + a10 else (1, one + a10), (0, zero + a01) if zero + a01 >= one + a11 else (1, one + a11)
            zero, one = from0[1], from1[1] + s
            back.append((from0[0], from1[0]))
        if not names:
            return []
        label = int(one > zero)
        out = [label]
        for step in reversed(back):
            label = step[label]
            out.append(label)
        return out[::-1]

    def _marginals(self, scores: list[float]) -> tuple[list[float], list[list[list[float]]]]:
        """P(label 1) of each block and the pair probabilities of neighbours."""
        n = len(scores)
        unary = [(0.0, s) for s in scores]
        add = lambda a, b: max(a, b) + math.log1p(math.exp(-abs(a - b)))
        ahead = [list(unary[0])]
        for i in range(1, n):
            ahead.append([add(ahead[-1][0] + self.moves[0][y], ahead[-1][1] + self.moves[1][y]) + unary[i][y] for y in (0, 1)])
        behind = [[0.0, 0.0]]
        for i in range(n - 1, 0, -1):
            behind.append([add(self.moves[y][0] + unary[i][0] + behind[-1][0], self.moves[y][1] + unary[i][1] + behind[-1][1]) for y in (0, 1)])
        behind.reverse()
        whole = add(*ahead[-1])
        single = [math.exp(ahead[i][1] + behind[i][1] - whole) for i in range(n)]
        pairs = [[[math.exp(ahead[i][x] + self.moves[x][y] + unary[i + 1][y] + behind[i + 1][y] - whole) for y in (0, 1)] for x in (0, 1)] for i in range(n - 1)]
        return single, pairs

    def fit(self, pages: list[tuple[list[Block], list[int]]], epochs: int = EPOCHS, rate: float = RATE, decay: float = DECAY, seed: int = SEED) -> "Field":
        """Stochastic gradient ascent with per-weight step sizes on labelled pages."""
        ready = [(features(blocks), labels) for blocks, labels in pages if blocks]
        squares: dict = {}
        rng = random.Random(seed)

        def step(key, holder, at, gradient: float) -> None:
            squares[key] = squares.get(key, 1e-6) + gradient * gradient
            holder[at] = holder.get(at, 0.0) * (1 - decay) + rate * gradient / math.sqrt(squares[key])

        moves = {(x, y): self.moves[x][y] for x in (0, 1) for y in (0, 1)}
        for _ in range(epochs):
            rng.shuffle(ready)
            for names, labels in ready:
                single, pairs = self._marginals(self.scores(names))
                gradient: dict[str, float] = {}
                for own, p, y in zip(names, single, labels):
                    for f in own:
                        gradient[f] = gradient.get(f, 0.0) + y - p
                for f, g in gradient.items():
                    if g:
                        step(f, self.weights, f, g)
                for x in (0, 1):
                    for y in (0, 1):
                        g = sum(float(labels[i] == x and labels[i + 1] == y) - q[x][y] for i, q in enumerate(pairs))
                        if g:
                            step((x, y), moves, (x, y), g)
                self.moves = [[moves[x, y] for y in (0, 1)] for x in (0, 1)]
        return self

    def save(self, path: Path = FILE) -> None:
        kept = {f: round(w, 4) for f, w in sorted(self.weights.items()) if abs(w) >= 0.005}
        path.write_text(json.dumps({"weights": kept, "moves": [[round(v, 4) for v in r] for r in self.moves]}, indent=0, ensure_ascii=False) + "\n")

    @classmethod
    def load(cls, path: Path = FILE) -> "Field":
        held = json.loads(path.read_text())
        return cls(held["weights"], held["moves"])
