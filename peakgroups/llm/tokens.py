"""Token counts by a compiled finite-state tokenizer (operator 7).

A byte-level BPE tokenizer works in two stages, and both are finite-state here.

Where a pre-token starts depends on the classes of two characters before and three after a
place; that automaton is evaluated for all places of a text at once.

Inside a pre-token a deterministic transducer reads one byte a step. Its state is what the
merges can still see: the longest suffix read that begins some token, and for each place in
it the last token of the encoding up to there and how many tokens ago that was. The encoding
of a prefix ends in the one token that stands next to its predecessor unmerged, so state and
byte give the next state and the change of the token count, with which the transition is
annotated (it may be below zero, where a byte joins tokens). Transitions are compiled when
first taken and equal states are one object.

The map of a chunk says what it leaves to its left neighbour (the bytes before its first
pre-token), the tokens that it emits and the state that it ends in. Such maps compose
associatively (:func:`compose`); every text goes through them, in chunks of CHUNK characters
whose maps are combined by the up-sweep of a prefix scan.
"""

from __future__ import annotations

import functools
import json
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Characters of a chunk, and of the places that are classified at once.
CHUNK, BLOCK = 1 << 12, 1 << 20
#: Compiled states, pre-tokens and pairs that a worker keeps; beyond, it starts anew.
MEMO = 400_000
#: Longest pre-token, in characters, that is kept as one transition.
WORD = 64
_BYTES = [bytes([b]) for b in range(256)]
_END = np.uint32(0xFFFFFFFF)
#: Unicode white space: fixed values.
_WHITE = (*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000)
_OTHER, _LETTER, _NUMBER, _WS, _SPACE, _STOP = range(6)


@functools.cache
def _classes() -> np.ndarray:
    kind = {"L": _LETTER, "N": _NUMBER}
    table = np.fromiter((kind.get(unicodedata.category(chr(c))[0], _OTHER) for c in range(0x110000)), np.uint8, 0x110000)
    table[list(_WHITE)] = _WS
    table[32] = _SPACE
    return table


def starts_of(points: np.ndarray) -> np.ndarray:
    """True where a pre-token starts. ``points``: code points, _END where a text ends."""
    stop = points == _END
    kind = _classes()[np.where(stop, 0, points)]
    kind[stop] = _STOP
    before = np.empty_like(kind)
    before[0], before[1:] = _STOP, kind[:-1]
    after = np.empty_like(kind)
    after[-1], after[:-1] = _STOP, kind[1:]
    white, white_before = (kind == _WS) | (kind == _SPACE), (before == _WS) | (before == _SPACE)
    # The last of several white spaces stands for itself or leads the word that follows.
    start = np.where(white, ~white_before | ((after < _WS)), (before != _SPACE) & (before != kind))
    start[stop] = True
    quote = np.flatnonzero((points == 39) & start)
    if len(quote):
        padded = np.concatenate([points, np.full(3, _END)])
        one, two = padded[quote + 1], padded[quote + 2]
        short = np.isin(one, [ord(c) for c in "stmd"])
        long = np.isin(one.astype(np.uint64) << 32 | two, [ord(a) << 32 | ord(b) for a, b in ("re", "ve", "ll")])
        for found, size in ((quote[short], 2), (quote[long], 3)):
            start[found + 1] = False
            ends = found + size
            ends = ends[ends < len(points)]
            start[ends[~white[ends]]] = True
    return start


def all_starts(text: str, ends: np.ndarray) -> np.ndarray:
    """:func:`starts_of` for a text with stops at ``ends``, in blocks that see their surroundings."""
    out = []
    for a in range(0, len(text), BLOCK):
        lead, b = max(0, a - 3), min(a + BLOCK, len(text))
        points = np.frombuffer(text[lead : b + 3].encode("utf-32-le", "surrogatepass"), np.uint32).copy()
        stops = ends[(ends >= lead) & (ends < b + 3)] - lead
        points[stops] = _END
        out.append(starts_of(points)[a - lead : b - lead])
    return np.concatenate(out)


class State:
    """``tail``: the bytes that tokens to come may hold; ``last``: for each place in it, the
    latest first, the token that ends there and the change of the count since."""

    __slots__ = ("tail", "last", "steps")

    def __init__(self, tail: bytes, last: tuple):
        self.tail, self.last, self.steps = tail, last, {}


@dataclass(frozen=True)
class Chunk:
    """What ``text[start:stop]`` does: the text up to ``head`` goes on from the state to its
    left, the rest emits ``count`` tokens and ends in ``state`` (None: no pre-token starts)."""

    start: int
    head: int
    count: int = 0
    state: State | None = None


class Transducer:
    """The compiled tokenizer. ``source``: the bytes of a tokenizer's JSON file."""

    def __init__(self, source: bytes):
        spec = json.loads(source)
        model, pre = spec["model"], spec["pre_tokenizer"] or {}
        plain = model["type"] == "BPE" and pre.get("type") == "ByteLevel" and not pre.get("add_prefix_space") and pre.get("use_regex", True)
        if not plain or spec.get("normalizer") or model.get("dropout") or model.get("ignore_merges"):
            raise ValueError("only plain byte-level BPE tokenizers compile to this transducer")
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(printable)]
        byte = {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(rest)}
        raw = lambda token: bytes(byte[c] for c in token)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        self.ranks = {(raw(a), raw(b)): i for i, (a, b) in enumerate(pairs)}
        made = {bytes([b]): -1 for b in range(256)}
        for (a, b), i in self.ranks.items():
            if made.get(a, i) >= i or made.get(b, i) >= i:
                raise ValueError("merges must come after those that make their parts")
            made.setdefault(a + b, i)
        self.tokens = set(made)
        self.prefixes = {t[:n] for t in self.tokens for n in range(len(t) + 1)}
        self.special = [t["content"] for t in spec["added_tokens"] or () if t["content"]]
        self.edges: dict[bytes, tuple | None] = {}
        self._anew()

    def _anew(self) -> None:
        self.root = State(b"", ((b"", 0),))
        self.states = {(b"", self.root.last): self.root}
        self.apart: dict[tuple[bytes, bytes], bool] = {}
        self.emitted: dict[str, int] = {}

    def _edges(self, token: bytes) -> tuple | None:
        """How merges build ``token``: what stands at its left and at its right end in turn, each
        with the rank of the merge that ends it. None if they do not build it."""
        if token not in self.edges:
            parts, rank, none = [bytes([x]) for x in token], self.ranks.get, len(self.ranks)
            left, right, at_left, at_right = [parts[0]], [parts[-1]], [], []
            while len(parts) > 1 and (best := min(scores := [rank(p, none) for p in zip(parts, parts[1:])])) < none:
                at = scores.index(best)
                parts[at : at + 2] = [parts[at] + parts[at + 1]]
                if at == 0:
                    left.append(parts[0])
                    at_left.append(best)
                if at == len(parts) - 1:
                    right.append(parts[-1])
                    at_right.append(best)
            # A pair without a rank has `none`; an end that no merge takes away lasts longer.
            built = len(parts) == 1
            self.edges[token] = ((left, [*at_left, none + 1]), (right, [*at_right, none + 1])) if built else None
        return self.edges[token]

    def _stays(self, a: bytes, b: bytes) -> bool:
        """Whether the merges leave ``a`` and ``b`` as two neighbouring tokens (no ``a``: one).

        Merges go by rank, then from the left, and build their parts first. So the pair at the
        seam merges if its rank comes before that of the merge that changes either end.
        """
        known = self.apart.get((a, b))
        if known is None:
            known = self._edges(b) is not None
            if known and a:
                (ends, until), (begins, till) = self._edges(a)[1], self._edges(b)[0]
                i = j = 0
                rank, none = self.ranks.get, len(self.ranks)
                while known and (i + 1 < len(ends) or j + 1 < len(begins)):
                    seam = rank((ends[i], begins[j]), none)
                    known = seam >= until[i] or seam > till[j]
                    if until[i] <= till[j]:
                        i += 1
                    else:
                        j += 1
                known = known and (a, b) not in self.ranks
            self.apart[a, b] = known
        return known

    def step(self, state: State, byte: int) -> tuple[State, int]:
        """The transition of ``state`` under ``byte``: the next state, tokens emitted."""
        found = state.steps.get(byte)
        if found is None:
            tail, last, tokens, apart = state.tail + _BYTES[byte], state.last, self.tokens, self.apart
            while tail not in self.prefixes:
                tail = tail[1:]
            for at, (before, ago) in zip(range(len(tail) - 1, -1, -1), last):
                token = tail[at:]
                if token in tokens:
                    stays = apart.get((before, token))
                    if stays or (stays is None and self._stays(before, token)):
                        break
            made = ago + 1
            history = ((token, 0), *[(t, n - made) for t, n in last[: len(tail)]])
            to = self.states.get((tail, history))
            if to is None:
                to = self.states[tail, history] = State(tail, history)
            found = state.steps[byte] = to, made
        return found

    def run(self, state: State, word: str) -> tuple[State, int]:
        """The state after ``word`` and the tokens emitted on the way."""
        count = 0
        for byte in word.encode("utf-8", "replace"):
            step = state.steps.get(byte) or self.step(state, byte)
            state = step[0]
            count += step[1]
        return state, count

    def emit(self, word: str) -> int:
        """Tokens of one whole pre-token: its path from the root, kept as one transition."""
        known = self.emitted.get(word)
        if known is None:
            if max(len(self.emitted), len(self.states), len(self.apart)) >= MEMO:
                self._anew()
            known = self.run(self.root, word)[1]
            if len(word) <= WORD:
                self.emitted[word] = known
        return known

    def chunks(self, text: str, start: np.ndarray, ends: np.ndarray, size: int = CHUNK) -> list[list[Chunk]]:
        """The maps of the chunks of each text in ``text``; ``ends``: where a stop follows one.

        ``start`` is :func:`starts_of` for all of ``text``.
        """
        cuts = np.append(np.flatnonzero(start), len(text))
        out, begin, emit = [], 0, self.emit
        for end in ends.tolist():
            maps = []
            for a in range(begin, end, size):
                b = min(a + size, end)
                lo, hi = np.searchsorted(cuts, (a, b)).tolist()
                if lo == hi:
                    maps.append(Chunk(a, b))
                    continue
                at = cuts[lo:hi].tolist()
                inner = sum([emit(text[x:y]) for x, y in zip(at, at[1:])])
                state, count = self.run(self.root, text[at[-1] : b])
                maps.append(Chunk(a, at[0], inner + count, state))
            out.append(maps)
            begin = end + 1
        return out

    def compose(self, text: str, a: Chunk, b: Chunk) -> Chunk:
        """The map of two neighbouring pieces of ``text``. Associative."""
        if a.state is None:
            return Chunk(a.start, b.head, b.count, b.state)
        state, count = self.run(a.state, text[b.start : b.head])
        return Chunk(a.start, a.head, a.count + count + b.count, b.state or state)

    def combined(self, text: str, maps: list[Chunk]) -> Chunk:
        """The map of a whole text: neighbours compose pairwise until one map is left."""
        while len(maps) > 1:
            maps = [self.compose(text, *maps[i : i + 2]) if i + 1 < len(maps) else maps[i] for i in range(0, len(maps), 2)]
        return maps[0]

    def count(self, texts: list[str | None], size: int = CHUNK) -> list[int]:
        """Tokens of each text. Added tokens' strings are tokens of their own, as by default."""
        pieces, owner, out = [], [], [0] * len(texts)
        for i, text in enumerate(texts):
            parts = [text or ""]
            for s in self.special:
                split = [p.split(s) for p in parts]
                out[i] += sum(len(p) - 1 for p in split)
                parts = [x for p in split for x in p]
            for p in filter(None, parts):
                pieces.append(p)
                owner.append(i)
        a = 0
        while a < len(pieces):
            b, n = a, 0
            while b < len(pieces) and n < BLOCK:
                n += len(pieces[b]) + 1
                b += 1
            joined = "\n".join(pieces[a:b]) + "\n"
            ends = np.cumsum([len(p) + 1 for p in pieces[a:b]]) - 1
            for i, maps in zip(owner[a:b], self.chunks(joined, all_starts(joined, ends), ends, size)):
                out[i] += self.combined(joined, maps).count
            a = b
        return out


@functools.lru_cache(maxsize=2)
def _compiled(source: bytes) -> Transducer:
    return Transducer(source)


def count_tokens(docs: DataFrame, tokenizer_file: str, limit: int = 1024, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, n_bytes, n_tokens, over_limit`` for each row; a null text counts as empty.

    ``tokenizer_file`` is read on the driver. Extra columns are not returned.
    """
    with open(tokenizer_file, "rb") as f:
        source = f.read()

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = _compiled(source)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(machine.count(b.column(2).to_pylist()), pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    d = docs.select(F.col(doc_id).alias("doc_id"), F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes"), F.col(text).alias("text"))
    out = d.mapInArrow(counted, f"doc_id {d.schema['doc_id'].dataType.simpleString()}, n_bytes long, n_tokens long")
    return out.withColumn("over_limit", F.col("n_tokens") > limit)


def op7_token_counts(spark, sf_dir):
    import public_tokenizers

    return count_tokens(spark.read.parquet(f"{sf_dir}/documents.parquet"), public_tokenizers.path("byte_bpe_50k.json"))
