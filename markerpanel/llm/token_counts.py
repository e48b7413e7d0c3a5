"""Token counts by a compiled finite-state tokenizer (byte-level merge tokenizers).

The tokenizer becomes one deterministic transducer. Its upper part reads character classes and cuts a
text as the pre-tokenizer's pattern does; its lower part reads bytes inside a piece. A lower state
holds what later bytes can depend on: the longest suffix that can begin a token, and for each place in
it the last token of the encoding up to there with its count. A transition carries the change of the
token count. States and transitions are built when first met and then only looked up.

A text is cut into chunks of CHUNK characters, anywhere. Each chunk has a state map, from the state in which it is entered
to the state in which it is left and the tokens in between. A state is what the upper part still holds unread: the
stretch since the last place where it is sure to start anew (white space after another character). All entry states of a
chunk meet at its first such place, so the map is the same from there on and is kept as three parts: the head, which waits
for the entry state, the count of the middle, and the tail, which is the exit state. Maps compose associatively, and a text's
count is the last entry of a prefix scan over its chunks' maps. Stretches of the middle and their pieces are memoised.

The transducer is kept per process; its tables start again once they hold MOST_STATES states.

Rows stand alone: null or empty texts have 0 tokens; texts of any length are read whole; repeated rows
and null ids give one row each; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import json
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from markerpanel.llm.common import arrow_map, public_file, table

#: White space of the pattern, and the endings that stand alone after an apostrophe.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")
MEMO_ENTRIES = 500_000
#: States of the lower part that a process keeps, and characters of a chunk.
MOST_STATES = 400_000
CHUNK = 4096
#: Room for a change of the count, which is less than the longest token's bytes either way.
GAINS = 1 << 14
START = 0


class Known(dict):
    """Token counts by string; what it doesn't hold is counted, and kept if short."""

    def __init__(self, count):
        super().__init__()
        self.count = count

    def __missing__(self, text: str) -> int:
        n = self.count(text)
        if len(text) < 64:
            if len(self) >= MEMO_ENTRIES:
                self.clear()
            self[text] = n
        return n


class Transducer:
    """Compiled from a tokenizers file whose model is byte-level BPE."""

    def __init__(self, file: str):
        with open(file, encoding="utf-8") as f:
            spec = json.load(f)
        model, pre = spec["model"], spec["pre_tokenizer"]
        if model["type"] != "BPE" or pre["type"] != "ByteLevel" or pre["add_prefix_space"] or spec["normalizer"]:
            raise ValueError("only plain byte-level merge tokenizers are compiled")
        shown = _shown_bytes()
        raw = lambda s: bytes(shown[c] for c in s)
        self.rank: dict[tuple[bytes, bytes], int] = {}
        self.parts: dict[bytes, tuple[bytes, bytes, int]] = {}
        for k, m in enumerate(model["merges"]):
            a, b = map(raw, m if isinstance(m, list) else m.split(" "))
            self.rank[a, b] = k
            self.parts.setdefault(a + b, (a, b, k))
        tokens = {raw(t) for t in model["vocab"] if all(c in shown for c in t)}
        self.tokens = {t: t for t in tokens if len(t) == 1 or t in self.parts}
        if max(map(len, self.tokens)) >= GAINS // 2:
            raise ValueError("a token is too long for a transition")
        self.begins = {t[:k] for t in self.tokens for k in range(1, len(t) + 1)}
        self.special = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.at_special = regex.compile("|".join(map(regex.escape, self.special))) if self.special else None
        self.forget()
        self.anew = regex.compile(f"[^{WHITE}](?=[{WHITE}])")
        self.chunks = re.compile(f"[{WHITE}]*[^{WHITE}]+|[{WHITE}]+")
        # runs of one class with the space before them; of white space the last character waits for what follows
        self.cut = regex.compile(rf"'(?:{'|'.join(ENDINGS)})| ?(?:\p{{L}}+|\p{{N}}+|[^{WHITE}\p{{L}}\p{{N}}]+)|[{WHITE}]+(?![^{WHITE}])|[{WHITE}]+")
        self.of_chunk = Known(self._stretch)
        self.of_piece = Known(self._piece)

    def forget(self) -> None:
        """Begin the tables anew; they are built again as they are needed."""
        self.beside: dict[tuple[bytes, bytes], bool] = {}
        # lower states: (suffix, last token and relative count at each place of it)
        self.states: list[tuple[bytes, tuple]] = []
        self.number: dict[tuple, int] = {}
        #: state << 8 | byte -> next state * GAINS + change of the count
        self.next: dict[int, int] = {}
        self.place: dict[tuple, tuple] = {}  # states share their places
        self._state(b"", ((None, 0),))

    # -- lower part: bytes inside a piece ---------------------------------------------------------
    def _fits(self, left: bytes, right: bytes) -> bool:
        """Whether no merge across the border of two neighbouring tokens comes before those inside them."""
        key = (left, right)
        if key not in self.beside:
            bound = None
            while True:
                k = self.rank.get((left, right))
                if k is not None and (bound is None or (k, 0) < bound):
                    ok = False
                    break
                a, b = self.parts.get(left), self.parts.get(right)
                if a is None and b is None:
                    ok = True
                    break
                of_a, of_b = (a[2], -1) if a else (-1, 0), (b[2], 1) if b else (-1, 0)
                if of_a > of_b:
                    bound, left = of_a, a[1]
                else:
                    bound, right = of_b, b[0]
            self.beside[key] = ok
        return self.beside[key]

    def _state(self, suffix: bytes, places: tuple) -> int:
        key = (suffix, places)
        if key not in self.number:
            self.number[key] = len(self.states)
            self.states.append(key)
        return self.number[key]

    def _build(self, state: int, byte: int) -> int:
        suffix, places = self.states[state]
        read = suffix + bytes((byte,))
        n = len(read)
        for k in range(n):  # the token that ends here: just one fits what stands before it
            token = read[k:]
            if (token := self.tokens.get(token)) is not None:
                before, count = places[k]
                if before is None or self._fits(before, token):
                    break
        else:
            raise AssertionError("every single byte is a token")
        gain = count + 1
        keep = next((k for k in range(n) if read[k:] in self.begins), n)
        share = self.place.setdefault
        after = tuple(share(p, p) for p in [(t, c - gain) for t, c in places[keep:]] + [(token, 0)])
        return self._state(read[keep:], after) * GAINS + gain + GAINS // 2

    def piece(self, data: bytes) -> int:
        if len(self.states) > MOST_STATES:
            self.forget()
        state, total, known = START, 0, self.next
        for byte in data:
            step = known.get(state << 8 | byte)
            if step is None:
                step = known[state << 8 | byte] = self._build(state, byte)
            state = step // GAINS
            total += step % GAINS
        return total - len(data) * (GAINS // 2)

    def starts_anew(self, left: str, right: str) -> bool:
        """Whether the upper part is sure to start anew between two neighbouring stretches."""
        return bool(left and right and self.anew.match(left[-1] + right[0]))

    # -- upper part: character classes ------------------------------------------------------------
    def _piece(self, piece: str) -> int:
        return self.piece(piece.encode("utf-8", "surrogatepass"))

    def _stretch(self, chunk: str) -> int:
        """Tokens of a stretch that begins and ends where the upper part starts anew."""
        return sum(map(self.of_piece.__getitem__, self.cut.findall(chunk)))

    def _tokens(self, text: str) -> int:
        return sum(map(self.of_chunk.__getitem__, self.chunks.findall(text)))

    def whole(self, text: str) -> int:
        """Tokens of a text by itself; special strings are one token each."""
        if self.at_special is None or not self.at_special.search(text):
            return self._tokens(text)
        found = self.at_special.findall(text)
        return len(found) + sum(map(self._tokens, self.at_special.split(text)))

    def state_map(self, chunk: str) -> StateMap:
        """The map of any chunk of a text."""
        first = self.anew.search(chunk)
        if first is None:
            return StateMap(self, chunk, None, "")
        lo, hi = first.start() + 1, len(chunk)
        while not self.anew.match(chunk, hi - 2):
            hi -= 1
        return StateMap(self, chunk[:lo], self.whole(chunk[lo : hi - 1]), chunk[hi - 1 :])

    def count(self, text: str) -> int:
        if len(text) <= CHUNK:
            return self.whole(text) if text else 0
        return scan([self.state_map(text[k : k + CHUNK]) for k in range(0, len(text), CHUNK)])[-1].tokens()


@dataclass(frozen=True)
class StateMap:
    """Entry state -> (exit state, tokens). middle is None where a chunk has no place to start anew: then all of it is head."""

    machine: Transducer
    head: str
    middle: int | None
    tail: str

    def __call__(self, state: str) -> tuple[str, int]:
        if self.middle is None:
            return state + self.head, 0
        return self.tail, self.machine.whole(state + self.head) + self.middle

    def tokens(self) -> int:
        """From the start state, with the exit state read out."""
        state, n = self("")
        return n + self.machine.whole(state)


def compose(first: StateMap, second: StateMap) -> StateMap:
    """The map of two neighbouring chunks."""
    m = first.machine
    anew = m.starts_anew(first.tail if first.middle is not None else first.head, second.head if second.middle is not None or second.head else second.tail)
    if first.middle is None:
        if anew:
            return StateMap(m, first.head, m.whole(second.head) + second.middle, second.tail) if second.middle is not None else StateMap(m, first.head, 0, second.head)
        return StateMap(m, first.head + second.head, second.middle, second.tail)
    if second.middle is None:
        if anew:
            return StateMap(m, first.head, first.middle + m.whole(first.tail), second.head)
        return StateMap(m, first.head, first.middle, first.tail + second.head)
    between = m.whole(first.tail) + m.whole(second.head) if anew else m.whole(first.tail + second.head)
    return StateMap(m, first.head, first.middle + between + second.middle, second.tail)


def scan(maps: list[StateMap]) -> list[StateMap]:
    """Inclusive prefix scan: entry k is the map of chunks 0..k.

    Pairs are composed, the half as many maps are scanned, and the rest filled in: n compositions a level less, all of a
    level independent of one another, so the work is linear.
    """
    if len(maps) < 2:
        return list(maps)
    pairs = scan([compose(maps[k], maps[k + 1]) for k in range(0, len(maps) - 1, 2)])
    out = [maps[0]]
    for k in range(1, len(maps)):
        out.append(pairs[k // 2] if k % 2 else compose(pairs[k // 2 - 1], maps[k]))
    return out


@functools.lru_cache(maxsize=2)
def compiled(file: str) -> Transducer:
    """One transducer a process: its tables serve all tasks that run there."""
    return Transducer(file)


def _shown_bytes() -> dict[str, int]:
    """Byte-level vocabularies show printable Latin-1 bytes as themselves and the rest from U+0100 on."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(256 + k): b for k, b in enumerate(rest)}


def count_tokens(docs: DataFrame, file: str, limit: int = 512) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit for every row."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def make():
        machine = compiled(file)

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            sizes, counts = [], []
            for lo in range(0, batch.num_rows, 500):
                for text in batch.column(1).slice(lo, 500).to_pylist():
                    text = text or ""
                    sizes.append(len(text.encode("utf-8", "surrogatepass")))
                    counts.append(machine.count(text))
            n = pa.array(counts, pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes, pa.int64()), n, pa.array([c > limit for c in counts], pa.bool_())], names=["doc_id", "n_bytes", "n_tokens", "over_limit"])

        return step

    return arrow_map(docs.select("doc_id", "text"), make, f"doc_id {kind}, n_bytes bigint, n_tokens bigint, over_limit boolean")


def op4(spark, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"), public_file("byte_bpe_50k.json"))
