"""SentencePiece encoding (merge type) by exact backtracking, and decoding.

A left-to-right walk takes the longest vocabulary piece at each place (matches come from one
Aho-Corasick pass) and steps back where the piece cannot stand beside the one before it. Two pieces
may stand side by side if, when both are taken apart merge by merge in reverse, no pair across their
border would have been merged earlier. Places from which no encoding goes on are kept in a bitfield,
so no place is tried twice and the walk is linear.

Rows stand alone: a null or empty text encodes to the end id only and decodes to the empty string;
texts of any length are encoded whole; repeated rows and null ids give one row each; other columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import functools
import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from markerpanel.llm.common import arrow_map, public_file, table

SPACE = "▁"
#: ASCII digits and punctuation, and Latin letters, as insides of character classes.
MARKS = r"!-@\[-`{-~"
LATIN = r"A-Za-z\u00C0-\u00D6\u00D8-\u00F6\u00F8-\u024F"
#: Entries of the per-task memo of encoded stretches; a full memo is emptied, results stay the same.
MEMO_ENTRIES = 500_000


class PieceCodec:
    """One model file. encode() and decode() equal the library's for merge-type models with byte fallback."""

    def __init__(self, model_file: str):
        import ahocorasick
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_file)
        self.eos = model.eos_id()
        self.id_of: dict[str, int] = {}
        self.score: dict[str, float] = {}
        self.byte_id: dict[int, int] = {}
        self.text_of: list[str | int | None] = []
        for i in range(model.get_piece_size()):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                self.byte_id[int(piece[3:5], 16)] = i
                self.text_of.append(int(piece[3:5], 16))
            elif model.is_control(i) or model.is_unknown(i) or model.is_unused(i):
                self.text_of.append(None)
            else:
                self.id_of[piece] = i
                self.score[piece] = model.get_score(i)
                self.text_of.append(piece)
        self.unknown = model.unk_id()
        # The library starts every non-empty text with one space, if the model is set so.
        self.prefix = SPACE if "".join(model.encode("a", out_type=str)).startswith(SPACE) else ""
        self.split_of: dict[str, tuple[str, str] | None] = {}
        self.beside: dict[tuple[str, str], bool] = {}
        self.automaton = ahocorasick.Automaton()
        for piece in self.id_of:
            self.automaton.add_word(piece, piece)
        self.automaton.make_automaton()
        self.longest = max(map(len, self.id_of), default=1)
        self.pairs = {pair for piece in self.id_of for pair in zip(piece, piece[1:], strict=False)}
        self.stretches = self._stretch_pattern()
        self.memo: dict[str, tuple[str, str]] = {}
        self.known: dict[str, list[str]] = {}
        self.makes: dict[str, bool] = {}

    def _stretch_pattern(self) -> re.Pattern:
        """Texts can be cut between two characters that stand next to each other in no piece.

        Three such cuts are made at once, each if the vocabulary allows it: before a run of spaces that
        follows another character, around a line feed, and between Latin letters and ASCII digits or punctuation.
        """
        if any(a != SPACE and b == SPACE for a, b in self.pairs):
            return re.compile(r"(?s).+")
        feed = not any("\n" in p for p in self.pairs)
        kinds = [(re.compile(f"[{x}]"), re.compile(f"[{y}]")) for x, y in ((MARKS, LATIN), (LATIN, MARKS))]
        apart = not any(x.match(a) and y.match(b) for x, y in kinds for a, b in self.pairs)
        rest = f"{SPACE}\n" if feed else SPACE
        alone = f"(?![^{rest}{MARKS}{LATIN}])"  # what is neither may belong to either
        parts = [f"{SPACE}*[{LATIN}]++{alone}", f"{SPACE}*[{MARKS}]++{alone}"] if apart else []
        return re.compile("|".join((["\n"] if feed else []) + parts + [f"{SPACE}*[^{rest}]+", f"{SPACE}+"]))

    def _cuts(self, s: str) -> list[str]:
        """A stretch cut wherever no piece has its two characters next to each other."""
        out, start, pairs = [], 0, self.pairs
        for k in range(1, len(s)):
            if (s[k - 1], s[k]) not in pairs:
                out.append(s[start:k])
                start = k
        out.append(s[start:])
        return out

    # -- merges ---------------------------------------------------------------------------------
    def _merge(self, symbols: list[str]) -> tuple[list[str], tuple[str, str] | None]:
        """Plain merging, best score first and leftmost among equals; the last pair that was merged."""
        last = None
        while True:
            best = max(((self.score.get(a + b, float("-inf")), -k) for k, (a, b) in enumerate(zip(symbols, symbols[1:], strict=False))), default=(float("-inf"), 0))
            if best[0] == float("-inf"):
                return symbols, last
            k = -best[1]
            last = (symbols[k], symbols[k + 1])
            symbols[k : k + 2] = [symbols[k] + symbols[k + 1]]

    def split(self, piece: str) -> tuple[str, str] | None:
        """The two parts a piece was last merged from; None for one character. Unreachable pieces have ("", "")."""
        if piece not in self.split_of:
            whole, last = self._merge(list(piece))
            self.split_of[piece] = (last if len(whole) == 1 else ("", "")) if len(piece) > 1 else None
        return self.split_of[piece]

    def fits(self, left: str, right: str) -> bool:
        """Whether the two pieces stay apart: undo the later merge of the two, again and again, and see
        whether the pair at the border would have been merged before the merge just undone."""
        key = (left, right)
        if key in self.beside:
            return self.beside[key]
        # When a merge happens: better scores first, then places from the left. A merge on the left of
        # the border comes before one of equal score across it, one on the right comes after it.
        bound, score, ok = None, self.score, True
        while True:
            joined = score.get(left + right)
            if joined is not None and (bound is None or (joined, 0) > bound):
                ok = False
                break
            a, b = self.split(left), self.split(right)
            if a is None and b is None:
                break
            of_a = (score[left], 1) if a is not None else (float("inf"), 1)
            of_b = (score[right], -1) if b is not None else (float("inf"), 1)
            if of_a < of_b:
                bound, left = of_a, a[1]
            else:
                bound, right = of_b, b[0]
        if len(self.beside) > 2_000_000:
            self.beside.clear()
        self.beside[key] = ok
        return ok

    def _whole(self, piece: str) -> bool:
        """Whether merging makes this piece of its characters."""
        hit = self.makes.get(piece)
        if hit is None:
            hit = len(piece) == 1 or (piece in self.id_of and self.split(piece) != ("", ""))
            if hit or piece in self.id_of:
                self.makes[piece] = hit
        return hit

    def _greedy(self, text: str) -> list[str] | None:
        """Longest matches one after another, if each may stand beside the one before it: then nothing is to be undone."""
        out: list[str] = []
        at = 0
        for end, piece in self.automaton.iter_long(text):
            start = end + 1 - len(piece)
            while at < start:  # characters without a piece
                out.append(text[at])
                at += 1
            if not self._whole(piece) or (out and not self.fits(out[-1], piece)):
                return None
            out.append(piece)
            at = end + 1
        out += text[at:]
        return out

    def pieces(self, text: str) -> list[str]:
        """The pieces of a stretch (spaces already replaced); characters without a piece stand alone."""
        n, whole, reach = len(text), self._whole, self.automaton.longest_prefix
        if whole(text):
            return [text]
        if (quick := self._greedy(text)) is not None:
            return quick
        failed = bytearray(n // 8 + 1)  # bit k: nothing that ends at k can be completed
        out: list[str] = []
        at, size = 0, max(1, reach(text[: self.longest]))
        while at < n:
            # the longest piece of at most ``size`` characters that fits here
            while size:
                end = at + size
                if not failed[end >> 3] >> (end & 7) & 1:
                    piece = text[at:end]
                    if whole(piece) and (not out or self.fits(out[-1], piece)):
                        break
                size -= 1
            if size:
                out.append(piece)
                at = end
                size = max(1, reach(text[at : at + self.longest]))
            else:  # back to the piece before, and on to a shorter one there
                failed[at >> 3] |= 1 << (at & 7)
                size = len(out.pop())
                at -= size
                size -= 1
        return out

    def ids(self, pieces: list[str]) -> list[int]:
        out = []
        for p in pieces:
            if p in self.id_of:
                out.append(self.id_of[p])
            elif self.byte_id:
                out += [self.byte_id[b] for b in p.encode("utf-8", "replace")]
            else:
                out.append(self.unknown)
        return out

    # -- texts ----------------------------------------------------------------------------------
    def _stretch(self, s: str) -> tuple[str, str]:
        """Ids of a stretch as decimal text, and what these ids decode to.

        A stretch holds whole characters, so its byte pieces decode alike alone and among others.
        """
        ids = self.ids([p for part in self._cuts(s) for p in (self.known.get(part) or self._part(part))])
        hit = (" ".join(map(str, ids)), self._decoded(ids))
        if len(self.memo) >= MEMO_ENTRIES:
            self.memo.clear()
        if len(s) < 64:
            self.memo[s] = hit
        return hit

    def _part(self, part: str) -> list[str]:
        out = self.pieces(part)
        if len(self.known) >= MEMO_ENTRIES // 2:
            self.known.clear()
        if len(part) < 32:
            self.known[part] = out
        return out

    def both(self, text: str) -> tuple[str, str]:
        """(ids with the end id, as decimals joined by one space; the text they decode to)."""
        if not text:
            return str(self.eos), ""
        memo, make = self.memo.get, self._stretch
        parts = [memo(s) or make(s) for s in self.stretches.findall(self.prefix + text.replace(" ", SPACE))]
        ids, texts = zip(*parts, strict=True)
        return f"{' '.join(ids)} {self.eos}", self._shown("".join(texts))

    def encode_text(self, text: str) -> str:
        return self.both(text)[0]

    def encode(self, text: str) -> list[int]:
        return list(map(int, self.encode_text(text).split(" ")))

    def _shown(self, joined: str) -> str:
        if self.prefix and joined.startswith(SPACE):
            joined = joined[1:]
        return joined.replace(SPACE, " ")

    def decode(self, ids: list[int]) -> str:
        """Pieces put together; runs of byte pieces are read as UTF-8; the leading space goes."""
        return self._shown(self._decoded(ids))

    def _decoded(self, ids: list[int]) -> str:
        parts: list[str] = []
        run = bytearray()
        of = self.text_of
        for i in ids:
            piece = of[i]
            if type(piece) is int:
                run.append(piece)
                continue
            if run:
                parts.append(_utf8(bytes(run)))
                run.clear()
            if piece is not None:
                parts.append(piece)
        if run:
            parts.append(_utf8(bytes(run)))
        return "".join(parts)


def _utf8(data: bytes) -> str:
    """Each byte that is no part of a whole character becomes U+FFFD, as the library does."""
    try:
        return data.decode("utf-8")
    except UnicodeDecodeError:
        out, k = [], 0
        while k < len(data):
            for size in (1, 2, 3, 4):
                try:
                    out.append(data[k : k + size].decode("utf-8"))
                    k += size
                    break
                except UnicodeDecodeError:
                    pass
            else:
                out.append("�")
                k += 1
        return "".join(out)


@functools.cache
def codec_of(model_file: str) -> PieceCodec:
    """One codec a process: tasks that follow one another on a worker share what it has learnt."""
    return PieceCodec(model_file)


def encode_documents(docs: DataFrame, model_file: str, with_ids: bool = True) -> DataFrame:
    """doc_id, ids (array, end id last), decoded text; without with_ids the two digests instead."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def make():
        codec = codec_of(model_file)

        def step(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            ids, texts = batch.column(0), batch.column(1)
            for lo in range(0, batch.num_rows, 500):
                counts, first, second, own = [], [], [], ids.slice(lo, 500)
                for text in texts.slice(lo, 500).to_pylist():
                    joined, back = codec.both(text or "")
                    counts.append(joined.count(" ") + 1)
                    first.append(np.array(joined.split(" "), np.int32) if with_ids else hashlib.sha256(joined.encode()).hexdigest())
                    second.append(back if with_ids else hashlib.sha256(back.encode("utf-8", "surrogatepass")).hexdigest())
                yield pa.RecordBatch.from_arrays([own, pa.array(counts, pa.int64()), pa.array(first, pa.list_(pa.int32()) if with_ids else pa.string()), pa.array(second, pa.string())], names=names)

        return step

    names = ["doc_id", "n_tokens", "ids", "decoded"] if with_ids else ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
    kinds = ("bigint", "array<int>", "string") if with_ids else ("bigint", "string", "string")
    return arrow_map(docs.select("doc_id", "text"), make, f"doc_id {kind}, " + ", ".join(f"{n} {k}" for n, k in zip(names[1:], kinds, strict=True)))


def op2(spark, sf_dir: str) -> DataFrame:
    return encode_documents(table(spark, sf_dir, "documents"), public_file("piece_bpe_32k.model"), with_ids=False)
