"""Exact SentencePiece BPE encoding by backtracking over longest matches, and decoding.

A sequence of tokens is the merge result of its text exactly if every token is the merge result of
its own text and every two neighbours stay apart when their joined text is merged. So a text is
covered by longest vocabulary matches, from an Aho-Corasick automaton, stepping back to shorter
matches where neighbours are not compatible; a bitfield marks text positions from which the rest is
already known to fail. No piece goes on past a space that follows other characters, so words are
encoded apart and their results are kept in a bounded store per worker.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SPACE = "▁"


class Bpe:
    """Encoder and decoder of one SentencePiece BPE model with byte fallback and identity normalisation."""

    def __init__(self, path: str):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        special = [sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) for i in range(n)]
        self.score = [sp.get_score(i) for i in range(n)]
        self.id = {p: i for i, p in enumerate(self.pieces) if not special[i] and not sp.is_unused(i)}
        self.byte = {int(p[3:5], 16): i for i, p in enumerate(self.pieces) if sp.is_byte(i)}
        self.byte_of = {i: b for b, i in self.byte.items()}
        self.control = {i for i in range(n) if sp.is_control(i)}
        self.unknown = sp.unk_id()
        # words may be encoded apart if no piece holds a space after another character
        self.by_word = not any(a != SPACE and b == SPACE for p in self.id for a, b in zip(p, p[1:], strict=False))
        self.automaton = ahocorasick.Automaton(ahocorasick.STORE_INTS)
        for p, i in self.id.items():
            if self.merge(p) == [i]:  # pieces that merging never makes are no tokens
                self.automaton.add_word(p, i)
        self.automaton.make_automaton()
        self.pairs: dict[int, bool] = {}
        self.length = [len(p) for p in self.pieces]
        # of each token: the longest token that its text begins with, but for itself
        self.shorter = [-1] * n
        for p, i in self.id.items():
            self.shorter[i] = next((self.id[p[:k]] for k in range(len(p) - 1, 0, -1) if p[:k] in self.automaton), -1)
        self.plain = set(self.id.values())
        self.spaced = [p.replace(SPACE, " ") for p in self.pieces]
        self.outside = re.compile("[^" + "".join(re.escape(p) for p in self.id if len(p) == 1) + "]")
        self.store = 300_000
        self.runs: dict[str, list[int]] = {}
        self.words: dict[str, str] = {}
        self.changed: set[str] = set()  # words in `words` that do not decode to themselves

    def merge(self, text: str) -> list[int]:
        """Tokens of a short text by merging the best neighbours, first from the left, again and again."""
        parts = list(text)
        while len(parts) > 1:
            best, at = None, -1
            for i in range(len(parts) - 1):
                j = self.id.get(parts[i] + parts[i + 1])
                if j is not None and (best is None or self.score[j] > best):
                    best, at = self.score[j], i
            if best is None:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return [self.id.get(p, self.unknown) for p in parts]

    def compatible(self, a: int, b: int) -> bool:
        """Whether merging the joined text of two tokens gives just these two."""
        key = a << 20 | b
        got = self.pairs.get(key)
        if got is None:
            if len(self.pairs) >= 1 << 19:
                self.pairs.clear()
            got = self.pairs[key] = self.merge(self.pieces[a] + self.pieces[b]) == [a, b]
        return got

    def _known(self, text: str) -> list[int]:
        """Tokens of a text all of whose characters are pieces."""
        n, length, shorter, pairs = len(text), self.length, self.shorter, self.pairs
        longest = [-1] * n  # of each start; matches come by rising ends
        for end, i in self.automaton.iter(text):
            longest[end + 1 - length[i]] = i
        tokens: list[int] = []
        failed, at, token, last = 0, 0, longest[0], -1
        while True:
            if token < 0:
                # longest-first order has tried every compatible way on from here
                failed |= 1 << at
                if not tokens:
                    raise ValueError("no merge-consistent cover")
                token = tokens.pop()
                last = tokens[-1] if tokens else -1
                at -= length[token]
                token = shorter[token]
                continue
            stop = at + length[token]
            fits = not failed >> stop & 1
            if fits and last >= 0:
                fits = pairs.get(last << 20 | token)
                if fits is None:
                    fits = self.compatible(last, token)
            if fits:
                tokens.append(token)
                if stop == n:
                    return tokens
                last, at, token = token, stop, longest[stop]
            else:
                token = shorter[token]

    def encode_segment(self, text: str) -> list[int]:
        """Tokens of a segment; characters outside the vocabulary become their UTF-8 bytes."""
        out: list[int] = []
        run = 0
        for m in self.outside.finditer(text):
            if run < m.start():
                out += self.run_tokens(text[run : m.start()])
            out += [self.byte[b] for b in m.group().encode()]
            run = m.end()
        if run < len(text):
            out += self.run_tokens(text[run:])
        return out

    def run_tokens(self, text: str) -> list[int]:
        """Tokens of a run of known characters, from the bounded store."""
        got = self.runs.get(text)
        if got is None:
            if len(self.runs) >= self.store // 8:
                self.runs.clear()
            got = self.runs[text] = self._known(text)
        return got

    def segments(self, text: str) -> list[str]:
        """Parts that encode apart, with spaces marked; a text gets a leading space, an empty one nothing."""
        if not text:
            return []
        text = SPACE + text.replace(" ", SPACE)
        if not self.by_word:
            return [text]
        out, pad = [], ""
        for w in text.split(SPACE)[1:]:  # each with the space before it; more spaces belong to the next word
            pad += SPACE
            if w:
                out.append(pad + w)
                pad = ""
        if pad:
            out.append(pad)
        return out

    def encode(self, text: str | None) -> list[int]:
        return [i for s in self.segments(text or "") for i in self.encode_segment(s)]

    def word_ids(self, word: str) -> str:
        """Comma-joined ids of a word after one space, kept in the bounded store."""
        if len(self.words) >= self.store:
            self.words.clear()
            self.changed.clear()
        ids = self.encode_segment(SPACE + word) if self.outside.search(word) else self._known(SPACE + word)
        got = self.words[word] = ",".join(map(str, ids))
        if self.decode_pieces(ids) != " " + word:
            self.changed.add(word)
        return got

    def encode_joined(self, text: str) -> tuple[str, str]:
        """Comma-joined ids and decoded text."""
        if not text:
            return "", ""
        words = text.split(" ")
        if self.by_word and SPACE not in text and "" not in words:
            parts = list(map(self.words.get, words))
            if None in parts:
                parts = [p if p is not None else self.words.get(w) or self.word_ids(w) for w, p in zip(words, parts, strict=True)]
            if not self.changed or self.changed.isdisjoint(words):
                return ",".join(parts), text
        ids = self.encode(text)
        return ",".join(map(str, ids)), self.decode(ids)

    def decode_pieces(self, ids: list[int]) -> str:
        """Text of the ids, its leading space kept: runs of byte pieces are UTF-8, bad bytes become U+FFFD."""
        if self.plain.issuperset(ids):
            return "".join([self.spaced[i] for i in ids])
        out: list[str] = []
        held = bytearray()
        for i in ids:
            b = self.byte_of.get(i)
            if b is not None:
                held.append(b)
                continue
            if held:
                out.append(_utf8(bytes(held)))
                held = bytearray()
            if i not in self.control:
                out.append(" ⁇ " if i == self.unknown else self.spaced[i])
        if held:
            out.append(_utf8(bytes(held)))
        return "".join(out)

    def decode(self, ids: list[int]) -> str:
        text = self.decode_pieces(ids)
        return text[1:] if text.startswith(" ") else text


def _utf8(b: bytes) -> str:
    try:
        return b.decode()
    except UnicodeDecodeError:  # one replacement for each byte that starts no character
        out, i = [], 0
        while i < len(b):
            for n in (1, 2, 3, 4):
                try:
                    out.append(b[i : i + n].decode())
                    i += n
                    break
                except UnicodeDecodeError:
                    continue
            else:
                out.append("�")
                i += 1
        return "".join(out)


def default_model() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def encode_documents(docs: DataFrame, model: str | None = None, id_col: str = "doc_id", text_col: str = "text", outputs: tuple[str, ...] = ("ids", "decoded"), store: int = 300_000) -> DataFrame:
    """Token ids and decoded text of each row: ``(id_col, n_tokens, ...)`` with the asked outputs.

    ``outputs`` may hold ``ids`` (array), ``decoded`` (string), ``ids_sha256`` and ``decoded_sha256``
    (lowercase hex digests of the comma-joined ids and of the decoded UTF-8 text). Null and empty
    texts have no tokens and decode to the empty string. ``model`` is a path every executor can read
    (default: the installed public tokenizers). ``store`` bounds the words kept per worker; it changes
    the speed only. Repeated rows repeat their results; other columns are ignored.
    """
    sql = {"ids": "array<int>", "decoded": "string", "ids_sha256": "string", "decoded_sha256": "string"}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = _loaded(model or default_model())
        bpe.store = store
        for b in (whole.slice(at, 256) for whole in batches for at in range(0, whole.num_rows, 256)):
            n, cols = [], {k: [] for k in outputs}
            for t in b.column(1).to_pylist():
                joined, text = bpe.encode_joined(t or "")
                n.append(joined.count(",") + 1 if joined else 0)
                for k, out in cols.items():
                    if k == "ids":
                        out.append(np.fromstring(joined, np.int32, sep=","))
                    elif k == "decoded":
                        out.append(text)
                    else:
                        out.append(hashlib.sha256((joined if k == "ids_sha256" else text).encode()).hexdigest())
            made = [pa.ListArray.from_arrays(np.cumsum([0, *n], dtype=np.int32), np.concatenate([*v, np.zeros(0, np.int32)])) if k == "ids" else pa.array(v, pa.string()) for k, v in cols.items()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), *made], names=["id", "n_tokens", *cols])

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("t"))
    return slim.mapInArrow(run, ", ".join(["id long", "n_tokens long", *(f"{k} {sql[k]}" for k in outputs)])).withColumnRenamed("id", id_col)


@lru_cache(2)
def _loaded(path: str) -> Bpe:
    return Bpe(path)


def encoding(spark, sf_dir: str) -> DataFrame:
    """Query op5: every document encoded and decoded."""
    return encode_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"), outputs=("ids_sha256", "decoded_sha256"))
