"""Byte-pair encoding and decoding with a word-end vocabulary, word by word over a contiguous rank array.

A word's state is two parallel arrays: the boundaries of its current parts, and for each part the rank of the
merge with its right neighbour. Encoding scans the ranks for the minimum, deletes one boundary, and refreshes
the two ranks that touch the merged part, until no rank is left. Words are short, so the scan costs less than
a heap. Finished words are remembered in a bounded table.

The vocabulary file is a parameter, read by each Python worker from its own installation and never shipped.
Normalisation, word pattern and decoding follow the file: NFC, lower case by single code points, the pattern's
matches only, byte symbols, and (no decoder being set) tokens joined by one space. Strings of special tokens in
a text are those tokens, as the library has it.

Defined cases: null and empty texts have no tokens, and both digests are of the empty string; repeated rows
give repeated results; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from memojoin.llm.common import read, texts_of, trimmed

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
#: Words that a worker remembers; the table is emptied when full.
REMEMBERED = 300_000
#: Words of more bytes are merged from a heap, and not remembered.
SHORT = 200
#: Unicode's White_Space, as a character class body.
SPACE = r"\x09-\x0D \x85\xA0  -     　"
NO_MERGE = 1 << 60


def byte_symbols() -> list[str]:
    """A printable code point for every byte: itself if it is a visible Latin-1 one, else the next from 256 on."""
    visible = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in visible else chr(next(spare)) for b in range(256)]


class WordBpe:
    """Encoder and decoder of one vocabulary file of the word-end kind."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model["end_of_word_suffix"]
        self.ranks = {tuple(m if isinstance(m, list) else m.split(" ")): k for k, m in enumerate(model["merges"])}
        self.specials = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.names = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.specials.items()}
        pattern = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"].replace(r"\s", SPACE)
        self.find = regex.compile(pattern, regex.V0).findall
        self.cut = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.specials, key=len, reverse=True)) + ")").split
        self.symbols = byte_symbols()
        self.known: dict[str, tuple[int, str, str]] = {}

    def parts(self, word: str) -> list[str]:
        """The symbols of one word after all merges."""
        text = [self.symbols[b] for b in word.encode("utf-8")]
        text[-1] += self.suffix
        if len(text) > SHORT:
            return self._long_parts(text)
        starts = list(range(len(text) + 1))
        piece = lambda k: "".join(text[starts[k] : starts[k + 1]])

        def rank(k: int) -> int:
            return self.ranks.get((piece(k), piece(k + 1)), NO_MERGE) if 0 <= k < len(starts) - 2 else NO_MERGE

        ranks = [rank(k) for k in range(len(starts) - 1)]
        while len(ranks) > 1:
            least = min(ranks)
            if least == NO_MERGE:
                break
            at = ranks.index(least)
            del starts[at + 1]
            del ranks[at]
            ranks[at] = rank(at)
            if at:
                ranks[at - 1] = rank(at - 1)
        return [piece(k) for k in range(len(starts) - 1)]

    def _long_parts(self, text: list[str]) -> list[str]:
        """The same merges in the same order (lowest rank, then leftmost) from a heap: n log n steps for long words."""
        ranks, n = self.ranks, len(text)
        piece: list[str | None] = list(text)
        before, after = list(range(-1, n - 1)), [*range(1, n), -1]
        heap = [(r, k, text[k], text[k + 1]) for k in range(n - 1) if (r := ranks.get((text[k], text[k + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            _, k, a, b = heapq.heappop(heap)
            j = after[k]
            if piece[k] != a or j < 0 or piece[j] != b:
                continue  # one of the two has been merged since
            piece[k], piece[j] = a + b, None
            after[k] = after[j]
            if after[j] >= 0:
                before[after[j]] = k
            for x, y in ((before[k], k), (k, after[k])):
                if x >= 0 and y >= 0 and (r := ranks.get((piece[x], piece[y]))) is not None:
                    heapq.heappush(heap, (r, x, piece[x], piece[y]))
        return [p for p in piece if p is not None]

    def ids(self, word: str) -> list[int]:
        return [self.vocab[p] for p in self.parts(word)]

    def words(self, text: str) -> list[str]:
        text = text if text.isascii() else unicodedata.normalize("NFC", text).replace("Σ", "σ")
        return self.find(text.lower())

    def encode(self, text: str | None) -> list[int]:
        out: list[int] = []
        for k, piece in enumerate(self.cut(text or "")):
            if k % 2:
                out.append(self.specials[piece])
            else:
                for w in self.words(piece):
                    out += self.ids(w)
        return out

    def decode(self, ids) -> str:
        return " ".join(self.names[i] for i in ids)

    def _remember(self, word: str) -> tuple[int, str, str]:
        if len(self.known) >= REMEMBERED:
            self.known.clear()
        ids = self.ids(word)
        found = (len(ids), " ".join(map(str, ids)), self.decode(ids))
        if len(word) <= SHORT:
            self.known[word] = found
        return found

    def digest(self, text: str | None) -> tuple[int, str, str]:
        """Tokens, and the digests of the ids in decimal and of the decoded text."""
        got: list[tuple[int, str, str]] = []
        for k, piece in enumerate(self.cut(text) if text and "<|" in text else [text or ""]):
            if k % 2:
                got.append((1, str(self.specials[piece]), piece))
            else:
                known = self.known
                for w in self.words(piece):
                    got.append(known.get(w) or self._remember(w))
        ids, decoded = " ".join([g[1] for g in got]), " ".join([g[2] for g in got])
        return sum([g[0] for g in got]), hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(decoded.encode("utf-8", "surrogatepass")).hexdigest()


@lru_cache(maxsize=4)
def load(vocabulary: str) -> WordBpe:
    """vocabulary: a file's path, or the name of one of the installed public vocabularies."""
    if "/" not in vocabulary:
        import public_tokenizers

        vocabulary = public_tokenizers.path(vocabulary)
    return WordBpe(vocabulary)


def digests(docs: DataFrame, vocabulary: str) -> DataFrame:
    """Token counts and digests of every whole text."""

    def run(batches):
        bpe = load(vocabulary)
        for batch in batches:
            got = [bpe.digest(t) for t in texts_of(batch)]
            n, ids, decoded = map(list, zip(*got)) if got else ([], [], [])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(trimmed(run), SCHEMA)


def encode(docs: DataFrame, vocabulary: str) -> DataFrame:
    """doc_id and the token ids of every whole text."""

    def run(batches):
        bpe = load(vocabulary)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bpe.encode(t) for t in texts_of(batch)], pa.list_(pa.int32()))], ["doc_id", "ids"])

    return docs.select("doc_id", "text").mapInArrow(trimmed(run), "doc_id long, ids array<int>")


def decode(encoded: DataFrame, vocabulary: str) -> DataFrame:
    """doc_id and the decoded text; null ids decode to the empty text."""

    def run(batches):
        bpe = load(vocabulary)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([bpe.decode(i or []) for i in texts_of(batch, "ids")], pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(trimmed(run), "doc_id long, text string")


VOCABULARY = "word_bpe_49k.json"


def op10_bpe(spark, sf_dir: str) -> DataFrame:
    return digests(read(spark, sf_dir, "documents"), VOCABULARY)
