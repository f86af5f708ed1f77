"""Byte-pair encoding and decoding with a public word vocabulary.

Text is split at special tokens, brought to NFC, white space runs become one space, letters become lower case. White
space ends a word and is dropped; a pattern splits the rest. Each word is a sequence of byte symbols, the last one
marked as the end of the word, and is merged by rank.

Short words are merged many at a time over contiguous arrays: a row holds the parts between a word's boundaries and
the ranks of adjacent parts. Each step scans every row for its smallest rank, deletes that boundary by moving the rest
of the row up, and looks up the ranks of the two neighbours anew; finished rows leave. Long words keep their parts in a
linked list with a heap of ranks. What a word becomes is kept in a bounded table per worker.

Decoding joins the tokens' strings with single spaces, which is what the library does for a vocabulary that comes
without a decoder.

Defined results: null and empty texts have no tokens; special tokens in a text become their own ids; texts are encoded
whole, whatever their length; rows with equal texts are encoded alike.
"""

from __future__ import annotations

import gc
import hashlib
import heapq
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import KEPT, read_table, trim

VOCABULARY = "word_bpe_49k.json"
SHORT = 24  # symbols of a word up to which it goes through the arrays
CACHE_WORDS = 300_000
_NONE = np.int32(2**31 - 1)
#: White space of the vocabulary's normaliser; Python's str.split() splits at four more characters.
_SPACE = r"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+"
_NOT_SPACE = "\x1c\x1d\x1e\x1f"
#: Marks a special token among the chunks; white space, so no chunk starts with it.
_SPECIAL = "\n"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_symbols() -> list[str]:
    """One printable character per byte: printable Latin-1 bytes are themselves, the rest follow from 256 on."""
    own = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, spare = [""] * 256, 256
    for b in range(256):
        if b in own:
            out[b] = chr(b)
        else:
            out[b] = chr(spare)
            spare += 1
    return out


class WordEncoder:
    """Encoder and decoder over one vocabulary file (JSON with model.vocab, model.merges, added_tokens)."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.end = model["end_of_word_suffix"]
        vocab = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.strings = {i: s for s, i in vocab.items()} | {i: s for s, i in self.special.items()}
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")["pattern"]["Regex"]
        self.pattern = regex.compile(split)
        self.space = regex.compile(_SPACE)
        self.at_special = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        symbols = _byte_symbols()
        self.byte_id = np.array([vocab[s] for s in symbols], dtype=np.int64)
        self.last_id = np.array([vocab[s + self.end] for s in symbols], dtype=np.int64)
        pairs = {}
        for rank, (a, b) in enumerate(model["merges"]):
            pairs.setdefault((vocab[a] << 17) | vocab[b], (rank, vocab[a + b]))
        self.pairs = pairs
        keys = np.array(sorted(pairs), dtype=np.int64)
        self.keys, self.ranks = keys, np.array([pairs[k][0] for k in keys.tolist()], dtype=np.int32)
        self.made = np.zeros(len(model["merges"]), dtype=np.int64)
        for rank, new in pairs.values():
            self.made[rank] = new
        self.token_bytes = {i: t.encode() for i, t in self.strings.items()}
        self.id_bytes = {i: b"%d" % i for i in self.strings}
        self.known: dict[str, tuple[int, bytes, bytes]] = {}

    # -- merging

    def _rank(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        key = (a << 17) | b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where((a >= 0) & (b >= 0) & (self.keys[at] == key), self.ranks[at], _NONE)

    def merge_short(self, words: list[bytes]) -> list[list[int]]:
        """Ids of words of 1 to SHORT bytes, all merged side by side."""
        out: list[list[int]] = [[] for _ in words]
        order = sorted(range(len(words)), key=lambda i: len(words[i]))
        for lo in range(0, len(order), 20_000):
            rows = order[lo : lo + 20_000]
            size = np.array([len(words[i]) for i in rows])
            width = int(size.max())
            flat = np.frombuffer(b"".join(words[i].ljust(width, b"\0") for i in rows), dtype=np.uint8).reshape(-1, width)
            col = np.arange(width)
            parts = np.where(col < size[:, None], self.byte_id[flat], -1)
            at = np.arange(len(rows))
            parts[at, size - 1] = self.last_id[flat[at, size - 1]]
            pad = np.full((len(rows), 1), -1, dtype=parts.dtype)
            parts = np.concatenate([parts, pad], axis=1)  # so that the last part has a right neighbour
            ranks = self._rank(parts[:, :-1], parts[:, 1:])
            who = np.array(rows)
            while len(who):
                best = ranks.argmin(axis=1)
                at = np.arange(len(who))
                low = ranks[at, best]
                going = low != _NONE
                if not going.all():
                    for i, p in zip(who[~going].tolist(), parts[~going].tolist(), strict=True):
                        out[i] = p[: p.index(-1)]
                    who, parts, ranks, best, low = who[going], parts[going], ranks[going], best[going], low[going]
                    if not len(who):
                        break
                    at = np.arange(len(who))
                # delete the boundary behind part ``best``
                here = np.arange(parts.shape[1] - 1)
                parts[:, :-1] = np.take_along_axis(parts, here + (here > best[:, None]), axis=1)
                parts[:, -1] = -1
                parts[at, best] = self.made[low]
                here = np.arange(ranks.shape[1] - 1)
                ranks[:, :-1] = np.take_along_axis(ranks, here + (here > best[:, None]), axis=1)
                ranks[:, -1] = _NONE
                ranks[at, best] = self._rank(parts[at, best], parts[at, best + 1])
                left = np.maximum(best - 1, 0)
                ranks[at, left] = np.where(best > 0, self._rank(parts[at, left], parts[at, best]), ranks[at, left])
        return out

    def merge_long(self, word: bytes) -> list[int]:
        """Ids of one word of any length."""
        ids = self.byte_id[np.frombuffer(word, dtype=np.uint8)].tolist()
        ids[-1] = int(self.last_id[word[-1]])
        n = len(ids)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r[0], i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.pairs.get((ids[i] << 17) | ids[i + 1]))]
        heapq.heapify(heap)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = after[i] if ids[i] == a else n
            if j >= n or ids[j] != b:
                continue  # a part has changed since
            ids[i], ids[j] = self.pairs[(a << 17) | b][1], -1
            after[i] = after[j]
            if after[j] < n:
                before[after[j]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y < n and (r := self.pairs.get((ids[x] << 17) | ids[y])):
                    heapq.heappush(heap, (r[0], x, ids[x], ids[y]))
        return [i for i in ids if i >= 0]

    # -- texts

    def normalise(self, text: str) -> list[str]:
        """The lower-case chunks between white space."""
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # letters are lowered one by one
        if any(c in text for c in _NOT_SPACE):
            return [c for c in self.space.sub(" ", text).lower().split(" ") if c]
        return text.lower().split()

    def learn(self, chunks: set[str]) -> None:
        """Fill the table for chunks that it lacks."""
        known, strings, numbers = self.known, self.token_bytes, self.id_bytes
        todo = [c for c in chunks if c not in known]
        if len(known) + len(todo) > CACHE_WORDS:
            known.clear()
            todo = list(chunks)
        cut = list(map(self.pattern.findall, todo))
        words = [w for w in {w for c in cut for w in c} if w not in known]
        raw = [w.encode("utf-8", "surrogatepass") for w in words]
        short = [i for i, r in enumerate(raw) if len(r) <= SHORT]
        merged = dict(zip(short, self.merge_short([raw[i] for i in short]), strict=True))
        for i, w in enumerate(words):
            ids = merged[i] if i in merged else self.merge_long(raw[i])
            known[w] = (len(ids), b" ".join([numbers[x] for x in ids]), b" ".join([strings[x] for x in ids]))
        for c, parts in zip(todo, cut, strict=True):
            if len(parts) > 1:
                n, i, d = zip(*[known[w] for w in parts], strict=True)
                known[c] = (sum(n), b" ".join(i), b" ".join(d))
            elif not parts:
                known[c] = (0, b"", b"")

    def decode(self, ids: list[int]) -> str:
        return b" ".join([self.token_bytes[i] for i in ids]).decode("utf-8", "surrogatepass")

    def pieces(self, text: str) -> list[str]:
        """Chunks between white space and special tokens, in order."""
        if self.at_special is None or not any(s in text for s in self.special):
            return self.normalise(text)
        out: list[str] = []
        for part in self.at_special.split(text):
            out += [_SPECIAL + part] if part in self.special else self.normalise(part)
        return out

    def encode_many(self, texts: list[str | None]) -> Iterator[tuple[int, bytes, bytes]]:
        """(number of ids, ids as text, decoded text) of each text."""
        cut = [self.pieces(t or "") for t in texts]
        self.learn({c for c in set().union(*cut) if c[0] != _SPECIAL})
        for s, i in self.special.items():
            self.known[_SPECIAL + s] = (1, self.id_bytes[i], self.token_bytes[i])
        get = self.known.__getitem__
        for p in cut:
            if not p:
                yield 0, b"", b""
                continue
            n, i, d = zip(*map(get, p), strict=True)
            if 0 in n:
                i, d = [x for x in i if x], [x for x in d if x]
            yield sum(n), b" ".join(i), b" ".join(d)

    def encode(self, text: str | None) -> list[int]:
        (_, ids, _), = self.encode_many([text])
        return [int(i) for i in ids.split()]


_OPEN: dict[str, WordEncoder] = {}
KEPT.append(_OPEN)


def _encoder(path: str) -> WordEncoder:
    if path not in _OPEN:
        gc.set_threshold(500_000, 50, 100)  # the table's many small tuples hold no cycles
        _OPEN[path] = WordEncoder(path)
    return _OPEN[path]


def _groups(texts: pd.Series, chars: int = 2_000_000) -> Iterator[list[str | None]]:
    held, size = [], 0
    for t in texts:
        held.append(t)
        size += len(t or "")
        if size >= chars:
            yield held
            held, size = [], 0
    if held:
        yield held


def encode_documents(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, ids array<int>) of each row."""
    where = path or vocabulary_path()

    @F.pandas_udf("array<int>")
    def ids(texts: pd.Series) -> pd.Series:
        enc = _encoder(where)
        return pd.Series([np.array(i.split(), dtype=np.int32) for g in _groups(texts) for _, i, _ in enc.encode_many(g)], dtype=object)

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), ids(F.col(text_col)).alias("ids"))


def decode_documents(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, text) from (doc_id, ids)."""
    where = path or vocabulary_path()

    @F.pandas_udf("string")
    def text(ids: pd.Series) -> pd.Series:
        enc = _encoder(where)
        return pd.Series([enc.decode(list(i) if i is not None else []) for i in ids], dtype=object)

    return encoded.select("doc_id", text("ids").alias("text"))


def digest_documents(docs: DataFrame, path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): the round trip of each row, reduced to digests where it is made."""
    where = path or vocabulary_path()

    @F.pandas_udf("n_tokens long, ids_sha256 string, decoded_sha256 string")
    def digests(parts: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        trim()
        enc = _encoder(where)
        for texts in parts:
            rows = [(n, hashlib.sha256(i).hexdigest(), hashlib.sha256(d).hexdigest()) for g in _groups(texts) for n, i, d in enc.encode_many(g)]
            yield pd.DataFrame(rows, columns=["n_tokens", "ids_sha256", "decoded_sha256"]).astype({"n_tokens": "int64"})
            del texts, rows
        trim()

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), digests(F.col(text_col)).alias("d")).select("doc_id", "d.*")


def op10_bpe(spark, sf_dir: str) -> DataFrame:
    return digest_documents(read_table(spark, sf_dir, "documents"))
