"""Byte-pair encoding and decoding by batched merge rounds in numpy.

The symbols of many words lie in one flat array. Each round looks up all neighbouring pairs by binary search in the
sorted pair keys, takes the lowest rank of every word and merges it wherever it stands in that word (left to right,
without overlap), so the number of rounds is that of the deepest word, not that of all merges. Merging all places of a
pair at once equals merging one at a time because no merge that uses a symbol ranks before one that makes it; this is
checked when the vocabulary is loaded, and otherwise one place per word and round is merged.

White space never lies inside a word, so a text is cut at ASCII white space into pieces whose results are remembered in
two generations of bounded dictionaries. The vocabulary file (its path is a parameter) is read on each worker.

Nulls and empty texts give no tokens. Texts of any length are encoded whole. Rows are independent, so repeated rows,
ties and extra columns don't matter; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import json
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, table

REMEMBERED = 200_000  # pieces a generation
_LETTER, _DIGIT = "a-z\u00aa\u00b5\u00ba\u00df-\u00f6\u00f8-\u024f", "0-9\u00b2\u00b3\u00b9\u00bc-\u00be"
_FAST = re.compile(rf"\n|'s|'t|'re|'ve|'m|'ll|'d|[{_LETTER}]+|[{_DIGIT}]|[^\s{_LETTER}{_DIGIT}]+")
_SLOW = re.compile("[\x1c-\x1f\u0250-\U0010ffff]|<\\|")  # control separators, other scripts, perhaps a special token
NONE = np.int32(2**31 - 1)


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(other)) for b in range(256)]


class Bpe:
    """Encoder and decoder for a tokenizer file with byte-level letters and word ends."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_truncation()
        self.library.no_padding()
        spec = json.loads(self.library.to_str())
        vocab, self.end = spec["model"]["vocab"], spec["model"].get("end_of_word_suffix") or ""
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.special_cut = re.compile("(" + "|".join(re.escape(x) for x in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        self.token = {i: t for t, i in (vocab | self.special).items()}
        letters = byte_letters()
        self.first = np.array([vocab[x] for x in letters], np.int32)
        self.last = np.array([vocab[x + self.end] for x in letters], np.int32)
        self.byte_of = {x: b for b, x in enumerate(letters)}
        pairs = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in spec["model"]["merges"]]
        left, right = (np.array([vocab[p[k]] for p in pairs], np.int64) for k in (0, 1))
        made = np.array([vocab[a + b] for a, b in pairs], np.int32)
        self.size = max(self.token) + 1
        key = left * self.size + right
        order = np.argsort(key, kind="stable")
        self.keys, self.rank, self.made = key[order], order.astype(np.int32), made
        born = np.zeros(self.size, np.int64) - 1  # the last merge that makes a symbol
        born[made] = np.arange(len(made))
        self.in_order = bool((np.maximum(born[left], born[right]) < np.arange(len(made))).all())
        self.seen: tuple[dict, dict] = ({}, {})
        self.seen_as = ""

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words given as bytes (each non-empty), one after the other, and the number of each."""
        if not words:
            return np.zeros(0, np.int32), np.zeros(0, np.int64)
        lens = np.fromiter(map(len, words), np.int64, len(words))
        raw = np.frombuffer(b"".join(words), np.uint8)
        sym = self.first[raw]
        ends = np.cumsum(lens) - 1
        sym[ends] = self.last[raw[ends]]
        word = np.repeat(np.arange(len(words)), lens)
        done_sym, done_word = [], []
        while len(sym):
            same = np.flatnonzero(word[1:] == word[:-1])
            key = sym[same].astype(np.int64) * self.size + sym[same + 1]
            at = np.searchsorted(self.keys, key)
            at[at == len(self.keys)] = 0
            rank = np.full(len(sym), NONE, np.int32)
            rank[same] = np.where(self.keys[at] == key, self.rank[at], NONE)
            begin = np.diff(word, prepend=-1) != 0
            low = np.minimum.reduceat(rank, np.flatnonzero(begin))
            of = np.cumsum(begin) - 1
            live = (low < NONE)[of]
            where = np.flatnonzero(live & (rank == low[of]))
            if not live.all():
                done_sym.append(sym[~live])
                done_word.append(word[~live])
            if self.in_order:  # of touching places in a run, every second one
                head = np.diff(where, prepend=-2) != 1
                where = where[(np.arange(len(where)) - np.flatnonzero(head)[np.cumsum(head) - 1]) % 2 == 0] if len(where) else where
            else:
                where = where[np.diff(of[where], prepend=-1) != 0]
            sym[where] = self.made[rank[where]]
            live[where + 1] = False
            sym, word = sym[live], word[live]
        flat, owner = np.concatenate(done_sym), np.concatenate(done_word)
        return flat[np.argsort(owner, kind="stable")], np.bincount(owner, minlength=len(words))

    def _words(self, piece: str) -> list[bytes | int]:
        """Words of any piece, by the library's normaliser and splitter, and special tokens as ids."""
        out: list[bytes | int] = []
        for part in self.special_cut.split(piece) if self.special_cut else (piece,):
            if part in self.special:
                out.append(self.special[part])
            else:
                normal = self.library.normalizer.normalize_str(part)
                out += [bytes(self.byte_of[c] for c in x) for x, _ in self.library.pre_tokenizer.pre_tokenize_str(normal) if x]
        return out

    def encode_flat(self, pieces: list[str]) -> tuple[np.ndarray, list[int]]:
        """Ids of all pieces (texts or parts of texts that white space bounds), and where each piece begins (and the last ends)."""
        slow = [i for i, p in enumerate(pieces) if _SLOW.search(p)] if _SLOW.search("\n".join(pieces)) else []
        plain = "\n".join(pieces) if not slow else "\n".join(["" if _SLOW.search(p) else p for p in pieces])
        words: list = _FAST.findall(plain.lower())
        if slow:
            out, at = [], 0
            breaks = [-1, *[k for k, w in enumerate(words) if w == "\n"], len(words)]
            for i in slow:
                out += words[at : breaks[i] + 1]
                out += self._words(pieces[i])
                at = breaks[i] + 1
            words = out + words[at:]
        index: dict = {"\n": 0}
        number = [index.setdefault(w, len(index)) for w in words]
        todo = [w for w in index if w != "\n" and not isinstance(w, int)]
        ids, n = self.merge([w if isinstance(w, bytes) else w.encode() for w in todo])
        start, count = np.zeros(len(index), np.int64), np.zeros(len(index), np.int64)
        own = np.array([index[w] for w in todo], np.int64)
        start[own], count[own] = np.cumsum(n) - n, n
        special = [w for w in index if isinstance(w, int)]
        for k, w in enumerate(special):
            start[index[w]], count[index[w]] = len(ids) + k, 1
        ids = np.concatenate([ids, np.array(special, np.int32)])
        num = np.array(number, np.int64)
        c = count[num]
        to = np.cumsum(c) - c
        out_ids = ids[np.repeat(start[num] - to, c) + np.arange(int(c.sum()))]
        return out_ids, [0, *to[num == 0].tolist(), len(out_ids)] if pieces else [0]

    def encode_pieces(self, pieces: list[str]) -> list[np.ndarray]:
        ids, at = self.encode_flat(pieces)
        return [ids[i:j] for i, j in zip(at, at[1:])]

    def encode(self, text: str | None) -> np.ndarray:
        parts = self.encode_pieces([x.decode() for x in (text or "").encode().split()])
        return np.concatenate(parts) if parts else np.zeros(0, np.int32)

    def decode(self, ids) -> str:
        """As the library does for a file without a decoder: the tokens with one space between them."""
        return " ".join([self.token[int(i)] for i in ids])

    def remember(self, kind: str, chunks: list[list[bytes]], make) -> dict:
        """What make(ids, begins) yields for every distinct piece of chunks; two generations of bounded size, kept for one kind of result."""
        if kind != self.seen_as:
            self.seen, self.seen_as = ({}, {}), kind
        new, old = self.seen
        if len(new) > REMEMBERED:
            self.seen = (new, old) = ({}, new)
        need = set().union(*chunks).difference(new)
        known = need.intersection(old)
        new.update(zip(known, map(old.__getitem__, known)))
        todo = list(need.difference(known))
        for i in range(0, len(todo), 20_000):
            part = todo[i : i + 20_000]
            new.update(zip(part, make(*self.encode_flat(b"\n".join(part).decode().split("\n")))))
        return new


def arrays(ids: np.ndarray, at: list[int]):
    return [ids[i:j].copy() for i, j in zip(at, at[1:])]


_loaded: dict[str, Bpe] = {}


def load(path: str) -> Bpe:
    if path not in _loaded:
        _loaded[path] = Bpe(path)
    return _loaded[path]


def groups(texts, most: int = 1 << 21):
    """Lists of pieces of consecutive texts of about `most` bytes."""
    out, size = [], 0
    for t in texts:
        out.append(t.split() if t else [])
        size += len(t) if t else 0
        if size > most:
            yield out
            out, size = [], 0
    if out:
        yield out


def encode_ids(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """docs with `ids` array<int>."""
    ship(docs.sparkSession)
    docs = docs.drop("ids")
    names = [*docs.columns, "ids"]

    def run(batches):
        bpe = load(path)
        for b in batches:
            col = b.column(b.num_columns - 1)
            ids = []
            for chunk in groups(col.cast(pa.binary()).to_pylist()):
                got = bpe.remember("ids", chunk, arrays)
                ids += [np.concatenate([got[p] for p in c]) if c else np.zeros(0, np.int32) for c in chunk]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(ids, pa.list_(pa.int32()))], names)
        bpe.seen = ({}, {})

    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in docs.columns) + ", ids array<int>"
    return docs.select("*", F.col(text).alias("__text")).mapInArrow(run, schema)


def decode_ids(docs: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """docs with `decoded` string (null for null ids)."""
    ship(docs.sparkSession)
    docs = docs.drop("decoded")
    names = [*docs.columns, "decoded"]
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in docs.columns) + ", decoded string"

    def run(batches):
        bpe = load(path)
        for b in batches:
            got = [None if x is None else bpe.decode(x) for x in b.column(b.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], pa.array(got, pa.string())], names)

    return docs.select("*", F.col(ids).alias("__ids")).mapInArrow(run, schema)


def digests(docs: DataFrame, path: str, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of the whole texts."""
    ship(docs.sparkSession)

    def make(bpe):
        def run(ids, at):
            ids = ids.tolist()
            number, token = list(map(str, ids)), list(map(bpe.token.__getitem__, ids))
            return [(j - i, " ".join(number[i:j]), " ".join(token[i:j])) for i, j in zip(at, at[1:])]

        return run

    def run(batches):
        bpe = load(path)
        for b in batches:
            n, enc, dec = [], [], []
            for chunk in groups(b.column(1).cast(pa.binary()).to_pylist()):
                got = bpe.remember("digests", chunk, make(bpe))
                for c in chunk:
                    parts = [x for x in map(got.__getitem__, c) if x[0]]
                    n.append(sum([x[0] for x in parts]))
                    enc.append(hashlib.sha256(" ".join([x[1] for x in parts]).encode()).hexdigest())
                    dec.append(hashlib.sha256(" ".join([x[2] for x in parts]).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(enc), pa.array(dec)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
        bpe.seen = ({}, {})  # a worker lives on after its task

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1(spark, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"), vocabulary())
