"""BPE encoding and decoding by forced boundaries.

Two neighbouring byte symbols that stand side by side in no token of the vocabulary can never be merged
across, so a cut between them is certain. A text is first cut at white space and by the vocabulary's own
splitting pattern, then each piece at every forced boundary; the fragments are encoded independently
of each other (each once per cache generation) and their ids concatenated. Decoding is the
concatenation of the ids' token strings.

The result equals the public library's for vocabularies of this kind: canonical composition, one blank for
white space, lower case by character, word ends marked on the last symbol, no decoder. Added tokens are
taken out of the raw text first.

Defined results: null and empty texts give no ids; rows are encoded one by one, so repeated rows, ties
and further columns change nothing; an empty table gives an empty result. Fragments of any length take
n log n time.
"""

from __future__ import annotations

import heapq
import json
import re
import unicodedata
from collections.abc import Iterator
from hashlib import sha256

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: White space of the vocabulary's pattern; unlike str.split() it has no U+001C to U+001F.
SPACE = r"\u0009-\u000d\u0020\u0085\u00a0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
OTHER_SPLIT = re.compile("[\x1c-\x1f]")
BY_SPACE = re.compile(f"[{SPACE}]+")
#: The splitting pattern of the vocabulary file (fixed value), white space spelled out.
PIECES = regex.compile(rf"'s|'t|'re|'ve|'m|'ll|'d|\p{{L}}+|\p{{N}}|[^{SPACE}\p{{L}}\p{{N}}]+")
#: The same for runs of lower-case ASCII without white space; and runs that are one piece of Latin letters.
ASCII_PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^a-z0-9]+")
LATIN = re.compile("[a-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+")
LONG = 200
#: Entries of a cache's generation: of word pieces, of runs between white space, and of fragments.
WORDS, CHUNKS, FRAGMENTS = 150_000, 150_000, 30_000
#: Characters of text that a worker turns into output at a time.
SLICE = 2_000_000


def byte_symbols() -> list[str]:
    """The printable stand-in of each byte: printable Latin bytes for themselves, others from U+0100 up."""
    keep = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    rest = iter(range(0x100, 0x200))
    return [chr(b) if b in keep else chr(next(rest)) for b in range(256)]


class Generations(dict):
    """A dict that computes missing values and forgets the older half of them at a bounded size."""

    def __init__(self, make, most: int):
        super().__init__()
        self.make, self.most, self.old = make, most, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(self) >= self.most:
            self.old = dict(self)
            self.clear()
        self[key] = value
        return value


class ForcedBoundaryBpe:
    def __init__(self, raw: str | bytes):
        spec = json.loads(raw)
        model = spec["model"]
        self.end = model["end_of_word_suffix"] or ""
        vocab: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.text_of = {i: t for t, i in {**vocab, **self.special}.items()}
        symbols = byte_symbols()
        #: Ids of byte symbols within and at the end of a word; those missing from the vocabulary count as -1.
        self.within = [vocab.get(x, -1) for x in symbols]
        self.at_end = [vocab.get(x + self.end, -1) for x in symbols]
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        self.rank = {(vocab[a], vocab[b]): i for i, (a, b) in reversed(list(enumerate(pairs))) if a + b in vocab}
        self.result = [vocab.get(a + b, -1) for a, b in pairs]
        #: Pairs of neighbours inside any token; the last symbol of a word is another than the same byte within.
        inside = set()
        for token in vocab:
            units = list(token.removesuffix(self.end)) if self.end and len(token) > len(self.end) else list(token)
            if self.end and token.endswith(self.end) and len(token) > len(self.end):
                units[-1] += self.end
            inside.update((vocab[x], vocab[y]) for x, y in zip(units, units[1:], strict=False) if x in vocab and y in vocab)
        self.inside = inside
        none = len(self.result)
        self.first_rank = {p: self.rank.get(p, none) for p in inside}
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        #: A run without any of these holds no added token.
        marks = {t[0] for t in self.special if t}
        self.marked = re.compile("[" + "".join(map(re.escape, sorted(marks))) + "]").search if marks else lambda chunk: None
        self.fragments = Generations(self.fragment_texts, FRAGMENTS)
        self.words = Generations(self.word_texts, WORDS)
        self.chunks = Generations(self.chunk_texts, CHUNKS)

    def cut(self, word: str) -> list[tuple[int, ...]]:
        """The fragments of a piece, as ids of byte symbols, between forced boundaries."""
        raw = word.encode("utf-8", "surrogatepass")
        ids = list(map(self.within.__getitem__, raw))
        ids[-1] = self.at_end[raw[-1]]
        if self.inside.issuperset(zip(ids, ids[1:], strict=False)):
            return [tuple(ids)]
        inside, out, at = self.inside, [], 0
        for i, pair in enumerate(zip(ids, ids[1:], strict=False), 1):
            if pair not in inside:
                out.append(tuple(ids[at:i]))
                at = i
        out.append(tuple(ids[at:]))
        return out

    def merge(self, fragment: tuple[int, ...]) -> list[int]:
        ids = list(fragment)
        if len(ids) == 1:
            return ids if ids[0] >= 0 else []
        if len(ids) > LONG:
            return self.merge_long(ids)
        # Within a fragment every pair is one inside some token, so its rank is known.
        get, none, result = self.rank.get, len(self.result), self.result
        ranks = list(map(self.first_rank.__getitem__, zip(ids, ids[1:], strict=False)))
        while ranks:
            best = min(ranks)
            if best == none:
                break
            i = ranks.index(best)
            ids[i : i + 2] = [result[best]]
            del ranks[i]
            if i:
                ranks[i - 1] = get((ids[i - 1], ids[i]), none)
            if i < len(ranks):
                ranks[i] = get((ids[i], ids[i + 1]), none)
        return ids

    def merge_long(self, ids: list[int]) -> list[int]:
        """The same merges from a heap over a linked list."""
        n = len(ids)
        after, before, alive = list(range(1, n + 1)), list(range(-1, n - 1)), [True] * n
        heap = [(r, i, ids[i], ids[i + 1]) for i in range(n - 1) if (r := self.rank.get((ids[i], ids[i + 1]))) is not None]
        heapq.heapify(heap)
        while heap:
            r, i, a, b = heapq.heappop(heap)
            j = after[i] if alive[i] else n
            if j >= n or ids[i] != a or ids[j] != b:
                continue
            ids[i], alive[j], after[i] = self.result[r], False, after[j]
            if after[i] < n:
                before[after[i]] = i
            for x in (before[i], i):
                if x >= 0 and after[x] < n and (q := self.rank.get((ids[x], ids[after[x]]))) is not None:
                    heapq.heappush(heap, (q, x, ids[x], ids[after[x]]))
        return [x for x, ok in zip(ids, alive, strict=True) if ok]

    def fragment_texts(self, fragment: tuple[int, ...]) -> tuple[str, str]:
        ids = self.merge(fragment)
        return " ".join(map(str, ids)), " ".join(map(self.text_of.__getitem__, ids))

    def word_texts(self, word: str) -> tuple[str, str]:
        """Ids and token strings of a piece, each joined by blanks."""
        parts = self.cut(word)
        if len(parts) == 1:
            return self.fragment_texts(parts[0])
        got = [self.fragments[f] for f in parts]
        return " ".join([g[0] for g in got]), " ".join([g[1] for g in got])

    def chunk_texts(self, chunk: str) -> tuple[str, str]:
        """The same for a run without white space."""
        if self.marked(chunk) is None:
            return self.run_texts(chunk)
        parts = self.split_special.split(chunk)
        got = [(str(self.special[x]), x) if k % 2 else self.run_texts(x) for k, x in enumerate(parts) if x]
        return " ".join([g[0] for g in got]), " ".join([g[1] for g in got])

    def run_texts(self, run: str) -> tuple[str, str]:
        """The same for a run that holds no added token."""
        if run.isascii():
            low = run.lower()
            pieces = (low,) if low.isalpha() else ASCII_PIECES.findall(low)
        else:
            # Lower case character by character: a final sigma stays a plain one.
            low = unicodedata.normalize("NFC", run).replace("Σ", "σ").lower()
            pieces = (low,) if LATIN.fullmatch(low) else PIECES.findall(low)
        if len(pieces) == 1:
            return self.words[pieces[0]]
        got = list(map(self.words.__getitem__, pieces))
        return " ".join([g[0] for g in got]), " ".join([g[1] for g in got])

    def encode_text(self, text: str | None) -> tuple[str, str]:
        """The ids and the decoded tokens of a whole text, each joined by blanks."""
        if not text:
            return "", ""
        pieces = [c for c in BY_SPACE.split(text) if c] if OTHER_SPLIT.search(text) else text.split()
        got = list(map(self.chunks.__getitem__, pieces))
        return " ".join([g[0] for g in got]), " ".join([g[1] for g in got])

    def encode(self, text: str | None) -> list[int]:
        return [int(i) for i in self.encode_text(text)[0].split()]

    def decode(self, ids: list[int]) -> str:
        return " ".join(self.text_of[i] for i in ids if i in self.text_of)


_READY: dict[int, ForcedBoundaryBpe] = {}


def encoder(raw: bytes) -> ForcedBoundaryBpe:
    """One encoder for each vocabulary in a worker, with its caches kept between tasks."""
    key = hash(raw)
    if key not in _READY:
        _READY.clear()
        _READY[key] = ForcedBoundaryBpe(raw)
    return _READY[key]


def vocabulary(path: str | None = None) -> bytes:
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, "rb") as f:
        return f.read()


def encode(df: DataFrame, id_col: str = "doc_id", text: str = "text", path: str | None = None, with_ids: bool = False) -> DataFrame:
    """One row per input row: id, n_tokens, digests of ids and of the decoded text; the ids on request.

    The vocabulary (a few MB, a fixed size) is read on the driver and broadcast.
    """
    shared = df.sparkSession.sparkContext.broadcast(vocabulary(path))
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = encoder(shared.value)
        names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256", *["ids"] * with_ids]
        for batch in batches:
            start, size = 0, 0
            n, a, b, lists = [], [], [], []
            for k, t in enumerate(batch.column(1)):
                text = t.as_py()
                ids, decoded = bpe.encode_text(text)
                n.append(ids.count(" ") + 1 if ids else 0)
                a.append(sha256(ids.encode()).hexdigest())
                b.append(sha256(decoded.encode()).hexdigest())
                if with_ids:
                    lists.append(np.array(ids.split(), np.int32))
                size += len(text or "")
                if size >= SLICE or k == batch.num_rows - 1:
                    cols = [batch.column(0).slice(start, k + 1 - start), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())]
                    if with_ids:
                        ends = np.concatenate(([0], np.cumsum([len(x) for x in lists]))).astype(np.int32)
                        cols.append(pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(lists))))
                    yield pa.RecordBatch.from_arrays(cols, names=names)
                    start, size = k + 1, 0
                    n, a, b, lists = [], [], [], []

    schema = f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return df.select(F.col(id_col), F.col(text)).mapInArrow(run, schema)
