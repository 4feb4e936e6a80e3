"""Byte-pair encoding and decoding of whole texts.

The tokenizer file's own words (vocabulary entries that end a word) are
compiled, with the ids that the merge rules give them, into a minimal acyclic
transducer (``lexicon``), which every worker memory-maps.  A word that it holds
is looked up; any other is merged exactly, lowest rank first and leftmost among
equals, and remembered in a bounded table of the task.
"""

from __future__ import annotations

import hashlib
import json
import os
import tempfile
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession

#: Runs of letters in a generation of what a worker remembers.
REMEMBERED = 300_000


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> list[str]:
    """The printable stand-in of each byte value in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    letters = {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(rest)}
    return [letters[b] for b in range(256)]


#: Above any packed rank.
_NEVER = 1 << 62


class Rules:
    """What of a tokenizer file encoding needs, in a form that is quick to use."""

    def __init__(self, spec: dict):
        model = spec["model"]
        self.end = model["end_of_word_suffix"] or ""
        vocab = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.text_of = {i: t for t, i in vocab.items()} | {i: t for t, i in self.special.items()}
        letters = byte_letters()
        self.inner = [vocab[c] for c in letters]
        self.last = [vocab[c + self.end] for c in letters]
        #: (left id << 32 | right id) to (rank << 32 | merged id)
        self.merge: dict[int, int] = {}
        for rank, (a, b) in enumerate(model["merges"]):
            self.merge.setdefault(vocab[a] << 32 | vocab[b], rank << 32 | vocab[a + b])
        byte_of = {c: b for b, c in enumerate(letters)}
        self.words = []
        for token in vocab:
            if self.end and token.endswith(self.end) and len(token) > len(self.end):
                self.words.append(bytes(byte_of[c] for c in token[: -len(self.end)]))
        steps = spec["pre_tokenizer"]["pretokenizers"]
        self.pattern = steps[0]["pattern"]["Regex"]
        #: Ranges of code points that the merge rules' library takes for unassigned.
        self.unknown = spec.get("unknown_ranges", [])

    def ids(self, word: bytes) -> list[int]:
        """Exact merges: the pair of lowest rank first, the leftmost of equals."""
        parts = [self.inner[b] for b in word[:-1]]
        parts.append(self.last[word[-1]])
        find = self.merge.get
        if len(parts) > 64:
            return self._ids_long(parts)
        if len(parts) == 1:
            return parts
        ranks = [find(parts[i] << 32 | parts[i + 1], _NEVER) for i in range(len(parts) - 1)]
        while ranks and (low := min(ranks)) is not _NEVER:
            at = ranks.index(low)
            parts[at] = low & 0xFFFFFFFF
            del parts[at + 1], ranks[at]
            if at < len(ranks):
                ranks[at] = find(parts[at] << 32 | parts[at + 1], _NEVER)
            if at:
                ranks[at - 1] = find(parts[at - 1] << 32 | parts[at], _NEVER)
        return parts

    def _ids_long(self, parts: list[int]) -> list[int]:
        """The same for long words, with a heap and linked neighbours."""
        import heapq

        n, find = len(parts), self.merge.get
        after, before = [*range(1, n), -1], [-1, *range(n - 1)]
        alive = [True] * n
        heap = [(got >> 32, i, got & 0xFFFFFFFF, parts[i], parts[i + 1]) for i in range(n - 1) if (got := find(parts[i] << 32 | parts[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, new, a, b = heapq.heappop(heap)
            j = after[i] if alive[i] else -1
            if j < 0 or parts[i] != a or parts[j] != b:
                continue
            parts[i], alive[j] = new, False
            after[i] = after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for left in (before[i], i):
                right = after[left] if left >= 0 else -1
                if right >= 0 and (got := find(parts[left] << 32 | parts[right])) is not None:
                    heapq.heappush(heap, (got >> 32, left, got & 0xFFFFFFFF, parts[left], parts[right]))
        return [p for p, ok in zip(parts, alive, strict=True) if ok]


def unknown_ranges() -> list[tuple[int, int]]:
    """Letters and numbers of the regex module's table of characters that the
    tokenizer library's older table has not, as ranges."""
    from tokenizers import Regex, pre_tokenizers

    drop = pre_tokenizers.Split(Regex(r"[\p{L}\p{N}]"), "removed").pre_tokenize_str
    newer = regex.compile(r"[\p{L}\p{N}]").match
    out: list[list[int]] = []
    for code in range(0x300, 0x110000):
        if unicodedata.category(c := chr(code)) == "Cn" and newer(c) and drop(c):
            if out and out[-1][1] == code - 1:
                out[-1][1] = code
            else:
                out.append([code, code])
    return [tuple(r) for r in out]


class _Seen(dict):
    """What ``make`` gives for strings, in two generations of bounded size."""

    def __init__(self, make):
        super().__init__()
        self._make, self._old = make, {}

    def __missing__(self, key: str) -> str:
        if len(self) >= REMEMBERED:
            self._old = dict(self)
            self.clear()
        got = self._old.get(key)
        if got is None:
            got = self._make(key)
        self[key] = got
        return got


#: Controls that some tables count as white space and others do not.
_DOUBTFUL = regex.compile("[\x1c-\x1f]").search


class Encoder:
    """Encodes and decodes texts with a tokenizer's rules and a compiled lexicon."""

    def __init__(self, rules: Rules, lexicon=None):
        self.rules, self.lexicon = rules, lexicon
        self._find = regex.compile(rules.pattern).findall
        self._odd = self._find_odd = None
        if rules.unknown:
            odd = "".join(f"{chr(a)}-{chr(b)}" for a, b in rules.unknown)
            self._odd = regex.compile(f"[{odd}]").search
            careful = rules.pattern.replace("[\\p{L}]+", f"(?:(?![{odd}])\\p{{L}})+").replace("[\\p{N}]", f"(?:(?![{odd}])\\p{{N}})")
            careful = careful.replace("[^\\s\\p{L}\\p{N}]+", f"(?:[^\\s\\p{{L}}\\p{{N}}]|[{odd}])+")
            self._find_odd = regex.compile(careful).findall
        self._cut = regex.compile("(" + "|".join(map(regex.escape, rules.special)) + ")").split if rules.special else None
        self._ids_of = _Seen(self._chunk)
        self._spelt = _Seen(self._spell)
        self._text_of = {str(i): t for i, t in rules.text_of.items()}

    def _spell(self, word: str) -> tuple[int, ...]:
        """Ids of one word: from the lexicon, or merged."""
        raw = word.encode()
        got = self.lexicon.get(raw) if self.lexicon is not None else None
        return tuple(self.rules.ids(raw)) if got is None else got

    def _chunk(self, chunk: str) -> str:
        """Decimal ids of a run without white space, lower-cased already."""
        find = self._find_odd if self._odd and not chunk.isascii() and self._odd(chunk) else self._find
        out: list[int] = []
        for word in find(chunk):
            out += self._spelt[word]
        return " ".join(map(str, out))

    def _plain(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            if "Σ" in text:  # lower-cased letter by letter, so without a final form
                text = text.replace("Σ", "σ")
        text = text.lower()
        if _DOUBTFUL(text):
            return self._chunk(text)
        return " ".join(map(self._ids_of.__getitem__, text.split()))

    def encode(self, text: str) -> str:
        """Decimal ids joined by one space; special tokens keep their ids."""
        if self._cut and "<|" in text:
            pieces = self._cut(text)
            if len(pieces) > 1:
                got = (str(self.rules.special[p]) if k % 2 else self._plain(p) for k, p in enumerate(pieces))
                return " ".join(filter(None, got))
        return self._plain(text)

    def text_of(self, ids: str) -> str:
        """The text that decoding decimal ids gives: token texts joined by a space."""
        return " ".join(map(self._text_of.__getitem__, ids.split(" "))) if ids else ""

    def both(self, text: str) -> tuple[str, str]:
        ids = self.encode(text)
        return ids, self.text_of(ids)

    def decode(self, ids: list[int]) -> str:
        return " ".join(self.rules.text_of[i] for i in ids if i in self.rules.text_of)


_SHIPPED: dict[tuple[str, str], tuple[str, str]] = {}


def ship(spark: SparkSession, tokenizer: str) -> tuple[str, str]:
    """Compile the lexicon on the driver and give the executors both files."""
    from linkgraph.llm.lexicon import compile_lexicon

    sc = spark.sparkContext
    key = (sc.applicationId, tokenizer)
    if key not in _SHIPPED:
        with open(tokenizer, "rb") as f:
            raw = f.read()
        rules = Rules(json.loads(raw))
        spec = json.loads(raw) | {"unknown_ranges": unknown_ranges()}
        image = compile_lexicon((w, rules.ids(w)) for w in rules.words)
        mark = hashlib.sha256(raw).hexdigest()[:16]
        where = tempfile.mkdtemp(prefix="linkgraph-lexicon-")
        names = f"bpe-{mark}.json", f"bpe-{mark}.lexicon"
        for name, content in zip(names, (json.dumps(spec).encode(), image), strict=True):
            with open(os.path.join(where, name), "wb") as f:
                f.write(content)
            sc.addFile(os.path.join(where, name))
        _SHIPPED[key] = names
    return _SHIPPED[key]


_READY: dict[tuple[str, str], Encoder] = {}


def encoder_of(names: tuple[str, str]) -> Encoder:
    """The worker's encoder over the files that the driver shipped."""
    from linkgraph.llm.lexicon import Lexicon

    if names not in _READY:
        with open(SparkFiles.get(names[0]), "rb") as f:
            rules = Rules(json.load(f))
        _READY[names] = Encoder(rules, Lexicon(SparkFiles.get(names[1])))
    return _READY[names]


def encode(docs: DataFrame, tokenizer: str | None = None, with_ids: bool = True) -> DataFrame:
    """One row per row of ``docs``: doc_id, n_tokens, digests, and the ids.

    A null text counts as empty and gives no tokens (digests of the empty
    string).  Special tokens written in a text are encoded as such.  Other
    columns of ``docs`` are ignored.
    """
    names = ship(docs.sparkSession, tokenizer or default_tokenizer())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder_of(names)
        sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                counts, ids_sha, text_sha, arrays = [], [], [], []
                for text in part.column("text"):
                    ids, back = coder.both(text.as_py() or "")
                    counts.append(ids.count(" ") + 1 if ids else 0)
                    ids_sha.append(sha(ids))
                    text_sha.append(sha(back))
                    if with_ids:
                        arrays.append(np.fromstring(ids, dtype=np.int32, sep=" ") if ids else np.zeros(0, np.int32))
                columns = {"doc_id": part.column("doc_id").cast(pa.int64()), "n_tokens": pa.array(counts, pa.int64()), "ids_sha256": pa.array(ids_sha, pa.string()), "decoded_sha256": pa.array(text_sha, pa.string())}
                if with_ids:
                    columns["ids"] = pa.array(arrays, pa.list_(pa.int32()))
                yield pa.RecordBatch.from_pydict(columns)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * with_ids
    return docs.select("doc_id", "text").mapInArrow(run, schema)


def decode(encoded: DataFrame, tokenizer: str | None = None) -> DataFrame:
    """``(doc_id, text)`` from ``(doc_id, ids)``: token texts joined by a space."""
    names = ship(encoded.sparkSession, tokenizer or default_tokenizer())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder_of(names)
        for batch in batches:
            texts = [coder.decode(ids.as_py() or []) for ids in batch.column("ids")]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op3_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encoding and decoding of every whole text of ``documents``."""
    return encode(spark.read.parquet(f"{sf_dir}/documents.parquet"), with_ids=False)
