"""BPE by a deterministic automaton over tokens, compiled from the merges one gadget at a time.

The automaton reads tokens; what it accepts are exactly the token sequences that applying the merges in
order would leave. It starts as one state on which every byte loops. The gadget of a merge (u, v) -> w forks
the state behind u: the fork lacks the arc v, and all u-arcs lead to it from then on; and wherever an arc u
leads on to an arc v, an arc w is added to where v leads. So all arcs of a label end in one state, which at
first has the arcs of the state behind v. A merge whose arc is not there any more, as earlier merges always take its parts
away, adds nothing, and its token is never given out.

The arcs w of all states are those u had when the merge was compiled. So if labels are numbered in preorder, a
label before those that begin with it and the later made of these first, what a fork takes away is a range of
numbers, and the arcs of a state are a row of ranges. Rows that are equal in the end are one state.

Encoding a pre-split word follows the table: the automaton accepts one sequence that spells a prefix of the word,
hence at every place one last token, the one whose arc leaves the state behind the token that ends where it
begins. A place is settled once, when a token behind it asks, and no sequence is tried and given up.
Decoding emits arc labels.

Edge cases: a null text is empty, an empty text has no ids and decodes to itself; the text of an added
token becomes its id, as in the library; texts and words of any length are whole; repeated rows give equal
results; an empty table stays empty; columns other than those named are ignored. Merge lists may hold merges
that can never be applied, and several that make the same token; one that needs a token made only later is refused.
"""

from __future__ import annotations

import hashlib
import json
import re
from array import array
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from crowding.llm.common import Bounded, claim, released, slices, table, utf8

#: White space, and the pattern that splits the rest of a text into words.
SPACE = "\\t-\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_OUTER = re.compile(f" ?[^{SPACE}]+|[{SPACE}]+(?![^{SPACE}])|[{SPACE}]+")
_INNER = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{L}\p{N} ]+|\s+")
#: Bytes of segments and words with their ids that a worker keeps.
CACHE = 128 << 20
#: Every so many bytes of a word, its prefix is settled before what comes behind.
_STRIDE = 128


def byte_letters() -> dict[str, int]:
    """The letter each byte is written as in byte-level vocabularies: printable Latin-1 as itself, others from U+0100 on."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {**{chr(b): b for b in plain}, **{chr(256 + i): b for i, b in enumerate(rest)}}


def merged(word: bytes, ranks: dict[tuple[bytes, bytes], int]) -> tuple[bytes, bytes] | None:
    """The merge that makes the word one token, or None if its merges do not; by applying them in order."""
    parts, last = [word[i : i + 1] for i in range(len(word))], None
    while len(parts) > 1:
        rank, last = min((ranks.get(p, len(ranks)), p) for p in zip(parts, parts[1:]))
        if rank == len(ranks):
            return None
        out: list[bytes] = []
        for p in parts:
            # a part made by this very merge is longer than its first half, so it is never taken for one
            if out and (out[-1], p) == last:
                out[-1] += p
            else:
                out.append(p)
        parts = out
    return last


class Automaton:
    """The token automaton of a merge list over byte strings: states as rows of arc ranges, one state behind each label."""

    def __init__(self, vocab: dict[bytes, int], merges: list[tuple[bytes, bytes]]):
        n = max(vocab.values(), default=-1) + 1
        self.label: list[bytes] = [b""] * n
        for s, i in vocab.items():
            self.label[i] = s
        made: dict[bytes, list[int]] = {}
        for k, (u, v) in enumerate(merges):
            made.setdefault(u + v, []).append(k)
        ranks = {p: k for k, p in reversed(list(enumerate(merges)))}
        use = set(range(len(merges)))
        for s, ks in made.items():
            if len(ks) > 1:  # of several merges to one token, the one that makes it
                use.difference_update(ks)
                if (pair := merged(s, ranks)) is not None:
                    use.add(ranks[pair])
        gadgets = [(k, vocab[u], vocab[v], vocab[u + v]) for k, (u, v) in enumerate(merges) if k in use]
        singles = [i for s, i in vocab.items() if len(s) == 1]
        self._number(n, singles, gadgets)
        kind = "H" if self._numbers < 1 << 16 else "I"
        rows: list[array | None] = [None] * n
        for i in singles:
            rows[i] = array(kind, [0, self._numbers])
        when = {w: k for k, _, _, w in gadgets}
        for k, u, v, w in gadgets:
            if max(when.get(u, -1), when.get(v, -1)) > k:
                raise ValueError(f"merge {k} does not follow from those before it")
            self._gadget(rows, k, u, v, w)
        # equal rows are one state; state 0 is the start, behind which every live label goes on
        known: dict[bytes | None, int] = {None: 0}
        numbers = list(range(self._numbers + 1))  # one object a number, however often it occurs
        self.arcs, self.first, self.behind = [0, self._numbers], [0, 2], [-1] * n
        for i, row in enumerate(rows):
            if row is None:
                continue
            state = known.setdefault(row.tobytes(), len(known))
            if state == len(self.first) - 1:
                self.arcs += map(numbers.__getitem__, row)
                self.first.append(len(self.arcs))
            self.behind[i] = state
        self.row = [(self.first[x], self.first[x + 1]) if x >= 0 else (0, 0) for x in self.behind]
        self.live = {self.label[i]: i for i in range(n) if rows[i] is not None}
        # every end of a live label, with the label it is (-1 if none), to find what may end at a place
        self.ends: dict[bytes, int] = {}
        for s in self.live:
            for e in range(len(s) - 1, 0, -1):
                if s[e:] not in self.ends:
                    self.ends[s[e:]] = -1
        self.ends.update(self.live)

    def _number(self, n: int, singles: list[int], gadgets: list[tuple[int, int, int, int]]) -> None:
        """Number labels in preorder of the tree in which a token hangs below its first half, latest ones first."""
        self._below: list[list[tuple[int, int]]] = [[] for _ in range(n)]  # (merge, token), in order of merges
        for k, u, _, w in gadgets:
            self._below[u].append((k, w))
        self.number, order, stack = [-1] * n, [], list(reversed(singles))
        while stack:
            x = stack.pop()
            self.number[x] = len(order)
            order.append(x)
            stack += [w for _, w in self._below[x]]
        self._numbers = len(order)
        self._span = [1] * n
        for x in reversed(order):
            self._span[x] += sum(self._span[w] for _, w in self._below[x])

    def _gadget(self, rows: list, k: int, u: int, v: int, w: int) -> None:
        """Fork the state behind u without the arc v and what is made from it later, and begin the state behind w."""
        row, low = rows[u], self.number[v]
        if row is None or rows[v] is None or not bisect_right(row, low) & 1:
            return  # no accepted sequence has v behind u by now
        rows[w] = rows[v][:]
        high = low + 1
        for born, token in reversed(self._below[v]):
            if born < k:
                break
            high += self._span[token]
        a, b = bisect_left(row, low), bisect_right(row, high)
        rows[u] = row[:a] + array(row.typecode, [low] * (a & 1) + [high] * (b & 1)) + row[b:]

    @property
    def states(self) -> int:
        return len(self.first) - 1

    def step(self, state: int, label: int) -> int:
        """The state that an arc leads to, or -1 if there is no such arc."""
        low = self.first[state]
        return self.behind[label] if (bisect_right(self.arcs, self.number[label], low, self.first[state + 1]) - low) & 1 else -1

    def encode(self, word: bytes) -> tuple[int, ...]:
        """The one accepted token sequence that spells the word."""
        if (whole := self.live.get(word)) is not None:
            return (whole,)
        n, ends, arcs, number, row = len(word), self.ends, self.arcs, self.number, self.row
        last = [-2] * (n + 1)  # the token that ends at a place; -2: not asked for yet, -1: none, as a byte is no token

        def settle(end: int) -> int:
            """The last token of the sequence that spells word[:end]."""
            found, at = [], end - 1
            while at >= 0 and (label := ends.get(word[at:end])) is not None:
                if label >= 0:
                    found.append((at, label))
                at -= 1
            for at, label in reversed(found):
                if at:
                    before = last[at]
                    if before < 0 and (before == -1 or (before := settle(at)) < 0):
                        continue
                    low, high = row[before]
                    if not bisect_right(arcs, number[label], low, high) - low & 1:
                        continue
                last[end] = label
                return label
            last[end] = -1
            return -1

        for at in range(_STRIDE, n, _STRIDE):  # so that no question goes far back
            settle(at)
        settle(n)
        out, at = [], n
        while at:
            if (label := last[at]) < 0:
                raise ValueError(f"no token sequence spells {word!r}")
            out.append(label)
            at -= len(self.label[label])
        return tuple(reversed(out))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.label.__getitem__, ids))


class ByteBpe:
    """Encoder and decoder of a byte-level BPE file: added tokens, word splitting, automaton, caches."""

    _loaded: dict[tuple[str, int], "ByteBpe"] = {}

    def __init__(self, path: str, cache: int = CACHE):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        letters = byte_letters()
        raw = lambda s: bytes(letters[c] for c in s)
        vocab = {raw(s): i for s, i in spec["model"]["vocab"].items()}
        merges = [m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"]]
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.automaton = Automaton(vocab, [(raw(a), raw(b)) for a, b in merges])
        top = max([len(self.automaton.label) - 1, *self.added.values()])
        self.label = self.automaton.label + [b""] * (top + 1 - len(self.automaton.label))
        for s, i in self.added.items():
            self.label[i] = s.encode()
        self.digits = [str(i) for i in range(top + 1)]
        self.split_added = re.compile("|".join(re.escape(s) for s in sorted(self.added, key=len, reverse=True))) if self.added else None
        self.segments, self.words = Bounded(2 * cache // 3), Bounded(cache // 3)

    @classmethod
    def of(cls, path: str, cache: int = CACHE) -> "ByteBpe":
        claim(f"bpe {path} {cache}", cls._loaded.clear)
        if (path, cache) not in cls._loaded:
            cls._loaded[path, cache] = cls(path, cache)
        return cls._loaded[path, cache]

    def _word(self, w: str) -> tuple[int, ...]:
        ids = self.words.find(w)
        if ids is None:
            raw = w.encode()
            ids = self.automaton.encode(raw)
            if len(raw) < 64:
                self.words.keep(w, ids, 220 + len(raw) + 8 * len(ids))
        return ids

    def _segment(self, s: str) -> tuple[int, ...]:
        if s[-1] in "\t\n\r\f\v" or s.isspace():
            return self.automaton.encode(s.encode())
        words = _INNER.findall(s)
        if len(words) == 1:
            return self.automaton.encode(s.encode())
        return tuple(i for w in words for i in self._word(w))

    def _plain(self, text: str, out: list[int]) -> None:
        known, get = self.segments, self.segments.young.get
        for s in _OUTER.findall(text):
            ids = get(s)
            if ids is None:
                ids = known.find(s)
                if ids is None:
                    ids = self._segment(s)
                    if len(s) < 64:
                        known.keep(s, ids, 220 + len(s) + 8 * len(ids))
            out += ids

    def encode(self, text: str) -> list[int]:
        out: list[int] = []
        at = 0
        if self.split_added:
            for m in self.split_added.finditer(text):
                self._plain(text[at : m.start()], out)
                out.append(self.added[m[0]])
                at = m.end()
        self._plain(text[at:] if at else text, out)
        return out

    def decode(self, ids: list[int]) -> str:
        return b"".join(map(self.label.__getitem__, ids)).decode("utf-8", "replace")


def encode_column(docs: DataFrame, tokenizer: str, text_col: str = "text", ids_col: str = "ids", cache: int = CACHE) -> DataFrame:
    """docs with a column of ids (array of int); a column of that name is replaced. cache: bytes a worker may keep."""
    docs = docs.drop(ids_col)
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = ByteBpe.of(tokenizer, cache)
        for b in slices(batches, 256, 8 << 20):
            ids = [bpe.encode(t or "") for t in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(ids, pa.list_(pa.int32()))], names=[*b.schema.names, ids_col])

    return docs.mapInArrow(released(run), T.StructType([*docs.schema.fields, T.StructField(ids_col, T.ArrayType(T.IntegerType()))]))


def decode_column(rows: DataFrame, tokenizer: str, ids_col: str = "ids", text_col: str = "decoded") -> DataFrame:
    """rows with the text that the ids spell; null ids give null."""
    rows = rows.drop(text_col)
    at = rows.columns.index(ids_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = ByteBpe.of(tokenizer)
        for b in slices(batches, 256, 32 << 20):
            texts = [None if i is None else bpe.decode(i) for i in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(texts, pa.string())], names=[*b.schema.names, text_col])

    return rows.mapInArrow(released(run), T.StructType([*rows.schema.fields, T.StructField(text_col, T.StringType())]))


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: ids and decoded text as digests, in one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = ByteBpe.of(tokenizer)
        digit = bpe.digits.__getitem__
        for b in slices(batches, 256, 8 << 20):
            n, ids_sha, text_sha = [], [], []
            for raw in utf8(b, "text"):
                ids = bpe.encode(raw.decode())
                n.append(len(ids))
                ids_sha.append(hashlib.sha256(",".join(map(digit, ids)).encode()).hexdigest())
                text_sha.append(hashlib.sha256(bpe.decode(ids).encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op10_bpe_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of every whole text and their decoding, as digests."""
    import public_tokenizers

    return digests(table(spark, sf_dir, "documents"), str(public_tokenizers.path("byte_bpe_50k.json")))
