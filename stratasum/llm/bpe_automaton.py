"""Byte-pair encoding by an automaton, and decoding by its arc labels.

The merges are compiled, in their order, into a deterministic automaton over tokens whose paths are
exactly the right tokenizations. It begins as one state with an arc for every byte. The gadget of a
merge (a, b) -> c does three things: the state that `a` leads to loses its arc `b`; every state that
has an arc `a` gets an arc `c`; and `c` leads to a copy of the state that `b` leads to. Since all
arcs with the same label lead to the same state, a state is named by its label, and the gadgets are
kept as three columns (rank, left part, right part) instead of 50,000 x 50,000 arcs: `has_arc`
replays those gadgets that touch one arc, newest first.

Each prefix of a word has exactly one path, so reading a word byte by byte needs, for each prefix,
only the label of the last arc: the one token that ends there whose arc leaves the state reached
before it. The transition table (set of open trie nodes with their states, byte) -> next set is
filled when first needed and kept while it is small; states that differ only in arcs which no open
node can still use are one.

Defined results: null and empty texts have no tokens; any text, however long, is encoded whole;
repeated rows give repeated results; other columns than doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
import json
import re
from functools import partial
from itertools import chain

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import map_texts, table

#: Words kept with their tokens in one Python worker; it starts anew when full.
WORDS_KEPT = 200_000
#: Entries of the transition table kept in one Python worker.
STEPS_KEPT = 400_000
#: States are told apart below a trie node by at most so many tokens; above that, by name.
FEW = 24
#: Arcs that are known without a replay; steps need them only when they are made.
ARCS_KEPT = 100_000
#: Below this code point the pattern's classes are the same in all versions of Unicode that are in use.
SETTLED = 0x530


def byte_letters() -> dict[str, int]:
    """The printable letter that stands for each byte in byte-level vocabularies, as a rule."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class TokenAutomaton:
    """merges: pairs of token ids with the id of their union, in order; labels: bytes of each id."""

    def __init__(self, labels: dict[int, bytes], merges: list[tuple[int, int, int]]):
        self.labels = labels
        self.born = {c: (rank, a, b) for rank, (a, b, c) in enumerate(merges)}
        self.lost = {(a, b): rank for rank, (a, b, _) in enumerate(merges)}
        self.trie: list[dict[int, int]] = [{}]
        self.ends: list[int] = [-1]
        for token, label in labels.items():
            if len(label) == 1 or token in self.born:
                node = 0
                for byte in label:
                    if byte not in self.trie[node]:
                        self.trie[node][byte] = len(self.trie)
                        self.trie.append({})
                        self.ends.append(-1)
                    node = self.trie[node][byte]
                self.ends[node] = token
        self.below: list[tuple[int, ...] | None] = [()] * len(self.trie)
        for node in range(len(self.trie) - 1, -1, -1):  # children have larger numbers
            found = [(self.ends[child],) * (self.ends[child] >= 0) + (self.below[child] or ()) for child in self.trie[node].values()]
            if any(self.below[child] is None for child in self.trie[node].values()) or sum(map(len, found)) > FEW:
                self.below[node] = None
            else:
                self.below[node] = tuple(chain.from_iterable(found))
        self._arcs: dict[int, bool] = {}
        self._reset()

    def _reset(self) -> None:
        start = ((-1, 0),)
        self._ids = {start: 0}
        self._sets = [start]
        self._last = [-1]
        self._next: dict[int, int] = {}
        self._same: dict[tuple[int, int], tuple[int, int] | None] = {}
        self._first: dict[tuple[int, int], tuple[int, int]] = {}

    def has_arc(self, state: int, label: int) -> bool:
        """Whether the state reached by token `state` (-1: the start) has the arc `label` after all gadgets."""
        if state < 0:
            return True
        key = state << 32 | label
        known = self._arcs.get(key)
        if known is None:
            known = self._replay(state, label)
            if len(self._arcs) >= ARCS_KEPT:
                self._arcs.clear()
            self._arcs[key] = known
        return known

    def _replay(self, state: int, label: int) -> bool:
        limit = len(self.born)
        while True:
            if self.lost.get((state, label), limit) < limit:
                return False
            s, t = self.born.get(state), self.born.get(label)
            if s is None and t is None:
                return True
            if t is not None and (s is None or t[0] >= s[0]):
                label, limit = t[1], t[0] + 1  # the arc came where the arc of its left part was, after the loss
            else:
                state, limit = s[2], s[0]  # the state is a copy, made before the loss

    def _alike(self, state: int, node: int) -> tuple[int, int] | None:
        """One name for all states that have the same arcs to the tokens below a trie node; none if they have no such arc."""
        if (state, node) not in self._same:
            mask = sum(1 << i for i, token in enumerate(self.below[node]) if self.has_arc(state, token))
            self._same[state, node] = self._first.setdefault((node, mask), (state, node)) if mask else None
        return self._same[state, node]

    def _step(self, at: int, byte: int) -> int:
        moved, last = [], -1
        for state, node in self._sets[at]:
            after = self.trie[node].get(byte)
            if after is not None:
                token = self.ends[after]
                if token >= 0 and last < 0 and self.has_arc(state, token):
                    last = token
                pair = (state, after) if self.below[after] is None else self._alike(state, after)
                if pair:
                    moved.append(pair)
        if last >= 0:
            moved.append((last, 0))
        moved = tuple(moved)
        found = self._ids.get(moved)
        if found is None:
            found = self._ids[moved] = len(self._sets)
            self._sets.append(moved)
            self._last.append(last)
        self._next[at << 8 | byte] = found
        return found

    def encode(self, word: bytes) -> tuple[int, ...]:
        """The tokens of one pre-split word."""
        if len(self._next) > STEPS_KEPT or len(self._same) > 2 * STEPS_KEPT:
            self._reset()
        table, last, at, ends = self._next, self._last, 0, []
        for byte in word:
            nxt = table.get(at << 8 | byte)
            at = self._step(at, byte) if nxt is None else nxt
            ends.append(last[at])
        out, i, labels = [], len(word), self.labels
        while i:
            token = ends[i - 1]
            out.append(token)
            i -= len(labels[token])
        return tuple(reversed(out))


class _Words(dict):
    """Per word: number of tokens, decimal ids, bytes that its arcs emit, ids. The words of the last generation stay at hand."""

    def __init__(self, automaton: TokenAutomaton, most: int):
        super().__init__()
        self.automaton, self.most = automaton, most
        self.before: dict = {}

    def __missing__(self, word: str) -> tuple[int, str, bytes, tuple[int, ...]]:
        out = self.before.get(word)
        if out is None:
            ids = self.automaton.encode(word.encode())
            out = len(ids), ",".join(map(str, ids)), b"".join(map(self.automaton.labels.__getitem__, ids)), ids
        if len(self) >= self.most:
            self.before = dict(self)
            self.clear()
        self[word] = out
        return out


def _settled_pattern(pattern: str) -> re.Pattern:
    """The splitting pattern for texts below SETTLED with its classes written out, for the quicker `re`."""

    def ranges(wanted: str) -> str:
        out, start = "", None
        of = regex.compile(wanted)
        for cp in range(SETTLED + 1):
            inside = cp < SETTLED and bool(of.match(chr(cp)))
            if inside and start is None:
                start = cp
            elif not inside and start is not None:
                out, start = out + f"\\u{start:04x}-\\u{cp - 1:04x}", None
        return out

    letters, digits, space = ranges(r"\p{L}"), ranges(r"\p{N}"), ranges(r"\s")
    for short, full in ((r"[^\s\p{L}\p{N}]", f"[^{space}{letters}{digits}]"), (r"\p{L}", f"[{letters}]"), (r"\p{N}", f"[{digits}]"), (r"\S", f"[^{space}]"), (r"\s", f"[{space}]")):
        pattern = pattern.replace(short, full)
    return re.compile(pattern)


class Tokenizer:
    """Splits a text into words, words into tokens, and turns tokens back into text.

    path: a tokenizer file of the public JSON form with a byte-level BPE model.
    """

    def __init__(self, path: str, words_kept: int = WORDS_KEPT):
        import public_tokenizers
        from tokenizers.pre_tokenizers import ByteLevel

        with open(path, encoding="utf-8") as f:
            form = json.load(f)
        letters, vocab = byte_letters(), form["model"]["vocab"]
        labels = {i: bytes(letters[c] for c in piece) for piece, i in vocab.items()}
        pairs = (m if isinstance(m, list) else m.split(" ") for m in form["model"]["merges"])
        merges = [(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs]
        self.added = {x["content"]: x["id"] for x in form["added_tokens"]}
        self.automaton = TokenAutomaton(labels, merges)
        self.words = _Words(self.automaton, words_kept)
        self.labels = dict(labels) | {i: s.encode() for s, i in self.added.items()}
        self._added = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        self._settled = _settled_pattern(public_tokenizers.PATTERN)
        self._other = re.compile(f"[\\u{SETTLED:04x}-\\U0010ffff]")
        self._library = ByteLevel(add_prefix_space=False, use_regex=True)

    def split(self, text: str) -> list[str]:
        """Words of a text. Past SETTLED the library's own splitter decides, as its Unicode tables are its own."""
        if self._other.search(text) is None:
            return self._settled.findall(text)
        return [text[a:b] for _, (a, b) in self._library.pre_tokenize_str(text)]

    def parts(self, text: str) -> list[tuple[int, str, bytes, tuple[int, ...]]]:
        """What is known of each word and each added token of a text, in order."""
        if self._added is None or self._added.search(text) is None:
            return list(map(self.words.__getitem__, self.split(text)))
        out = []
        for piece in self._added.split(text):
            if piece in self.added:
                token = self.added[piece]
                out.append((1, str(token), piece.encode(), (token,)))
            else:
                out.extend(map(self.words.__getitem__, self.split(piece)))
        return out

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(p[3] for p in self.parts(text)))

    def decode(self, ids: list[int]) -> str:
        """The labels of the arcs, joined; bytes that are no UTF-8 become U+FFFD."""
        return b"".join(map(self.labels.__getitem__, ids)).decode("utf-8", "replace")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def encode(df: DataFrame, path: str | None = None, ids: bool = True, words_kept: int = WORDS_KEPT) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 and, if `ids`, the array of ids, of each row of (doc_id, text).

    The vocabulary file must be at the same path on each executor. No shuffle.
    """
    path = path or default_path()

    def make(tok: Tokenizer):
        def one(part: pa.RecordBatch) -> pa.RecordBatch:
            n, digest, back, all_ids = [], [], [], []
            for text in part.column("text").to_pylist():
                got = tok.parts(text or "")
                counts, digits, emitted, each = zip(*got) if got else ((), (), (), ())
                n.append(sum(counts))
                digest.append(hashlib.sha256(",".join(digits).encode()).hexdigest())
                back.append(hashlib.sha256(b"".join(emitted).decode("utf-8", "replace").encode()).hexdigest())
                if ids:
                    all_ids.append(list(chain.from_iterable(each)))
            out = [part.column("doc_id"), pa.array(n, pa.int64()), pa.array(digest), pa.array(back)]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if ids:
                out.append(pa.array(all_ids, pa.list_(pa.int32())))
                names.append("ids")
            return pa.RecordBatch.from_arrays(out, names)

        return one

    kind = dict(df.dtypes)["doc_id"]
    schema = f"doc_id {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids array<int>" * ids
    return map_texts(df.select("doc_id", "text"), schema, make, keeps=(("bpe", path, words_kept), partial(Tokenizer, path, words_kept)))


def op9_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), ids=False)
