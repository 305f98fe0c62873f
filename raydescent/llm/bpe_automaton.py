"""Byte-pair encoding by a deterministic automaton, and decoding by its arc labels.

First an automaton over tokens. A state is the last token read; an arc says which token may follow. It is built by one
gadget for each merge u v -> w, in the order of the merges: arcs for w are added wherever u could be entered, w's state
takes the exits that v's state has at that moment, and the arc v leaves u's state. What remains after all gadgets accepts,
of all ways to spell a word in tokens, only the one that the merges produce. Written out, the arcs of 50,000 states would
be 50,000 x 50,000 bits, so a gadget is kept as three table entries (entered as, exits as, arc cut), and an arc is looked up
by going back through the gadgets.

Then an automaton over bytes, made deterministic from the first and the trie of the tokens' spellings. Its state stands for
all ways in which the word may go on: the pairs (last token so far, place in the trie since). Every prefix of a word has one
valid spelling, so that of the tokens that a byte completes just one may follow its pair's token: it is the arc's label, the
last token of the prefix. Encoding is one table look-up per byte, without going back; the labels are then read from the
word's end. The table is compiled once, on the driver, for all prefixes of all tokens, and broadcast. Arcs beyond (words that
no token starts with can be of any length, and so can the states they need) are added by the worker that meets them, up to
a limit, at which it returns to the compiled table.

Words come from the tokenizer's own splitting rule.
"""

from __future__ import annotations

import hashlib
import json
import re
import unicodedata
from array import array
from functools import lru_cache

import numpy as np

#: Below this code point the splitting rule's classes are those of any Unicode version; texts beyond are split by the library.
LATIN_END = 0x250
_BEYOND = re.compile("[^\u0000-ɏ]")


def byte_symbols() -> dict[str, int]:
    """The printable character that byte-level vocabularies write for each byte: itself where printable, else the next free one from U+0100."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    rest = [b for b in range(256) if b not in plain]
    return {chr(b): b for b in plain} | {chr(0x100 + i): b for i, b in enumerate(rest)}


def latin_class(first: str) -> str:
    """A regular-expression class body of the characters below LATIN_END whose category starts with first."""
    return "".join(f"\\u{c:04x}" for c in range(LATIN_END) if unicodedata.category(chr(c)).startswith(first))


def splitting_rule() -> re.Pattern:
    letters, numbers, space = latin_class("L"), latin_class("N"), "\\t\\n\\x0b\\x0c\\r\\x20\\x85\\xa0"
    short = "'s|'t|'re|'ve|'m|'ll|'d"
    return re.compile(f"{short}| ?[{letters}]+| ?[{numbers}]+| ?[^{space}{letters}{numbers}]+|[{space}]+(?![^{space}])|[{space}]+")


#: Labels take this many bits of a table entry.
LABEL_BITS = 24
_LABEL = (1 << LABEL_BITS) - 1


class TokenAutomaton:
    """merges: pairs of token ids and the id of the token they make, in order. base: id of each symbol (a byte)."""

    def __init__(self, spelling: list[bytes], base: list[int], merges: list[tuple[int, int, int]], most_extra: int = 200_000):
        n = len(spelling)
        self.spelling, self.most_extra = spelling, most_extra
        self.sizes = [len(x) for x in spelling]
        self.born = [0] * n
        self.enters_as, self.exits_as = list(range(n)), list(range(n))
        self.cut_at: dict[int, int] = {}
        self.size = n
        self.trie: dict[int, int] = {}
        self.token_at: list[int] = [-1]
        for token in base:
            self._spell(token)
        for number, (u, v, w) in enumerate(merges, 1):
            self._gadget(number, u, v, w)
        self.inner = {key >> 8 for key in self.trie}  # trie nodes from which a byte leads on
        self.states: list[bytes] = []  # each the 64-bit numbers of its pairs
        self.number: dict[bytes, int] = {}
        self.table: dict[int, int] = {}
        self._state([0])  # before the first byte: no last token (0, tokens count from 1), at the trie's root
        self._compile()

    def _compile(self) -> None:
        """Arcs for every prefix of every token, walking the trie from its root."""
        children: dict[int, list[tuple[int, int]]] = {}
        for key, node in self.trie.items():
            children.setdefault(key >> 8, []).append((key & 255, node))
        todo = [(0, 0)]
        while todo:
            node, state = todo.pop()
            for byte, child in children.get(node, ()):
                todo.append((child, self._extend(state, byte) >> LABEL_BITS))
        self.compiled_states, self.compiled_arcs = len(self.states), len(self.table)
        self._base = dict(self.table)

    def __getstate__(self):
        own = dict(self.__dict__)
        del own["_base"], own["number"], own["inner"]
        own["table"] = tuple(np.fromiter(x, np.int64, self.compiled_arcs) for x in (self._base, self._base.values()))
        own["states"] = self.states[: self.compiled_states]
        return own

    def __setstate__(self, own):
        self.__dict__.update(own)
        keys, values = own["table"]
        self._base = dict(zip(keys.tolist(), values.tolist()))
        self.inner = {key >> 8 for key in self.trie}
        self._reset()

    def _reset(self) -> None:
        """Back to the compiled arcs."""
        del self.states[self.compiled_states :]
        self.table, self.number = dict(self._base), {pairs: i for i, pairs in enumerate(self.states)}

    def _state(self, alive: list[int]) -> int:
        pairs = array("q", alive).tobytes()
        found = self.number.get(pairs)
        if found is None:
            found = self.number[pairs] = len(self.states)
            self.states.append(pairs)
        return found

    def _extend(self, state: int, byte: int) -> int:
        """Make the arc of a state under a byte: its entry is the next state and the label."""
        alive, label = [], -1
        for pair in memoryview(self.states[state]).cast("q"):
            last, node = pair >> 32, pair & 0xFFFFFFFF
            node = self.trie.get(node << 8 | byte)
            if node is None:
                continue
            token = self.token_at[node]
            if token >= 0 and (not last or self.arc(last - 1, token)):
                label = token
            if node in self.inner:
                alive.append(last << 32 | node)
        if label < 0:
            raise ValueError(f"the vocabulary has no token for byte {byte}")
        alive.append(label + 1 << 32)
        if len(self.states) - getattr(self, "compiled_states", len(self.states)) > self.most_extra:
            self._reset()
            return self._state(alive) << LABEL_BITS | label
        entry = self.table[state << 8 | byte] = self._state(alive) << LABEL_BITS | label
        return entry

    def _gadget(self, number: int, u: int, v: int, w: int) -> None:
        self.born[w], self.enters_as[w], self.exits_as[w] = number, u, v
        self.cut_at[u * self.size + v] = number
        self._spell(w)

    def _spell(self, token: int) -> None:
        node = 0
        for b in self.spelling[token]:
            key = node << 8 | b
            node = self.trie.setdefault(key, len(self.token_at))
            if node == len(self.token_at):
                self.token_at.append(-1)
        self.token_at[node] = token

    def arc(self, a: int, b: int) -> bool:
        """Whether token b may follow token a."""
        born, before = self.born, 1 << 60  # only gadgets with a smaller number have been applied
        while True:
            if self.cut_at.get(a * self.size + b, before) < before:
                return False
            if born[a] == 0 == born[b]:
                return True
            if born[b] >= born[a]:
                before = min(before, born[b] + 1)  # b is entered where its first part is, after its own gadget's cut
                b = self.enters_as[b]
            else:
                before = min(before, born[a])  # a took the exits of its second part before its own gadget's cut
                a = self.exits_as[a]

    def encode_word(self, word: bytes) -> list[int]:
        """One look-up per byte; then the last token of each prefix, from the whole word back to its start."""
        get, state, last = self.table.get, 0, []
        for byte in word:
            entry = get(state << 8 | byte)
            if entry is None:
                entry = self._extend(state, byte)
                get = self.table.get
            state = entry >> LABEL_BITS
            last.append(entry & _LABEL)
        path, at = [], len(last)
        while at:
            token = last[at - 1]
            path.append(token)
            at -= self.sizes[token]
        path.reverse()
        return path


class ByteBpe:
    """Texts to ids and back with a byte-level vocabulary file of the tokenizers library (its JSON text)."""

    def __init__(self, source: str, specials_are_text: bool = False, most_words: int = 300_000):
        spec = json.loads(source)
        vocab, merges = spec["model"]["vocab"], spec["model"]["merges"]
        symbols = byte_symbols()
        self.specials = {} if specials_are_text else {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *self.specials.values()]) + 1
        spelling = [b""] * size
        for name, token in vocab.items():
            spelling[token] = bytes(symbols[c] for c in name)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in merges]
        self.automaton = TokenAutomaton(spelling, [vocab[c] for c in symbols], [(vocab[a], vocab[b], vocab[a + b]) for a, b in pairs])
        self.labels = list(spelling)
        for name, token in self.specials.items():
            self.labels[token] = name.encode()
        self.words = _Words(self.automaton, most_words)
        self.rule = splitting_rule()
        self.special_rule = re.compile("(" + "|".join(map(re.escape, self.specials)) + ")") if self.specials else None
        self._library = None
        self.source = source

    def __getstate__(self):
        return self.__dict__ | {"_library": None, "words": self.words.most}

    def __setstate__(self, own):
        self.__dict__.update(own)
        self.words = _Words(self.automaton, own["words"])

    def _split(self, text: str) -> list[str]:
        if not _BEYOND.search(text):
            return self.rule.findall(text)
        if self._library is None:
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_str(self.source).pre_tokenizer, byte_symbols()
        splitter, symbols = self._library
        return [bytes(symbols[c] for c in w).decode() for w, _ in splitter.pre_tokenize_str(text)]

    def encode(self, text: str) -> bytes:
        """The ids as little-endian unsigned 32-bit integers."""
        get = self.words.__getitem__
        if self.special_rule is None or not self.special_rule.search(text):
            return b"".join(map(get, self._split(text)))
        out = []
        for part in self.special_rule.split(text):
            out += [self.specials[part].to_bytes(4, "little")] if part in self.specials else map(get, self._split(part))
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        raw = b"".join(map(self.labels.__getitem__, np.frombuffer(ids, "<u4").tolist()))
        return raw.decode("utf-8", "replace")


class _Words(dict):
    """Ids of words already encoded; emptied when full, so that its memory is bounded whatever the texts are."""

    def __init__(self, automaton: TokenAutomaton, most: int):
        self.automaton, self.most = automaton, most
        self.wire = [i.to_bytes(4, "little") for i in range(automaton.size)]

    def __missing__(self, word: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        wire = self.wire
        made = b"".join([wire[t] for t in self.automaton.encode_word(word.encode("utf-8", "surrogatepass"))])
        if len(word) <= 64:
            self[word] = made
        return made


@lru_cache(maxsize=4)
def compiled(source: str, specials_are_text: bool = False) -> ByteBpe:
    """The compiled automaton of a vocabulary, made once per driver."""
    return ByteBpe(source, specials_are_text)


def sent(spark, vocabulary: str, specials_are_text: bool = False):
    """The compiled automaton of the vocabulary file as a broadcast variable; its size does not depend on the data."""
    return spark.sparkContext.broadcast(compiled(read_vocabulary(vocabulary), specials_are_text))


def read_vocabulary(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def encode_digests(docs, vocabulary: str, id_col: str = "doc_id", text_col: str = "text"):
    """id, n_tokens, ids_sha256 and decoded_sha256 of every whole text. Null is empty: no tokens, digests of nothing.

    vocabulary: path of the JSON file, read and compiled by the driver.
    """
    from pyspark.sql import functions as F

    held = sent(docs.sparkSession, vocabulary)

    def run(batches):
        import pyarrow as pa

        bpe = held.value
        for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
            rows = []
            for text in batch.column("text").to_pylist():
                ids = bpe.encode(text or "")
                rows.append((len(ids) // 4, hashlib.sha256(ids).hexdigest(), hashlib.sha256(bpe.decode(ids).encode("utf-8", "surrogatepass")).hexdigest()))
            n, a, b = zip(*rows) if rows else ((), (), ())
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())], [id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return rows.mapInArrow(run, f"`{id_col}` long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode_texts(docs, vocabulary: str, text_col: str = "text", out_col: str = "token_ids"):
    """docs with the ids of each whole text as array<int> (replacing a column of that name); null is empty."""
    from collections.abc import Iterator

    import pandas as pd
    from pyspark.sql import functions as F

    held = sent(docs.sparkSession, vocabulary)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bpe = held.value
        for texts in batches:
            yield pd.Series([np.frombuffer(bpe.encode(t or ""), "<u4").astype(np.int32) for t in texts])

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return docs.withColumn(out_col, F.pandas_udf(run, "array<int>")(F.col(text_col)))


def decode_texts(docs, vocabulary: str, ids_col: str = "token_ids", out_col: str = "text"):
    """docs with the text of each list of ids; null ids are no ids."""
    from collections.abc import Iterator

    import pandas as pd
    from pyspark.sql import functions as F

    held = sent(docs.sparkSession, vocabulary)

    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        bpe = held.value
        for lists in batches:
            yield pd.Series(["" if x is None else bpe.decode(np.asarray(x, "<u4").tobytes()) for x in lists])

    run.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return docs.withColumn(out_col, F.pandas_udf(run, "string")(F.col(ids_col)))
