"""BPE encoding and decoding with a merge-gadget token automaton.

The automaton reads *tokens*: a path from the start state spells a pre-split word, and the only
path that a word has is its BPE tokenisation. It is compiled by taking the merges in order of rank
and applying one gadget per merge ``u v -> t``:

* ``t`` gets the arcs into it that ``u`` had and the state behind it that ``v`` had;
* the arc labelled ``v`` is cut from the state behind ``u`` (that state is split off first if other
  tokens share it, and so is the arc class of ``v``);
* if ``u`` equals ``v``, the arc labelled ``t`` is cut there as well, because merging runs left to
  right.

States and arc classes are shared until a gadget has to split them, so the transition table is one
bit per (state, arc class). Encoding walks all words of a batch together: a trie finds every token
occurrence, and position by position the table admits exactly one token that ends there. Decoding
emits the arc labels.

Pre-splitting follows the tokenizer file: NFC, white space, lower case, the split pattern, bytes.
Words between white space are independent of each other, so results are kept per word in a bounded
table; the table only saves work, it never changes a result.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import WordTable, process_table, sheltered, table, text_column

#: Fixed value of the vocabulary file: its end-of-word mark.
WORD_END = "</w>"
#: Control characters that str.split() takes for white space and the pattern does not.
_NOT_SPACE = ("\x1c", "\x1d", "\x1e", "\x1f")
_SPACES = regex.compile(r"[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+")
#: Words in a generation of a worker's table (about 60 MB).
WORD_TABLE = 150_000


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    keep = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out = [""] * 256
    for b in keep:
        out[b] = chr(b)
    for n, b in enumerate(x for x in range(256) if not out[x]):
        out[b] = chr(256 + n)
    return out


def split_pattern(config: dict) -> str:
    """The pattern by which a tokenizer file splits words."""
    found = [x["pattern"]["Regex"] for x in config["pre_tokenizer"]["pretokenizers"] if x["type"] == "Split"]
    if len(found) != 1:
        raise ValueError("the file must have one split pattern")
    return found[0]


def odd_characters(pattern: str) -> tuple[str, str]:
    """Characters that the library and ``regex`` class differently, and for each one that both class alike.

    Only code points that this Python does not know can differ: the two follow other versions of the
    standard. Planes 4 to 13 are empty in all versions.
    """
    from tokenizers import Regex, normalizers, pre_tokenizers

    asked = [chr(c) for c in range(0x40000) if unicodedata.category(chr(c)) == "Cn"]
    split, lower = pre_tokenizers.Split(Regex(pattern), "removed", invert=True), normalizers.Lowercase()
    mine = regex.compile(pattern)
    odd, like = [], []
    for lo in range(0, len(asked), 20_000):
        some = asked[lo : lo + 20_000]
        text = "".join(f"a{c}{c} " for c in some)
        theirs: list[list[str]] = [[] for _ in some]
        for piece, (at, _) in split.pre_tokenize_str(text):
            theirs[at // 4].append(piece)
        for c, pieces in zip(some, theirs):
            small = lower.normalize_str(c)
            if pieces != mine.findall(f"a{c}{c}") or small != c.lower():
                odd.append(c)
                like.append("\u02b0" if len(pieces) == 1 and len(pieces[0]) == 3 else "\u00bd" if len(pieces) == 3 else "\u00a7")  # a letter, a number, a sign
    return "".join(odd), "".join(like)


def chunks_of(text: str) -> list[str]:
    """The parts of a text between the pattern's white space."""
    if any(c in text for c in _NOT_SPACE):
        return [x for x in _SPACES.split(text) if x]
    return text.split()


def _library_lower(c: str) -> str:
    from tokenizers import normalizers

    return normalizers.Lowercase().normalize_str(c)


class TokenAutomaton:
    """Deterministic automaton over tokens; see the module's text."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]]):
        syms = byte_symbols()
        self.labels = [""] * (max(vocab.values()) + 1)
        for s, i in vocab.items():
            self.labels[i] = s
        code = {}
        for b, s in enumerate(syms):
            if s in vocab:
                code[vocab[s]] = (b,)
            if s + WORD_END in vocab:
                code[vocab[s + WORD_END]] = (256 + b,)
        n = len(self.labels)
        row, col = np.zeros(n, np.int32), np.zeros(n, np.int32)
        for i, c in code.items():
            row[i] = c[0] >= 256  # behind an end of word nothing follows
        row_n, col_n = [sum(c[0] < 256 for c in code.values()) + 1, sum(c[0] >= 256 for c in code.values())], [len(code)]
        cap_r, cap_c = 1 << 10, 1 << 10
        bits = np.zeros((cap_c, cap_r // 8), np.uint8)  # one arc class a line, one bit a state
        bits[0, 0] = 1 << 0
        n_r, n_c = 2, 1
        for a, b in merges:
            u, v, t = vocab[a], vocab[b], vocab[a + b]
            if t in code:
                raise ValueError(f"two merges give {a + b!r}")
            code[t] = code[u] + code[v]
            live = bits[col[v], row[u] >> 3] >> (row[u] & 7) & 1
            row[t], col[t] = row[v], col[u]
            row_n[row[v]] += 1
            col_n[col[u]] += 1
            cut = [v] if u != v else [v, t]
            if not live:  # this merge can never apply, so no arc leads to its token
                cut = []
            if live and row_n[row[u]] > 1:
                if n_r == cap_r:
                    bits = np.concatenate([bits, np.zeros_like(bits)], axis=1)
                    cap_r *= 2
                old = row[u]
                on = bits[:n_c, old >> 3] >> (old & 7) & 1
                bits[:n_c, n_r >> 3] |= (on << (n_r & 7)).astype(np.uint8)
                row_n[old] -= 1
                row_n.append(1)
                row[u] = n_r
                n_r += 1
            for y in [t] if not live else cut:
                if col_n[col[y]] > 1:
                    if n_c == cap_c:
                        bits = np.concatenate([bits, np.zeros_like(bits)], axis=0)
                        cap_c *= 2
                    bits[n_c] = bits[col[y]]
                    col_n[col[y]] -= 1
                    col_n.append(1)
                    col[y] = n_c
                    n_c += 1
                if live:
                    bits[col[y], row[u] >> 3] &= 0xFF ^ (1 << (row[u] & 7))
                else:
                    bits[col[y]] = 0
        self.row, self.col, self.bits = row, col, np.ascontiguousarray(bits[:n_c, : (n_r + 7) // 8])
        self.n_states, self.n_classes = n_r, n_c
        self._trie(code)

    def _trie(self, code: dict[int, tuple]) -> None:
        """Edges of the trie over byte symbols as one sorted key array (node * 512 + symbol)."""
        child: dict[int, int] = {}
        token = [-1]
        for i, path in code.items():
            node = 0
            for s in path:
                nxt = child.get(node * 512 + s)
                if nxt is None:
                    nxt = child[node * 512 + s] = len(token)
                    token.append(-1)
                node = nxt
            token[node] = i
        keys = np.array(sorted(child), np.int64)
        self.edge_key, self.edge_to = keys, np.array([child[k] for k in keys.tolist()], np.int32)
        self.node_token = np.array(token, np.int32)
        self.root = np.full(512, -1, np.int32)
        self.root[keys[keys < 512]] = self.edge_to[keys < 512]

    def allowed(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Table lookup: may token b follow token a?"""
        r = self.row[a]
        return (self.bits[self.col[b], r >> 3] >> (r & 7) & 1).astype(bool)

    def encode_words(self, words: list[bytes]) -> list[list[int]]:
        """Token ids of each non-empty word (UTF-8 bytes without the end mark)."""
        if not words:
            return []
        size = np.fromiter(map(len, words), np.int64, len(words))
        end = np.cumsum(size)
        sym = np.frombuffer(b"".join(words), np.uint8).astype(np.int64)
        sym[end - 1] += 256
        start_of = end - size
        word_end = np.repeat(end, size)
        rel = np.arange(len(sym)) - np.repeat(start_of, size)
        at = np.arange(len(sym))
        node = self.root[sym]
        if (node < 0).any():
            raise ValueError("a byte is missing from the vocabulary")
        arcs: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        pos = at.copy()  # the symbol read last
        while len(at):
            tok = self.node_token[node]
            hit = tok >= 0
            arcs.append((at[hit], pos[hit], tok[hit]))
            more = pos + 1 < word_end[at]
            at, pos, node = at[more], pos[more] + 1, node[more]
            key = node.astype(np.int64) * 512 + sym[pos]
            j = np.minimum(np.searchsorted(self.edge_key, key), len(self.edge_key) - 1)
            ok = self.edge_key[j] == key
            at, pos, node = at[ok], pos[ok], self.edge_to[j[ok]]
        a, z, t = (np.concatenate(x) for x in zip(*arcs))
        order = np.argsort(rel[z], kind="stable")
        a, z, t = a[order], z[order], t[order]
        bounds = np.concatenate([[0], np.cumsum(np.bincount(rel[z]))])
        row_at = np.zeros(len(sym), np.int32)  # state after the token that ends at a symbol
        tok_at = np.full(len(sym), -1, np.int32)
        back = np.zeros(len(sym), np.int64)
        for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
            s, e, k = a[lo:hi], z[lo:hi], t[lo:hi]
            r = np.where(rel[s] == 0, 0, row_at[s - 1])
            ok = ((self.bits[self.col[k], r >> 3] >> (r & 7) & 1) == 1) & ((rel[s] == 0) | (tok_at[s - 1] >= 0))
            s, e, k = s[ok], e[ok], k[ok]
            tok_at[e], row_at[e], back[e] = k, self.row[k], s
        out: list[list[int]] = [[] for _ in words]
        at, who = end - 1, np.arange(len(words))
        while len(at):
            for w, k in zip(who.tolist(), tok_at[at].tolist()):
                out[w].append(k)
            nxt = back[at]
            more = rel[nxt] > 0
            at, who = nxt[more] - 1, who[more]
        for x in out:
            x.reverse()
        return out


class WordBpe:
    """Pre-splitting, encoding and decoding for a word-end BPE tokenizer file."""

    def __init__(self, config: str | dict):
        d = json.loads(config) if isinstance(config, str) else config
        merges = [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in d["model"]["merges"]]
        self.automaton = TokenAutomaton(d["model"]["vocab"], merges)
        self.labels = self.automaton.labels + [""] * (1 + max([-1, *(x["id"] for x in d["added_tokens"])]) - len(self.automaton.labels))
        self.special = {x["content"]: x["id"] for x in d["added_tokens"]}
        for s, i in self.special.items():
            self.labels[i] = s
        self._special = regex.compile("(" + "|".join(regex.escape(s) for s in sorted(self.special, key=len, reverse=True)) + ")") if self.special else None
        pattern = split_pattern(d)
        self._split = regex.compile(pattern)
        odd, like = odd_characters(pattern)
        self._odd = frozenset(odd)
        self._like = str.maketrans(odd, like)
        self._lower = {ord(c): s for c in odd for s in [_library_lower(c)]}

    @classmethod
    def from_file(cls, path: str) -> WordBpe:
        with open(path, encoding="utf-8") as f:
            return cls(f.read())

    def pieces(self, chunk: str) -> list[str | int]:
        """Pre-split words of a text without white space; special tokens come as ids."""
        if self._special and "<" in chunk:
            out: list[str | int] = []
            for x in self._special.split(chunk):
                out += [self.special[x]] if x in self.special else self.pieces_plain(x)
            return out
        return self.pieces_plain(chunk)

    def pieces_plain(self, chunk: str) -> list[str]:
        if not chunk:
            return []
        if not chunk.isascii() and not self._odd.isdisjoint(chunk):
            text = unicodedata.normalize("NFC", chunk).replace("Σ", "σ")
            text = "".join(self._lower.get(ord(c)) or c.lower() for c in text)
            return [text[m.start() : m.end()] for m in self._split.finditer(text.translate(self._like))]
        return self._split.findall(unicodedata.normalize("NFC", chunk).replace("Σ", "σ").lower())

    def chunks(self, text: str) -> list[str]:
        return chunks_of(text)

    def encode_chunks(self, chunks: list[str]) -> list[list[int]]:
        parts = [self.pieces(c) for c in chunks]
        flat = dict.fromkeys(p for ps in parts for p in ps if isinstance(p, str))
        got = dict(zip(flat, self.automaton.encode_words([p.encode() for p in flat])))
        return [[i for p in ps for i in (got[p] if isinstance(p, str) else (p,))] for ps in parts]

    def encode(self, text: str) -> list[int]:
        return [i for x in self.encode_chunks(self.chunks(text)) for i in x]

    def decode(self, ids) -> str:
        """Arc labels joined by a space, as the file has no decoder."""
        return " ".join(map(self.labels.__getitem__, ids))


_COMPILED: dict[str, WordBpe] = {}


def compiled(path: str) -> WordBpe:
    """The automaton of a file, compiled once in this process."""
    if path not in _COMPILED:
        _COMPILED[path] = WordBpe.from_file(path)
    return _COMPILED[path]


def _word_table(m: WordBpe) -> WordTable:
    """(ids, decoded, number) per word, kept over the tasks of a worker."""

    def learn(words: list[str]) -> list[tuple[str, str, int]]:
        out = []
        for lo in range(0, len(words), 20_000):
            out += [(" ".join(map(str, ids)), m.decode(ids), len(ids)) for ids in m.encode_chunks(words[lo : lo + 20_000])]
        return out

    return process_table(("bpe", id(m)), lambda: WordTable(learn, WORD_TABLE))


def encode_documents(docs: DataFrame, path: str, text: str = "text", keep_ids: bool = False) -> DataFrame:
    """Encode and decode every whole ``text``.

    Adds n_tokens, ids_sha256, decoded_sha256 and, with ``keep_ids``, ids (array of int);
    columns of those names are replaced, others stay. Null or empty text: no
    tokens, digests of the empty string. The compiled automaton is broadcast; its size is bounded
    by the vocabulary, not by the data.
    """
    model = docs.sparkSession.sparkContext.broadcast(compiled(path))
    extra = "n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>" if keep_ids else "")
    kept = [c for c in docs.columns if c not in ("n_tokens", "ids_sha256", "decoded_sha256", *(("ids",) if keep_ids else ()))]
    src, restored = sheltered(docs.withColumn("the text", docs[text]).select(*[f"`{c}`" for c in kept], "the text"))
    kept = src.columns[:-1]
    src = src.withColumnRenamed("the text", "__text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = model.value
        known = _word_table(m)
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                split = [m.chunks(x) for x in text_column(part, "__text")]
                n, a, b, ids_out = [], [], [], []
                for got in known.lookup(split):
                    ids = " ".join([g[0] for g in got])
                    dec = " ".join([g[1] for g in got])
                    n.append(sum([g[2] for g in got]))
                    a.append(hashlib.sha256(ids.encode()).hexdigest())
                    b.append(hashlib.sha256(dec.encode()).hexdigest())
                    if keep_ids:
                        ids_out.append(list(map(int, ids.split())))
                cols = [part.column(c) for c in kept] + [pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(b, pa.string())]
                names = [*kept, "n_tokens", "ids_sha256", "decoded_sha256"]
                if keep_ids:
                    cols += [pa.array(ids_out, pa.list_(pa.int32()))]
                    names += ["ids"]
                yield pa.RecordBatch.from_arrays(cols, names=names)

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema if f.name != "__text")
    return restored(src.mapInArrow(run, f"{fields}, {extra}"))


def op2_bpe_automaton(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode and decode all ``documents``; digests per document."""
    import public_tokenizers

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return encode_documents(docs, public_tokenizers.path("word_bpe_49k.json")).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
