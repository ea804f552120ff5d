"""Exact BPE encoding by dynamic programming over prefixes.

For every prefix of a word exactly one token can be the last one of the
prefix's encoding.  An automaton over the vocabulary finds all tokens that end
at a position; the one whose neighbour, the last token of the prefix before
it, is compatible with it is stored.  Back-pointers from the end then give the
ids.  Two tokens are compatible if the merges would leave the border between
them alone, which the merge trees of the two tokens decide without running any
merge.  Work is linear in the word's length, also for words of megabytes.
"""

from __future__ import annotations

import hashlib
import json
import struct
import uuid

import ahocorasick
import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession
from tokenizers import Tokenizer

from .common import add_columns, documents, per_process

#: Stands for the vocabulary's end-of-word suffix; byte-level text never holds it.
END = ""
NEVER = 1 << 40


def byte_letters() -> list[str]:
    """The visible letter of each byte in byte-level vocabularies: printable Latin-1 keeps its own, the rest follow from U+0100."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    moved = iter(range(0x100, 0x200))
    return [chr(b if b in plain else next(moved)) for b in range(256)]


def naive(symbols: list[str], ranks: dict[tuple[str, str], int]) -> tuple[list[str], tuple[str, str] | None]:
    """Plain BPE: the encoding, and the last pair merged."""
    last = None
    while len(symbols) > 1:
        best, at = min((ranks.get((a, b), NEVER), i) for i, (a, b) in enumerate(zip(symbols, symbols[1:])))
        if best == NEVER:
            break
        last = (symbols[at], symbols[at + 1])
        symbols = [*symbols[:at], symbols[at] + symbols[at + 1], *symbols[at + 2 :]]
    return symbols, last


def tables(spec: str) -> dict:
    """What encoding needs of a tokenizer file: a table whose size the vocabulary fixes."""
    model = json.loads(spec)["model"]
    suffix = model.get("end_of_word_suffix") or ""
    if model["type"] != "BPE" or not suffix or model.get("continuing_subword_prefix") or model.get("byte_fallback"):
        raise ValueError("a byte-level BPE file with an end-of-word suffix is needed")
    inner = lambda s: s[: -len(suffix)] + END if s.endswith(suffix) and len(s) > len(suffix) else s
    ids = {inner(s): i for s, i in model["vocab"].items()}
    pairs = [tuple(m if isinstance(m, list) else m.split(" ")) for m in model["merges"]]
    ranks = {(inner(a), inner(b)): r for r, (a, b) in enumerate(pairs)}
    born, split = {}, {}
    for s, i in ids.items():
        symbols = [*s[:-2], s[-2:]] if s.endswith(END) else list(s)
        if len(symbols) == 1:
            born[i] = -1
            continue
        got, last = naive(symbols, ranks)
        if len(got) == 1 and last:  # else no encoding ever holds it
            born[i], split[i] = ranks[last], (ids[last[0]], ids[last[1]])
    return {"spec": spec, "ids": {s: i for s, i in ids.items() if i in born}, "names": {i: s for s, i in model["vocab"].items()}, "born": born, "split": split, "ranks": {(ids[a], ids[b]): r for (a, b), r in ranks.items()}}


class WordEncoder:
    """Encodes texts as the tokenizer file says, words by the dynamic program."""

    #: Letters up to U+024F and common punctuation are their own normal form; what needs more goes through the file's own normaliser and splitter.
    PLAIN = regex.compile(r"[\t-\r \x21-\x7E\xA0-\u012F\u0131-\u0239\u023B-\u023D\u023F-\u024F\u2010-\u2027\u2030-\u205E\u20A0-\u20BF]*+")
    SPLIT = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+")
    CACHE = 100_000
    #: Token pairs whose compatibility is remembered.
    BORDERS = 500_000

    def __init__(self, t: dict):
        self.ids, self.names, self.born, self.split, self.ranks = t["ids"], t["names"], t["born"], t["split"], t["ranks"]
        letters = byte_letters()
        self.wide = {c: "".join(letters[b] for b in chr(c).encode()) for c in (*range(0x80, 0x250), *range(0x2010, 0x2060), *range(0x20A0, 0x20C0))}
        self.automaton = ahocorasick.Automaton()
        for s, i in self.ids.items():
            self.automaton.add_word(s, (len(s), i))
        self.automaton.make_automaton()
        tok = Tokenizer.from_str(t["spec"])
        self.normalizer, self.splitter = tok.normalizer, tok.pre_tokenizer
        spec = json.loads(t["spec"])
        self.own = spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"] == self.SPLIT.pattern and [n["type"] for n in spec["normalizer"]["normalizers"]] == ["NFC", "Replace", "Lowercase"]
        special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        if any(x[k] for x in spec["added_tokens"] for k in ("single_word", "lstrip", "rstrip", "normalized")):
            raise ValueError("added tokens with options are not supported")
        self.special = special
        self.names |= {i: s for s, i in special.items()}
        self.by_id = np.array([self.names.get(i, "") for i in range(max(self.names) + 1)], dtype=object)
        self.special_at = regex.compile("(" + "|".join(sorted(map(regex.escape, special), key=len, reverse=True)) + ")") if special else None
        self.border: dict[int, bool] = {}
        self.edges: dict[tuple[int, bool], list] = {}
        self.younger: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def edge(self, token: int, right: bool) -> list[tuple[int, int, int]]:
        """The nodes of the token's merge tree at its right (left) border, root first: (node, rank that makes it, rank that takes it up)."""
        if (token, right) not in self.edges:
            out, taken, node = [], NEVER, token
            while True:
                out.append((node, self.born[node], taken))
                if node not in self.split:
                    break
                taken, node = self.born[node], self.split[node][right]
            self.edges[token, right] = out
        return self.edges[token, right]

    def compatible(self, a: int, b: int) -> bool:
        """No merge would ever join a node at a's right border with one at b's left border while both stand.

        Equal ranks merge from the left: a's own merge of that rank comes first, b's own comes after.
        """
        if len(self.border) > self.BORDERS:
            self.border.clear()
        fits = self.border[a * 65536 + b] = not any(
            (r := self.ranks.get((u, v))) is not None and r < u_end and r <= v_end
            for u, u_born, u_end in self.edge(a, True)
            for v, v_born, v_end in self.edge(b, False)
            if u_born < v_end and v_born < u_end
        )
        return fits

    def word(self, piece: str) -> list[int]:
        """Ids of one byte-level piece (no end mark yet)."""
        s = piece + END
        if s in self.ids:
            return [self.ids[s]]
        last, back, border = [-1] * (len(s) + 1), [0] * (len(s) + 1), self.border
        settled = -1
        for at, (size, token) in self.automaton.iter(s):  # at each end the longest first
            if at == settled:
                continue
            start = at + 1 - size
            if start:
                before = last[start]
                if before < 0:
                    continue
                fits = border.get(before * 65536 + token)
                if not (self.compatible(before, token) if fits is None else fits):
                    continue
            last[at + 1], back[at + 1], settled = token, start, at
        out, end = [], len(s)
        while end:
            out.append(last[end])
            end = back[end]
        return out[::-1]

    def pieces(self, segment: str, plain: bool) -> list[str]:
        """The byte-level pieces of a text without added tokens."""
        if plain:
            found = self.SPLIT.findall(segment.lower())
            return found if segment.isascii() else [x.translate(self.wide) for x in found]
        return [x for x, _ in self.splitter.pre_tokenize_str(self.normalizer.normalize_str(segment))]

    def segment(self, segment: str, plain: bool) -> bytes:
        ids = [i for piece in self.pieces(segment, plain) for i in self.word(piece)]
        return struct.pack(f"<{len(ids)}I", *ids)

    def chunk(self, c: str) -> bytes:
        """A chunk's ids, from the older half of what is remembered, or new."""
        got = self.older.get(c)
        if got is None:
            got = self.segment(c, True)
        if len(c) <= 64:
            if len(self.younger) >= self.CACHE:
                self.younger, self.older = {}, self.younger
            self.younger[c] = got
        return got

    def encode(self, text: str) -> bytes:
        """Ids as little-endian 32-bit integers.

        Plain texts go chunk by chunk between blanks, where no token crosses; the last chunks' results are remembered.
        """
        out = []
        for part in self.special_at.split(text) if self.special_at else [text]:
            if part in self.special:
                out.append(struct.pack("<I", self.special[part]))
            elif part and self.own and self.PLAIN.fullmatch(part):
                known = self.younger.get
                out += [known(c) or self.chunk(c) for c in part.split()]
            elif part:
                out.append(self.segment(part, False))
        return b"".join(out)

    def decode(self, ids: bytes) -> str:
        """The vocabulary's names of ids, joined by blanks: the file has no decoder step."""
        return " ".join(self.by_id[np.frombuffer(ids, "<u4")])


def vocabulary(path: str | None = None) -> str:
    """A tokenizer file's text; by default the public word-end vocabulary."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    with open(path, encoding="utf-8") as f:
        return f.read()


def encode(docs: DataFrame, tokenizer: str | None = None, text_col: str = "text", extra: tuple[str, ...] = ("token_ids", "decoded"), drop: tuple[str, ...] = ()) -> DataFrame:
    """docs without the columns in `drop`, with n_tokens, ids_sha256, decoded_sha256 and, if asked for, token_ids (binary, little-endian 32-bit) and decoded.

    Null and empty texts have no ids.  Rows, ties and repeats pass through; columns of the result's names are replaced.
    """
    shared = docs.sparkSession.sparkContext.broadcast(tables(vocabulary(tokenizer)))

    token = uuid.uuid4().hex

    def make():
        encoder = per_process("bpe", token, lambda: WordEncoder(shared.value))

        def work(texts: list[bytes]) -> list:
            got = [encoder.encode(t.decode("utf-8", "replace")) for t in texts]
            back = [encoder.decode(i) for i in got]
            out = [[len(i) // 4 for i in got], [hashlib.sha256(i).hexdigest() for i in got], [hashlib.sha256(s.encode()).hexdigest() for s in back]]
            return out + [{"token_ids": got, "decoded": back}[x] for x in extra]

        return work

    return add_columns(docs, text_col, "n_tokens long, ids_sha256 string, decoded_sha256 string" + "".join({"token_ids": ", token_ids binary", "decoded": ", decoded string"}[x] for x in extra), make, token, drop)


def op1_bpe_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(documents(spark, sf_dir).select("doc_id", "text"), extra=(), drop=("text",)).select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
