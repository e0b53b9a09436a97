"""BPE encoding by forced-boundary splitting, and decoding.

A pair of adjacent bytes that stands inside no vocabulary token can't end up inside a token of any text, so the place
between the two bytes is a certain cut: fragments between certain cuts are encoded independently and their ids put in a
row. Every text is cut that way: a table over pairs of bytes is looked up for all neighbours of a run of texts at once.
The vocabularies read here mark the ends of words, so a cut also says whether a word ends at it: a fragment that ends
inside a word is encoded without the mark. White space is in no token, so it is always cut away. Where the vocabulary
would join two bytes that its own splitting pattern keeps apart (a contraction before a letter), the fragment is split
there too; nothing else depends on that pattern. Equal fragments are encoded once per worker, in a bounded memory that
only saves time.

Texts of Latin-1 characters are normal forms of themselves but for their case, so they are cut as they are. Other texts
go through the library's normaliser and splitter, fragment by fragment between white space, and are then cut in the same
way. The string of a special token is left to the library at the fragment that holds it.

Decoding goes from ids alone: without a decoder in the file, the library joins the tokens of the ids by one space.

A file of another kind than the one described (bytes as stand-in characters, white space dropped, words split by the
pattern below) is refused, because its certain cuts would be others.

Defined cases: null and empty texts give no ids, an empty decoded text and the hashes of no bytes; a very long text is
taken in parts that end at white space, so memory follows the longest run without any; repeated rows are encoded alike;
there are no ties; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import json
import re
import struct
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer, models

from sparkverdict.llm.common import ship_package

#: Fragments that a worker remembers in each of two generations; those longer than LONG bytes seldom return and are forgotten after their run.
FRAGMENTS_KEPT = 100_000
LONG = 64
#: Characters of the texts that are cut at once, and of the parts of a longer text.
RUN = 1 << 20
#: How the vocabulary files that are read here prepare a text.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
CONTRACTION = b"'(?:s|t|re|ve|m|ll|d)"
LATIN_SPACE = b"\t\n\x0b\x0c\r \x85\xa0"
SPACE, LETTER, NUMBER, OTHER = range(4)
#: Separators that str.split() knows besides Unicode white space; where a text holds one, a pattern splits it.
_ODD_SEPARATORS = ("\x1c", "\x1d", "\x1e", "\x1f")
_ASCII_SPACE = re.compile(r"[\x20\x09-\x0D]+")
#: White space has left the runs when these two mark the end of a document and a fragment that ends inside a word.
_END, _INSIDE = 0xA0, 0x85


def byte_alphabet() -> dict[str, int]:
    """The printable stand-in character of each byte in byte-level vocabularies, by its published rule."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    shown = {chr(b): b for b in plain}
    rest = [b for b in range(256) if b not in plain]
    return shown | {chr(256 + i): b for i, b in enumerate(rest)}


def latin_classes() -> np.ndarray:
    """SPACE, LETTER, NUMBER or OTHER for each Latin-1 character."""
    kind = {"L": LETTER, "N": NUMBER}
    return np.asarray([SPACE if c in LATIN_SPACE else kind.get(unicodedata.category(chr(c))[0], OTHER) for c in range(256)], "u1")


def ascii_fragments(text: str) -> list[str]:
    """Fragments between runs of ASCII white space."""
    if text.isascii():
        if any(c in text for c in _ODD_SEPARATORS):
            return [x for x in _ASCII_SPACE.split(text) if x]
        return text.split()
    # bytes.split() knows ASCII white space only, so no other separator is taken for a cut
    return [x.decode() for x in text.encode().split()]


def refuse_other_kinds(spec: dict) -> None:
    """Raises ValueError for a vocabulary file whose texts are prepared in another way than the module says."""
    model, normalizer, splitter = spec["model"], spec["normalizer"] or {}, spec["pre_tokenizer"] or {}
    steps = normalizer.get("normalizers", [])
    splits = splitter.get("pretokenizers", [])
    ok = (
        model["type"] == "BPE"
        and not any(model.get(x) for x in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges", "unk_token"))
        and [x["type"] for x in steps] == ["NFC", "Replace", "Lowercase"]
        and (steps[1]["pattern"], steps[1]["content"]) == ({"Regex": r"\s+"}, " ")
        and [x["type"] for x in splits] == ["Split", "ByteLevel"]
        and (splits[0]["pattern"], splits[0]["behavior"], splits[0]["invert"]) == ({"Regex": PATTERN}, "Removed", True)
        and not splits[1]["add_prefix_space"]
        and not splits[1].get("use_regex", True)
    )
    if not ok:
        raise ValueError("this vocabulary file prepares texts in a way whose certain cuts are not known here")


class ForcedCutEncoder:
    """The encoder of one vocabulary file, with its table of joined bytes and its memory of fragments."""

    def __init__(self, path: str) -> None:
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        refuse_other_kinds(spec)
        model = spec["model"]
        self.suffix = model["end_of_word_suffix"] or ""
        merges = [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in model["merges"]]
        self.last = models.BPE(model["vocab"], merges, end_of_word_suffix=self.suffix) if self.suffix else models.BPE(model["vocab"], merges)
        self.inner = models.BPE(model["vocab"], merges)
        self.special = [t["content"] for t in spec["added_tokens"]]
        self.alphabet = byte_alphabet()
        self.shown = {b: c for c, b in self.alphabet.items() if chr(b) != c}
        self.joined = self._joined(model["vocab"])
        self.pairs = set(map(tuple, np.argwhere(self.joined).tolist()))
        self.classes = latin_classes()
        ends = [chr(c).encode() for c in range(256)]
        self.latin_forced = ~self.joined[np.ix_([e[-1] for e in ends], [e[0] for e in ends])].ravel()
        others = b"".join(re.escape(bytes([c])) for c in range(256) if self.classes[c] == OTHER)
        self.contraction = re.compile(b"(?<![" + others + b"])" + CONTRACTION)
        self.spaces = bytes(0x0A if c in LATIN_SPACE else c for c in range(256))
        self.plain_decoder = spec["decoder"] is None
        size = self.tokenizer.get_vocab_size(with_added_tokens=True)
        self.said = [(self.tokenizer.id_to_token(i) or "").encode() + b" " for i in range(size)]
        #: A full memory becomes the older generation, from which fragments that return are taken over.
        self.memory: dict[bytes | str, bytes] = {}
        self.older: dict[bytes | str, bytes] = {}

    def _joined(self, vocab: dict[str, int]) -> np.ndarray:
        """joined[a, b]: byte a stands right before byte b in some token."""
        joined = np.zeros((256, 256), bool)
        special = set(self.special)
        for token in vocab:
            if token in special:
                continue
            body = token[: -len(self.suffix)] if self.suffix and token.endswith(self.suffix) and len(token) > len(self.suffix) else token
            raw = [self.alphabet[c] for c in body]
            joined[raw[:-1], raw[1:]] = True
        return joined

    def pieces(self, raw: bytes) -> list[bytes]:
        """The fragments of some bytes between the pairs that no token joins."""
        if self.pairs.issuperset(zip(raw, raw[1:])):
            return [raw]
        cuts = [i for i, pair in enumerate(zip(raw, raw[1:]), 1) if pair not in self.pairs]
        return [raw[a:b] for a, b in zip([0, *cuts], [*cuts, len(raw)], strict=True)]

    def encode_word(self, raw: bytes, ends: bool = True) -> list[int]:
        """Ids of the bytes of a word, or of a part that does not end one: each fragment between certain cuts by itself."""
        *inner, last = self.pieces(raw)
        found = [t.id for part in inner for t in self.inner.tokenize(part.decode("latin-1").translate(self.shown))]
        return found + [t.id for t in (self.last if ends else self.inner).tokenize(last.decode("latin-1").translate(self.shown))]

    def cuts(self, run: bytes) -> tuple[np.ndarray, np.ndarray]:
        """For each neighbouring pair of lower-case Latin-1 characters: whether no token joins them, whether a word ends."""
        x = np.frombuffer(run, "u1")
        kind = self.classes[x]
        forced = self.latin_forced.take((x[:-1].astype("u2") << 8) | x[1:])
        ends = (kind[:-1] != kind[1:]) | (kind[:-1] == NUMBER)
        for m in self.contraction.finditer(run):
            ends[m.start() : m.end() - 1] = False
            ends[m.end() - 1 : m.end()] = True
        return forced, ends

    def _latin_fragments(self, parts: list[bytes]) -> list[bytes]:
        """The fragments of some parts; after those of each part stands one that is the _END mark alone."""
        run = b"\n".join(parts) + b"\n"
        forced, ends = self.cuts(run)
        x = np.frombuffer(run.translate(self.spaces), "u1").copy()
        full = x != 0x0A
        inside = full[:-1] & full[1:]
        words = np.flatnonzero(inside & ends) + 1
        broken = np.flatnonzero(inside & forced & ~ends) + 1
        last = np.cumsum([len(p) + 1 for p in parts]) - 1
        x[last] = _END
        at = np.concatenate([words, np.repeat(broken, 2), last, last + 1])
        put = np.full(len(at), 0x20, "u1")
        put[len(words) : len(words) + 2 * len(broken) : 2] = _INSIDE
        return np.insert(x, at, put).tobytes().split()

    def _learn(self, fragments: set) -> list:
        """Encodes the fragments that the memory lacks; returns those that it should not keep."""
        for f in fragments:
            if isinstance(f, bytes):
                ends = f[-1] != _INSIDE
                ids = self.encode_word((f if ends else f[:-1]).decode("latin-1").encode(), ends)
            elif any(s in f for s in self.special):
                ids = self.tokenizer.encode(f, add_special_tokens=False).ids
            else:
                shown = self.tokenizer.pre_tokenizer.pre_tokenize_str(self.tokenizer.normalizer.normalize_str(f))
                ids = [i for word, _ in shown for i in self.encode_word(bytes([self.alphabet[c] for c in word]))]
            self.memory[f] = struct.pack(f"<{len(ids)}I", *ids)
        return [f for f in fragments if len(f) > LONG]

    def _known(self, fragments: list) -> list:
        """Makes the memory know these fragments; returns those to forget after use."""
        if len(self.memory) > FRAGMENTS_KEPT:
            self.memory, self.older = {}, self.memory
        new = set(fragments).difference(self.memory)
        for f in self.older.keys() & new:
            self.memory[f] = self.older[f]
            new.discard(f)
        return self._learn(new)

    def _encode_run(self, run: list[tuple[int, str]], found: list[list[bytes]]) -> None:
        latin: list[tuple[int, bytes]] = []
        for at, text in run:
            raw = None
            if not any(s in text for s in self.special):
                try:
                    raw = text.lower().encode("latin-1")
                except UnicodeEncodeError:
                    pass
            if raw is not None:
                latin.append((at, raw))
                continue
            fragments = ascii_fragments(text)
            passing = self._known(fragments)
            found[at].append(b"".join([self.memory[f] for f in fragments]))
            for f in passing:
                del self.memory[f]
        if latin:
            fragments = self._latin_fragments([raw for _, raw in latin])
            end = bytes([_END])
            self.memory[end] = b""
            passing = self._known(fragments)
            self.memory[end] = b""
            ids, low = self.memory, 0
            for at, _ in latin:
                high = fragments.index(end, low)
                found[at].append(b"".join(map(ids.__getitem__, fragments[low:high])))
                low = high + 1
            for f in passing:
                del self.memory[f]

    def encode_batch(self, texts: list[str | None]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        found: list[list[bytes]] = [[] for _ in texts]
        run: list[tuple[int, str]] = []
        size = 0
        for at, text in enumerate(texts):
            for part in parts_of(text) if text else ():
                if size and size + len(part) > RUN:
                    self._encode_run(run, found)
                    run, size = [], 0
                run.append((at, part))
                size += len(part)
        if run:
            self._encode_run(run, found)
        return [x[0] if len(x) == 1 else b"".join(x) for x in found]

    def decode(self, ids: bytes) -> bytes:
        """What the library's decode() returns for these ids, special tokens included, in UTF-8."""
        numbers = np.frombuffer(ids, "<u4").tolist()
        if not self.plain_decoder:
            return self.tokenizer.decode(numbers, skip_special_tokens=False).encode()
        return b"".join(map(self.said.__getitem__, numbers))[:-1]

    def encode(self, text: str | None) -> tuple[bytes, bytes]:
        """Ids as bytes, and the text decoded from them."""
        (ids,) = self.encode_batch([text])
        return ids, self.decode(ids)


def parts_of(text: str) -> Iterator[str]:
    """The text in parts of about RUN characters that end before white space."""
    low = 0
    while len(text) - low > RUN:
        m = _ASCII_SPACE.search(text, low + RUN)
        if m is None:
            break
        yield text[low : m.start()]
        low = m.end()
    yield text[low:] if low else text


_ENCODERS: dict[str, ForcedCutEncoder] = {}


def encoder(path: str) -> ForcedCutEncoder:
    """One encoder per worker and vocabulary file."""
    if path not in _ENCODERS:
        _ENCODERS[path] = ForcedCutEncoder(path)
    return _ENCODERS[path]


def _digest_batches(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sparkverdict.llm import bpe
        from sparkverdict.llm.common import slices

        coder = bpe.encoder(path)
        for batch in slices(batches):
            found = coder.encode_batch(batch.column(1).to_pylist())
            n = [len(ids) // 4 for ids in found]
            ids_hash = [hashlib.sha256(ids).hexdigest() for ids in found]
            text_hash = [hashlib.sha256(coder.decode(ids)).hexdigest() for ids in found]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids_hash, pa.string()), pa.array(text_hash, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return run


def _id_batches(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sparkverdict.llm import bpe
        from sparkverdict.llm.common import slices

        coder = bpe.encoder(path)
        for batch in slices(batches):
            found = coder.encode_batch(batch.column(batch.schema.get_field_index("_text")).to_pylist())
            ids = [np.frombuffer(raw, "<u4").astype("i4") for raw in found]
            decoded = [coder.decode(raw).decode() for raw in found]
            kept = [i for i, name in enumerate(batch.schema.names) if name != "_text"]
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in kept], pa.array(ids, pa.list_(pa.int32())), pa.array(decoded, pa.string())], names=[*[batch.schema.names[i] for i in kept], "ids", "decoded"])

    return run


def encode(docs: DataFrame, path: str, keep: tuple[str, ...] = ("doc_id",), text: str = "text") -> DataFrame:
    """The kept columns with `ids` (array of int) and `decoded` (string)."""
    ship_package(docs.sparkSession)
    schema = ", ".join(f"`{c}` {docs.schema[c].dataType.simpleString()}" for c in keep)
    return docs.select(*keep, F.col(text).cast("string").alias("_text")).mapInArrow(_id_batches(path), f"{schema}, ids array<int>, decoded string")


def digests(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """doc_id, n_tokens and the SHA-256 of the ids and of the decoded text."""
    ship_package(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(text).cast("string").alias("text")).mapInArrow(
        _digest_batches(path), "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"
    )
