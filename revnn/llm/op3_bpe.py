"""BPE as a streaming transducer with bounded lookahead, and its inverse as a state machine.

Whether two neighbouring symbols end up in one token can depend on text to the right only through merges of ever lower
rank that cross the token bounds in between. Following these chains through the merge list gives its sufficient
lookahead: the largest number of symbols to the right that can matter (:meth:`Merges.lookahead`). A transducer that has
read so far past a token bound may emit what stands before it, so a word of any length is encoded in memory that the
merge list alone determines. Words shorter than the lookahead end before that and are merged at once; results of
frequent words are kept in a bounded table.

Decoding turns ids into text piece by piece: bytes go through an incremental UTF-8 machine that holds back at most an
unfinished character. A vocabulary file without a decoder (as the given one) is decoded as its library does: the
tokens' own strings, joined by one blank.

The vocabulary file stays where it is; its path is a parameter. Defined cases: null text is empty: no ids, empty
decoding; strings of special tokens in a text become those tokens; repeated rows give repeated results; an empty table
gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import codecs
import hashlib
import heapq
import json
import re
import unicodedata
from collections.abc import Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from revnn.llm.common import table

#: Characters that a slice of a long text has, more or less; slices end before white space.
SLICE = 1 << 16
#: Words kept with their ids, for each worker.
KEPT_WORDS = 300_000
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


#: Code points (hexadecimal) that the splitter's expressions take for letters or numbers and the library,
#: which follows Unicode 16, does not.
UNKNOWN = """
558 58B-58C 88F C5C CDC 208F 209D-209F A7CE-A7CF A7D2 A7D4 A7DD A7E2 A7F1 AB6C-AB6D 107BB-107BF
10940-10959 10EC5-10EC7 10ED9-10EEE 11B0A 11DB0-11DDB 11DE0-11DE9 11DF1 1246F 12475-1247F
12550-12686 16EA0-16EB8 16EBB-16ED3 16FF2-16FF6 187F8-187FF 18CD6-18CDA 18D09-18D20 18D80-18DF2
18E00-19191 191A0-191D2 1B123-1B128 1B168 1D6A6 1DF1F-1DF24 1DF2B-1DF81 1DF90-1DF96 1DFCD-1DFFF
1E6C0-1E6DE 1E6E0-1E6E2 1E6E4-1E6E5 1E6E7-1E6ED 1E6F0-1E6F4 1E6FE-1E6FF 2B73A-2B73F 2B81E
2CEA2-2CEAD 323B0-33479 3D000-3FC3F
"""
#: First and last capital and distance of its small letter, where the library knows one and Python does not.
CAPITALS = [(0x1C89, 0x1C89, 1), (0xA7CB, 0xA7CB, 0x264 - 0xA7CB), (0xA7CC, 0xA7CC, 1), (0xA7CE, 0xA7CE, 1), (0xA7D2, 0xA7D2, 1), (0xA7D4, 0xA7D4, 1), (0xA7DA, 0xA7DA, 1), (0xA7DC, 0xA7DC, 0x19B - 0xA7DC), (0x10D50, 0x10D65, 0x20), (0x16EA0, 0x16EB8, 0x1B)]
SMALL = {c: c + d for a, b, d in CAPITALS for c in range(a, b + 1)}
_RANGES = "".join("-".join(chr(int(x, 16)) for x in r.split("-")) for r in UNKNOWN.split())
#: Finds characters that need the slower, exact way; few texts have one.
ODD = regex.compile(f"[{_RANGES}{''.join(map(chr, SMALL))}]")


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> dict[int, str]:
    """The letter that stands for each byte in vocabularies of this kind: printable ones for themselves."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class Merges:
    """A merge list over symbols; ids are those of the vocabulary."""

    def __init__(self, vocab: dict[str, int], merges: list, suffix: str = ""):
        self.vocab, self.suffix = vocab, suffix
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in merges]
        self.ranks = {(vocab[a], vocab[b]): (rank, vocab[a + b]) for rank, (a, b) in enumerate(pairs)}
        self.pairs = pairs
        self._lookahead = 0

    def n_symbols(self, token: str) -> int:
        return len(token.removesuffix(self.suffix)) if self.suffix else len(token)

    @property
    def lookahead(self) -> int:
        """Symbols right of a token bound that can decide whether it stays one, at most."""
        if not self._lookahead:
            farthest: dict[str, int] = {}  # by left part: over merges of lower rank, symbols right of their inner bound
            for a, b in self.pairs:
                tails = (farthest.get(b[i:], 0) for i in range(len(b)))
                farthest[a] = max(farthest.get(a, 0), reach := self.n_symbols(b) + max(tails))
                self._lookahead = max(self._lookahead, reach)
        return self._lookahead

    def merge(self, ids: list[int]) -> list[int]:
        """Merges of lowest rank first, leftmost first among equals."""
        ranks, n = self.ranks, len(ids)
        if n < 24:
            ids = list(ids)
            while len(ids) > 1:
                best, at, to = len(ranks), -1, 0
                for i in range(len(ids) - 1):
                    found = ranks.get((ids[i], ids[i + 1]))
                    if found and found[0] < best:
                        best, at, to = found[0], i, found[1]
                if at < 0:
                    break
                ids[at : at + 2] = [to]
            return ids
        ids, after, before = list(ids), [*range(1, n), -1], [*range(-1, n - 1)]
        heap = [(r[0], i, ids[i], ids[i + 1], r[1]) for i in range(n - 1) if (r := ranks.get((ids[i], ids[i + 1])))]
        heapq.heapify(heap)
        while heap:
            _, i, a, b, to = heapq.heappop(heap)
            j = after[i]
            if ids[i] != a or j < 0 or ids[j] != b:
                continue
            ids[i], ids[j] = to, -1
            after[i] = after[j]
            if after[j] >= 0:
                before[after[j]] = i
            for x, y in ((before[i], i), (i, after[i])):
                if x >= 0 and y >= 0 and (r := ranks.get((ids[x], ids[y]))):
                    heapq.heappush(heap, (r[0], x, ids[x], ids[y], r[1]))
        return [x for x in ids if x >= 0]

    def stream(self, symbols: Iterable[str]) -> Iterator[int]:
        """Ids of one word, each emitted as soon as nothing that may follow can change it; constant memory."""
        lengths = self.lengths
        ahead, vocab = self.lookahead, self.vocab
        held: list[int] = []
        for s in self.closed(symbols):
            held.append(vocab[s])
            if len(held) == 4 * ahead + 64:
                stable, used = len(held) - ahead, 0
                for t in self.merge(held):
                    if used + lengths[t] > stable:
                        break
                    used += lengths[t]
                    yield t
                del held[:used]
        yield from self.merge(held)

    def closed(self, symbols: Iterable[str]) -> Iterator[str]:
        """The symbols, the last one with the mark of a word's end."""
        last = None
        for s in symbols:
            if last is not None:
                yield last
            last = s
        if last is not None:
            yield last + self.suffix

    @property
    def lengths(self) -> dict[int, int]:
        if not hasattr(self, "_lengths"):
            self._lengths = {i: self.n_symbols(t) for t, i in self.vocab.items()}
        return self._lengths


class Codec:
    """Encoder and decoder of a vocabulary file that splits text into words."""

    def __init__(self, path: str):
        d = json.load(open(path, encoding="utf-8"))
        model = d["model"]
        self.merges = Merges(model["vocab"], model["merges"], model["end_of_word_suffix"] or "")
        self.special = {t["content"]: t["id"] for t in d["added_tokens"]}
        self.special_at = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.tokens = {i: t for t, i in model["vocab"].items()} | {i: t for t, i in self.special.items()}
        pattern = next(p["pattern"]["Regex"] for p in d["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.words_at = regex.compile(pattern)
        known = {f"\\p{{{c}}}": f"[\\p{{{c}}}--[{_RANGES}]]" for c in "LN"}
        self.odd_words_at = regex.compile(regex.sub(r"\\p\{[LN]\}", lambda m: known[m[0]], pattern), regex.V1)
        self.letters = byte_letters()
        self.bytes = {c: b for b, c in self.letters.items()}
        self.kept: dict[str, tuple[int, str, str]] = {}

    def words(self, text: str) -> list[str]:
        """The words of a slice, composed and in lower case."""
        if text.isascii() or not ODD.search(text):
            return self.words_at.findall(self.normal(text))
        return self.odd_words_at.findall(self.normal(text).translate(SMALL))

    def normal(self, text: str) -> str:
        """Composed, lower case; white space is dropped later. Letter by letter where lower case depends on place."""
        text = unicodedata.normalize("NFC", text)
        return "".join(map(str.lower, text)) if "Σ" in text else text.lower()

    def slices(self, text: str) -> Iterator[str]:
        """The text in slices that no word, and no character with its marks, crosses."""
        at = 0
        while len(text) - at > SLICE:
            cut = max(text.rfind(" ", at + 1, at + SLICE), text.rfind("\n", at + 1, at + SLICE))
            if cut < 0:
                found = min((x for x in (text.find(" ", at + SLICE), text.find("\n", at + SLICE)) if x >= 0), default=len(text))
                cut = found
            yield text[at:cut]
            at = cut
        yield text[at:]

    def symbols(self, word: str) -> Iterator[str]:
        for i in range(0, len(word), 4096):
            yield from map(self.letters.__getitem__, word[i : i + 4096].encode())

    def word(self, word: str) -> Iterator[int]:
        """Ids of a word; long ones as a stream."""
        if len(word) * 4 < self.merges.lookahead or len(word) <= 64:
            return iter(self.merge_word(word))
        return self.merges.stream(self.symbols(word))

    def merge_word(self, word: str) -> list[int]:
        vocab = self.merges.vocab
        return self.merges.merge([vocab[s] for s in self.merges.closed(self.symbols(word))])

    def encode(self, text: str) -> Iterator[int]:
        """Ids of a text, one after the other."""
        for piece in self.special_at.split(text) if self.special_at else [text]:
            if piece in self.special:
                yield self.special[piece]
            else:
                for part in self.slices(piece):
                    for word in self.words(part):
                        yield from self.word(word)

    def texts(self, text: str) -> Iterator[tuple[int, str, str]]:
        """Word by word: number of ids, ids in decimal, and what decoding these ids gives."""
        kept = self.kept
        for piece in self.special_at.split(text) if self.special_at else [text]:
            if piece in self.special:
                yield 1, str(self.special[piece]), self.decode_plain([self.special[piece]])
                continue
            for part in self.slices(piece):
                for word in self.words(part):
                    found = kept.get(word)
                    if found is None:
                        if len(word) > 64:
                            yield from self.streamed(word)
                            continue
                        ids = list(self.word(word))
                        if len(kept) >= KEPT_WORDS:
                            kept.clear()
                        found = kept[word] = (len(ids), " ".join(map(str, ids)), self.decode_plain(ids))
                    yield found

    def streamed(self, word: str) -> Iterator[tuple[int, str, str]]:
        for i in self.word(word):
            yield 1, str(i), self.tokens[i]

    def decode_plain(self, ids: Iterable[int]) -> str:
        """As the library decodes a file that names no decoder."""
        return " ".join(map(self.tokens.__getitem__, ids))

    def decode(self, ids: Iterable[int]) -> Iterator[str]:
        """Text of a stream of ids, piece by piece: words end in a blank, unfinished characters wait for their bytes."""
        machine, suffix = codecs.getincrementaldecoder("utf-8")("replace"), self.merges.suffix
        for i in ids:
            token = self.tokens[i]
            if i in self.special.values():
                yield machine.decode(b"", True) + token
                machine.reset()
                continue
            ends = bool(suffix) and token.endswith(suffix)
            text = machine.decode(bytes(self.bytes[c] for c in (token.removesuffix(suffix) if ends else token)))
            if text or ends:
                yield text + " " * ends
        if rest := machine.decode(b"", True):
            yield rest


@lru_cache(maxsize=2)
def codec(path: str) -> Codec:
    return Codec(path)


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens and digests of ids and decoded text for every row."""
    path = path or default_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = codec(path)
        for batch in batches:
            out = ([], [], [], [])
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                n, ids, decoded, gap = 0, hashlib.sha256(), hashlib.sha256(), ""
                held: list[tuple[int, str, str]] = []

                def flush() -> None:
                    nonlocal n, gap
                    if held:
                        counts, a, b = zip(*held, strict=True)
                        n += sum(counts)
                        ids.update((gap + " ".join(a)).encode())  # noqa: B023
                        decoded.update((gap + " ".join(b)).encode())  # noqa: B023
                        gap = " "
                        held.clear()

                for found in c.texts(text.as_py() or ""):
                    held.append(found)
                    if len(held) == 8192:
                        flush()
                flush()
                for x, v in zip(out, (doc_id, n, ids.hexdigest(), decoded.hexdigest()), strict=True):
                    x.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(out, (pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


def op3_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"))


QUERIES = {"op3_bpe_codec": op3_bpe_codec}
