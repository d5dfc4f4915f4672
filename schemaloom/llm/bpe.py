"""BPE encoding as a bounded-lookahead streaming transducer, and decoding as a byte-to-text state machine."""

from __future__ import annotations

import codecs
import hashlib
import json
import re
import unicodedata
from collections.abc import Iterable, Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from schemaloom.llm.shared import byte_texts, documents, slices

SLICE_BYTES = 4 << 20
CACHE_ENTRIES = 350_000
#: Bytes of a tokenizer file that is broadcast.
MODEL_BYTES = 64 << 20
TOKEN = ""  # the key of a trie node under which its token stands
#: Separators of the white space pattern; Python's split() has these and the next four.
SPACE = re.compile("[\t-\r \x85\xa0  -     　]+")
NOT_SPACE = re.compile("[\x1c-\x1f]")


def byte_letters() -> list[str]:
    """The printable letter of each byte: itself if printable in Latin-1, else the next free one from 256."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    extra = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(extra)) for b in range(256)]


LETTERS = byte_letters()


class MergeList:
    """Tokens in the order of their merges, with what splits and joins them.

    A prefix of a word has one encoding; its last token is the only one ending there that is compatible with the last
    token before it. So an encoder needs, for each live boundary, that boundary's last token alone. A boundary is live
    while some token could still reach past the newest symbol from it: reach, the symbols of the longest token, is the
    lookahead that the list asks for.
    """

    def __init__(self, vocabulary: dict[str, int], merges: Iterable[tuple[str, str]], word_end: str):
        self.word_end, self.names, self.ids = word_end, [], []
        order: dict[str, int] = {}
        bases = [s for s in (*LETTERS, *(x + word_end for x in LETTERS if word_end)) if s in vocabulary]
        for name in bases:
            order[name] = len(order)
        self.bases = len(order)
        self.parts = [(k, k) for k in range(self.bases)]
        symbols = [(name,) for name in bases]
        self.join: dict[tuple[int, int], int] = {}
        for a, b in merges:
            left, right, name = order[a], order[b], a + b
            if name in order:
                raise ValueError(f"two merges make {name}")
            self.join[left, right] = order[name] = len(order)
            self.parts.append((left, right))
            symbols.append(symbols[left] + symbols[right])
        self.names = list(order)
        self.ids = [vocabulary[x] for x in self.names]
        self.sizes = list(map(len, symbols))
        self.reach = max(self.sizes, default=1)
        self.lookahead = self.longest_chain()
        self.trie: dict = {}
        for k, path in enumerate(symbols):
            node = self.trie
            for s in path:
                node = node.setdefault(s, {})
            node[TOKEN] = k
        self.known: dict[tuple[int, int], bool] = {}

    def right_parts(self, token: int) -> Iterator[int]:
        """The token, what it ends with, what that ends with, down to a symbol."""
        yield token
        while token >= self.bases:
            token = self.parts[token][1]
            yield token

    def longest_chain(self) -> int:
        """Symbols that may have to be seen behind a boundary until no merge can reach it any more. A merge takes the end
        of the token before a boundary; its own end may be taken by an earlier merge alone, and so on. Merges in their
        order: the chain behind each is that of its right part's ends."""
        best: dict[int, int] = {}
        for token in range(self.bases, len(self.parts)):
            left, right = self.parts[token]
            chain = self.sizes[right] + max((best.get(x, 0) for x in self.right_parts(right)), default=0)
            best[left] = max(best.get(left, 0), chain)
        return max(best.values(), default=0)

    def check(self) -> None:
        """Raises if a token's own text is encoded otherwise: such a list has no bounded lookahead that holds."""
        for k in range(self.bases, len(self.parts)):
            if not self.compatible(*self.parts[k]) and self.join[self.parts[k]] != k:
                raise ValueError(f"no text is encoded as {self.names[k]!r}")
            left, right = self.parts[k]
            if not self.made_whole(left, right, k):
                raise ValueError(f"no text is encoded as {self.names[k]!r}")

    def made_whole(self, left: int, right: int, token: int) -> bool:
        """Whether the two parts stand side by side until their own merge."""
        a, b, bound = left, right, token
        while True:
            made = self.join.get((a, b), bound)
            if made < bound and (a, b) != (left, right):
                return False
            if a > b and a >= self.bases or b < self.bases <= a:
                bound, a = a, self.parts[a][1]
            elif b >= self.bases:
                bound, b = b + 1, self.parts[b][0]
            else:
                return True

    def compatible(self, a: int, b: int) -> bool:
        """Whether the encoding of both tokens' text is just a, b: no merge across the boundary comes before those that
        made them. Undoes the later of the two merges, again and again."""
        known = self.known.get((a, b))
        if known is None:
            if len(self.known) > 1_000_000:
                self.known.clear()
            known = self.known[a, b] = self._compatible(a, b)
        return known

    def short(self, symbols: list[str]) -> list[int]:
        """Tokens of a word that is held whole: the transducer's steps without its emissions."""
        trie, known, compatible = self.trie, self.known, self.compatible
        last, back, live = [-1], [-1], []
        for n, symbol in enumerate(symbols):
            live.append((n, trie))
            going, token = [], -1
            for state in live:
                child = state[1].get(symbol)
                if child is not None:
                    at = state[0]
                    going.append((at, child))
                    if token < 0 and TOKEN in child:
                        k, before = child[TOKEN], last[at]
                        fits = before < 0 or known.get((before, k))
                        if fits or fits is None and compatible(before, k):
                            token, start = k, at
            if token < 0:
                raise ValueError(f"no token for {symbol!r}")
            live = going
            last.append(token)
            back.append(start)
        out, at = [], len(symbols)
        while at:
            out.append(last[at])
            at = back[at]
        return out[::-1]

    def _compatible(self, a: int, b: int) -> bool:
        bound = len(self.parts)
        while True:
            if (made := self.join.get((a, b), bound)) < bound:
                return False
            if a > b and a >= self.bases or b < self.bases <= a:
                bound, a = a, self.parts[a][1]  # the same merge further left comes first, so this one does not bind
            elif b >= self.bases:
                bound, b = b + 1, self.parts[b][0]
            else:
                return True


class Transducer:
    """Takes a word's symbols one by one, gives tokens as soon as every later end of the word agrees on them."""

    def __init__(self, merges: MergeList):
        self.m = merges
        self.reset()

    def reset(self) -> None:
        self.n = self.base = 0
        self.last: list[int] = [-1]  # at each boundary from base: the last token
        self.back: list[int] = [-1]  # and where it starts
        self.live: list[tuple[int, dict]] = []

    def feed(self, symbol: str) -> list[int]:
        merges, base = self.m, self.base
        self.live.append((self.n, merges.trie))
        live, token, start = [], -1, -1
        for at, node in self.live:
            child = node.get(symbol)
            if child is None:
                continue
            live.append((at, child))
            k = child.get(TOKEN)
            if k is not None and token < 0 and ((before := self.last[at - base]) < 0 or merges.compatible(before, k)):
                token, start = k, at
        if token < 0:
            raise ValueError(f"no token for {symbol!r}")
        self.n += 1
        self.live = live
        self.last.append(token)
        self.back.append(start)
        if len(self.last) <= 4 * merges.reach:
            return []
        out = self.settle()
        if len(self.last) > 4 * merges.reach + merges.lookahead:
            raise ValueError("the merge list holds more than its lookahead")
        return out

    def settle(self) -> list[int]:
        """Emits up to the last boundary that lies on the way back from every live one."""
        ends = {self.n, *(at for at, _ in self.live)}
        while len(ends) > 1:
            ends.remove(far := max(ends))
            ends.add(self.back[far - self.base])
        return self.emit(ends.pop())

    def emit(self, end: int) -> list[int]:
        out, at = [], end
        while at > self.base:
            out.append(self.last[at - self.base])
            at = self.back[at - self.base]
        cut = end - self.base
        if cut > 0:
            self.last, self.back, self.base = self.last[cut:], self.back[cut:], end
        return out[::-1]

    def finish(self) -> list[int]:
        out = self.emit(self.n)
        self.reset()
        return out


class Decoder:
    """Ids to text, piece by piece. Without a byte decoder tokens stand as they are, with spaces between; with one,
    their letters are bytes again, and a character waits until its last byte has come."""

    def __init__(self, names: dict[int, str], special: dict[int, str], bytewise: bool):
        self.names, self.special, self.bytewise = names, special, bytewise
        self.codes = {x: b for b, x in enumerate(LETTERS)}
        self.reset()

    def reset(self) -> None:
        self.started, self.utf8 = False, codecs.getincrementaldecoder("utf-8")("replace")

    def feed(self, token: int) -> str:
        name = self.special.get(token) or self.names.get(token)
        if name is None:
            return ""
        if not self.bytewise:
            space, self.started = " " * self.started, True
            return space + name
        data = name.encode() if token in self.special else bytes(self.codes[x] for x in name)
        return self.utf8.decode(data)

    def finish(self) -> str:
        out = self.utf8.decode(b"", True) if self.bytewise else ""
        self.reset()
        return out


class WordEncoder:
    """Encoder of a tokenizer file that drops white space and encodes words apart.

    What a text gives depends on its parts between white space alone; their ids, and those of the words that they fall
    into, are kept in one cache of bounded size, which forgets all when it is full.
    """

    def __init__(self, spec: str):
        j = json.loads(spec)
        model, steps = j["model"], j["normalizer"]["normalizers"]
        split = j["pre_tokenizer"]["pretokenizers"][0]
        if [x["type"] for x in steps] != ["NFC", "Replace", "Lowercase"] or not split["invert"] or split["behavior"] != "Removed" or j["decoder"]:
            raise ValueError("another kind of tokenizer file")
        merges = [tuple(x.split(" ")) if isinstance(x, str) else tuple(x) for x in model["merges"]]
        self.merges = MergeList(model["vocab"], merges, model["end_of_word_suffix"] or "")
        self.special = {x["content"]: x["id"] for x in j["added_tokens"]}
        self.cut = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")")
        self.pieces = regex.compile(split["pattern"]["Regex"])
        self.transducer = Transducer(self.merges)
        self.decoder = Decoder({v: k for k, v in model["vocab"].items()}, {v: k for k, v in self.special.items()}, False)
        size = 1 + max(max(model["vocab"].values()), max(self.special.values(), default=0))
        self.decimals = [str(k) for k in range(size)]
        self.texts = [self.decoder.special.get(k) or self.decoder.names.get(k, "") for k in range(size)]
        self.cache: dict[str, tuple[int, ...]] = {}
        self.odd_special = not all(x.startswith("<|") for x in self.special)

    def keep(self, part: str, ids: tuple[int, ...]) -> tuple[int, ...]:
        if len(part) <= 64:
            if len(self.cache) >= CACHE_ENTRIES:
                self.cache.clear()
            self.cache[part] = ids
        return ids

    def word(self, piece: str) -> tuple[int, ...]:
        """Ids of one word, which a long one gives as they settle."""
        known = self.cache.get(piece)
        if known is not None:
            return known
        data = [LETTERS[b] for b in piece.encode()]
        data[-1] += self.merges.word_end
        if len(data) > 4 * self.merges.reach:
            out: list[int] = []
            for symbol in data:
                out += self.transducer.feed(symbol)
            out += self.transducer.finish()
        else:
            out = self.merges.short(data)
        return self.keep(piece, tuple([self.merges.ids[k] for k in out]))

    def part(self, part: str) -> tuple[int, ...]:
        """Ids of what stands between white space."""
        if part.isalpha():
            return self.word(part)
        pieces = self.pieces.findall(part)
        if pieces == [part]:
            return self.word(part)
        return self.keep(part, tuple([t for piece in pieces for t in self.word(piece)]))

    def encode(self, text: str) -> list[int]:
        get, part, out = self.cache.get, self.part, []
        for segment in self.cut.split(text) if "<|" in text or self.odd_special else (text,):
            if segment in self.special:
                out.append(self.special[segment])
                continue
            if not segment.isascii():
                segment = unicodedata.normalize("NFC", segment).replace("Σ", "σ")  # each letter is lowered on its own: no final sigma
            segment = segment.lower()
            for x in SPACE.split(segment) if NOT_SPACE.search(segment) else segment.split():
                known = get(x)
                out += part(x) if known is None else known
        return out

    def digest(self, ids: list[int]) -> tuple[str, str]:
        """(SHA-256 of the decimal ids, SHA-256 of the decoded text)."""
        sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
        return sha(" ".join(map(self.decimals.__getitem__, ids))), sha(" ".join(map(self.texts.__getitem__, ids)))

    def decode(self, ids: Iterable[int]) -> str:
        return "".join(map(self.decoder.feed, ids)) + self.decoder.finish()


_ENCODERS: dict[str, WordEncoder] = {}


def encoder_of(spec: str) -> WordEncoder:
    """One encoder for each tokenizer file and process."""
    key = hashlib.sha256(spec.encode()).hexdigest()
    if key not in _ENCODERS:
        _ENCODERS[key] = WordEncoder(spec)
    return _ENCODERS[key]


def encode_words(docs: DataFrame, path: str, id_col: str = "doc_id", text: str = "text", with_ids: bool = False, with_text: bool = False) -> DataFrame:
    """For each row: id, n_tokens, ids_sha256, decoded_sha256, and where asked for the ids and the decoded text.

    A null text is empty and has no ids. Each row stands for itself: repeated ids, ties and other columns play no part.
    Memory: a slice of texts, one text's parts, and caches of bounded size.
    """
    with open(path, encoding="utf-8") as f:
        spec = f.read(MODEL_BYTES + 1)
    if len(spec) > MODEL_BYTES:
        raise ValueError(f"{path} is too large to broadcast")
    encoder_of(spec).merges.check()
    held = docs.sparkSession.sparkContext.broadcast(spec)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = encoder_of(held.value)
        for batch in slices(batches, text, SLICE_BYTES):
            texts = [x.decode("utf-8", "replace") for x in byte_texts(batch.column(text))]
            lists = [encoder.encode(x) for x in texts]
            ids, decoded = zip(*map(encoder.digest, lists), strict=True)
            out = [batch.column(id_col), pa.array(list(map(len, lists)), pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())]
            if with_ids:
                out.append(pa.array(lists, pa.list_(pa.int32())))
            if with_text:
                out.append(pa.array([encoder.decode(x) for x in lists], pa.string()))
            yield pa.RecordBatch.from_arrays(out, names)

    names = [id_col, "n_tokens", "ids_sha256", "decoded_sha256"] + ["ids"] * with_ids + ["decoded"] * with_text
    kinds = [docs.schema[id_col].dataType.simpleString(), "long", "string", "string"] + ["array<int>"] * with_ids + ["string"] * with_text
    return docs.select(id_col, text).mapInArrow(run, ", ".join(f"`{a}` {b}" for a, b in zip(names, kinds, strict=True)))


def op7_streaming_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return encode_words(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
