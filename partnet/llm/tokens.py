"""Token ids of whole texts, piece by piece from a bounded cache.

A text of Latin letters, ASCII and ASCII white space is cut into pre-tokens by
the vocabulary's own rule; new pre-tokens go to the library's model many at a
time, already in the vocabulary's alphabet.

Any other text may be cut at a single space between two other characters without
changing its ids, for both kinds of vocabulary: pre-tokens never cross such a
space. Latin letters alone are one pre-token. A piece of letters,
digits, ASCII marks and single line ends falls into pre-tokens where the class
changes. Every other piece, and any text with a special token's string in it,
goes through the whole tokenizer. Ids are kept as packed little-endian 32-bit
numbers, so a text's ids are a join of byte strings.
"""

from __future__ import annotations

import codecs
import re

import numpy as np
from tokenizers import Tokenizer, pre_tokenizers

from partnet.llm.common import kept

CACHE_LIMIT = 400_000
PIECE_LIMIT = 100_000
LONG_PIECE = 200
GROUP_CHARS = 1 << 21
JOINED = 2_000
WORD_END = "</w>"
LATIN_END = 0x250
#: capitals below LATIN_END that are lower-cased to something beyond it
STRAYS = "".join(x for x in map(chr, range(LATIN_END)) if any(ord(y) >= LATIN_END for y in x.lower()))
beyond_latin = re.compile(f"[{STRAYS}{chr(LATIN_END)}-\U0010ffff]").search
LETTERS = "A-Za-z" + "".join(x for x in map(chr, range(0xC0, LATIN_END)) if x.isalpha() and x not in STRAYS)
MARKS = r"!-&(-/:-@\[-`{-~"
beyond_plain = re.compile(f"[^{LETTERS}0-9{MARKS}' \t\n\r]").search
ENDINGS = "'(?:[stmd]|re|ve|ll)"
#: pre-tokens of plain texts: with the space before them, or lower-cased and without white space
SPACED = re.compile(rf"{ENDINGS}| ?(?:[{LETTERS}]+|[0-9]+|[{MARKS}']+)|\s+(?!\S)|\s+").findall
BARE = re.compile(f"[{LETTERS}]+|{ENDINGS}|[0-9]|[{MARKS}']+").findall
PLAIN = re.compile(f"[{LETTERS}0-9{MARKS}]+(?:\n[{LETTERS}0-9{MARKS}]+)*").fullmatch


def byte_alphabet() -> dict[int, int]:
    """Code points that byte-level vocabularies use for the bytes that are not printable: 256 and on, in byte order."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    return {b: 256 + i for i, b in enumerate(b for b in range(256) if b not in printable)}


def pack(ids: list[int]) -> bytes:
    return np.array(ids, dtype="<u4").tobytes()


class MemoEncoder:
    """encode_all(texts) gives each text's ids as packed bytes, as the library does with add_special_tokens=False.

    The string of a special token is that token, as it is to the library; with strings_as_text it is ordinary text.
    """

    def __init__(self, path: str, limit: int = CACHE_LIMIT, strings_as_text: bool = False):
        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True  # pieces that are lower-cased here may come to look like such a string
        added = [] if strings_as_text else [x.content for x in self.tokenizer.get_added_tokens_decoder().values()]
        self.names_token = re.compile("|".join(map(re.escape, added))).search if added else lambda text: None
        self.limit = limit
        #: pieces between spaces, of texts that are not plain
        self.known: dict[str, bytes] = {}
        #: pre-tokens, in two generations
        self.bare: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        #: byte-level vocabularies keep the space as the first byte of the next piece; the others drop white space and case
        self.spaced = self.tokenizer.normalizer is None
        self.regular = re.compile(r"(?<=\S) (?=\S)").split
        self.atoms_of = re.compile(f"[{LETTERS}]+|[0-9]{'+' if self.spaced else ''}|[{MARKS}]+{'|\n' if self.spaced else ''}").findall
        # the same model behind a plain split: words come to it joined by line ends, in the vocabulary's alphabet
        self.model = Tokenizer(self.tokenizer.model)
        self.model.pre_tokenizer = pre_tokenizers.Split("\n", "removed")
        self.alphabet = "".join("\n" if b == 10 else chr(byte_alphabet().get(b, b)) for b in range(256))
        vocabulary = self.tokenizer.get_vocab()
        self.token_chars = np.zeros(max(vocabulary.values()) + 1, dtype=np.int64)
        self.ends_word = np.zeros(self.token_chars.size, dtype=bool)
        for token, i in vocabulary.items():
            self.token_chars[i], self.ends_word[i] = len(token), token.endswith(WORD_END)

    def with_special(self, texts: list[str]) -> list[bytes]:
        """Whole texts, special tokens' strings as those tokens."""
        self.tokenizer.encode_special_tokens = False
        made = [pack(x.ids) for x in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)] if texts else []
        self.tokenizer.encode_special_tokens = True
        return made

    def forget(self) -> None:
        """Gives the caches' memory back; workers live on after a stage."""
        self.known, self.older, self.bare = {}, {}, {}

    def ids(self, text: str) -> list[int]:
        return self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids

    def learn_words(self, words: list[str], into: dict[str, bytes], front: str) -> None:
        """Pre-tokens of Latin letters, digits or marks. Joined ids are cut again where a word ends, or by the characters that tokens cover."""
        for at in range(0, len(words), JOINED):
            part = words[at : at + JOINED]
            line, _ = codecs.charmap_decode((front + ("\n" + front).join(part)).encode(), "strict", self.alphabet)
            ids = np.array(self.model.encode_batch_fast([line], add_special_tokens=False)[0].ids, dtype="<u4")
            if self.spaced:
                sizes = np.fromiter(map(len, line.split("\n")), dtype=np.int64, count=len(part))
                ends = np.searchsorted(np.cumsum(self.token_chars[ids]), np.cumsum(sizes)) + 1
            else:
                ends = np.flatnonzero(self.ends_word[ids]) + 1
            packed, start = ids.tobytes(), 0
            for word, end in zip(part, (4 * ends).tolist(), strict=True):
                into[word] = packed[start:end]
                start = end

    def learn_others(self, pieces: list[str], into: dict[str, bytes], front: str) -> None:
        for at in range(0, len(pieces), JOINED):
            part = pieces[at : at + JOINED]
            for x, got in zip(part, self.tokenizer.encode_batch_fast([front + x for x in part], add_special_tokens=False), strict=True):
                into[x] = pack(got.ids)

    def learn(self, fresh: set[str]) -> list[str]:
        """Adds pieces to the cache; returns those that are not to stay."""
        known, bare, front = self.known, self.bare, " " if self.spaced else ""
        words = [x for x in fresh if x.isalpha() and len(x) <= LONG_PIECE]
        others = fresh.difference(words)
        if not self.spaced or beyond_latin("\n".join(words)):
            odd = [x for x in words if beyond_latin(x) or not (self.spaced or x.islower())]
            others.update(odd)
            words = list(set(words).difference(odd))
        mixed = {x: self.atoms_of(x if self.spaced else x.lower()) for x in others if len(x) <= LONG_PIECE and PLAIN(x)}
        firsts = {x[0] for x in mixed.values() if x and self.spaced}.difference(words)
        self.learn_words(words + [x for x in firsts if x not in known], known, front)
        if "\n" not in bare:
            bare["\n"] = pack(self.ids("\n"))
        inner = {a for x in mixed.values() for a in (x[1:] if self.spaced else x)}
        self.learn_words([x for x in inner if x not in bare], bare, "")
        for piece, atoms in mixed.items():
            head = [known[atoms[0]]] if self.spaced else [bare[atoms[0]]]
            known[piece] = b"".join(head + [bare[x] for x in atoms[1:]])
        left = list(others.difference(mixed))
        self.learn_others(left, known, front)
        return [x for x in left if len(x) > LONG_PIECE] + [x for x in mixed if "\n" in x]

    def plain(self, texts: list[str]) -> list[bytes]:
        """Texts without a character beyond the plain ones."""
        cut = [SPACED(x) for x in texts] if self.spaced else [BARE(x.lower()) for x in texts]
        if len(self.bare) > self.limit:
            self.older, self.bare = self.bare, {}
        bare, older = self.bare, self.older
        fresh = set().union(*cut).difference(bare)
        if older:
            kept = {x: older[x] for x in fresh if x in older}
            bare.update(kept)
            fresh.difference_update(kept)
        apart = [x for x in fresh if len(x) > LONG_PIECE or "\n" in x]
        fresh.difference_update(apart)
        self.learn_words(list(fresh), bare, "")
        self.learn_others(apart, bare, "")
        out = [b"".join(map(bare.__getitem__, x)) for x in cut]
        for x in apart:
            if len(x) > LONG_PIECE:
                del bare[x]
        return out

    def group(self, texts: list[str]) -> list[bytes]:
        whole = [i for i, x in enumerate(texts) if self.names_token(x)]
        odd = [i for i, x in enumerate(texts) if beyond_plain(x) and not self.names_token(x)]
        if not whole and not odd:
            return self.plain(texts)
        out, others = [b""] * len(texts), {*whole, *odd}
        rest = [i for i in range(len(texts)) if i not in others]
        for own, made in ((whole, self.with_special([texts[i] for i in whole])), (odd, self.pieces([texts[i] for i in odd])), (rest, self.plain([texts[i] for i in rest]))):
            for i, ids in zip(own, made, strict=True):
                out[i] = ids
        return out

    def pieces(self, texts: list[str]) -> list[bytes]:
        """Any texts, by what lies between their spaces."""
        if len(self.known) > PIECE_LIMIT:
            self.known = {}
        if len(self.bare) > self.limit:
            self.older, self.bare = self.bare, {}
        if not self.spaced:  # lower case comes first where that is what the library's own mapping gives
            texts = [x if beyond_latin(x) else x.lower() for x in texts]
        known, cut = self.known, [x.split(" ") for x in texts]
        heads = [x.pop(0) for x in cut] if self.spaced else []
        fresh = {x for x in set().union(*cut) if x not in known}
        if self.spaced:
            # a piece that is empty or has white space at an end may not be cut off there
            loose = {x for x in fresh if not x or x[0].isspace() or x[-1].isspace()}
            again = [i for i, (head, x) in enumerate(zip(heads, cut, strict=True)) if x and (not head or head[-1].isspace() or (loose and not loose.isdisjoint(x)))]
            for i in again:
                heads[i], *cut[i] = self.regular(texts[i])
            fresh = fresh - loose | {x for i in again for x in cut[i] if x not in known}
        once = self.learn(fresh)
        out = [b"".join(map(known.__getitem__, x)) for x in cut]
        for x in once:
            del known[x]
        if self.spaced:
            first = self.tokenizer.encode_batch_fast(heads, add_special_tokens=False)
            out = [pack(a.ids) + b for a, b in zip(first, out, strict=True)]
        return out

    def encode_all(self, texts: list[str | None]) -> list[bytes]:
        out, at = [], 0
        while at < len(texts):
            end, held = at, 0
            while end < len(texts) and (end == at or held < GROUP_CHARS):
                held += len(texts[end] or "")
                end += 1
            once = dict.fromkeys(x or "" for x in texts[at:end])  # copies often stand side by side
            once.update(zip(once, self.group(list(once)), strict=True))
            out += [once[x or ""] for x in texts[at:end]]
            at = end
        return out


def encoder(path: str) -> MemoEncoder:
    """One encoder for each vocabulary in a worker process, for steps that keep things."""
    return kept(path, MemoEncoder)
