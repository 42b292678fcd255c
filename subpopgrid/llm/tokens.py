"""Exact tokenization with a word cache in front of the tokenizers library."""

from __future__ import annotations

import re
from array import array

import numpy as np

from .common import hold, take_over

_OPEN: dict = {}
#: Entries of a worker's word cache before it becomes the older generation, and the longest word that is kept.
CACHE_WORDS, CACHE_CHARS = 500_000, 48
#: Text that is encoded at once.
SLICE_BYTES = 6 << 20
#: Unseen words whose texts are made ready at once.
BLOCK_WORDS = 20_000
#: Letters and then signs, but no apostrophe, which may begin a pre-token of its own with the letters behind it.
_SIGNED = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([!-&(-/:-@\[-`{-~]+)")


def vocabulary(name: str) -> str:
    """Path of a public vocabulary file; resolved on the executor, as every machine has its own copy."""
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_letters() -> dict[int, str]:
    """Byte-level vocabularies write each byte as a printable character: itself, or the next free one from 256 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    rest = (b for b in range(256) if b not in plain)
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class _Words(dict):
    """Ids of ``prefix + word`` as little-endian 32-bit bytes; None where the word alone does not fix its ids."""

    def __init__(self, owner: Encoder, prefix: str):
        super().__init__()
        self.owner, self.prefix, self.older, self.marks = owner, prefix, {}, {}

    def turn(self) -> None:
        """A full cache becomes the older generation."""
        if len(self) > CACHE_WORDS:
            self.older = dict(self)
            self.clear()

    def __missing__(self, word: str):
        self.turn()
        if word in self.older:
            ids = self.older[word]
        elif not word:
            ids = None if self.owner.spaced else b""
        elif word[-1].isspace() and self.owner.spaced:
            ids = None
        elif word[-1] in ".," and len(word) > 1 and word[-2] <= "ÿ" and word[-2].isalpha():
            # a run of letters and a mark behind it are split before the merges, so their ids are independent
            if (mark := self.marks.get(word[-1])) is None:
                mark = self.marks[word[-1]] = self.owner.whole(word[-1])
            return self[word[:-1]] + mark
        elif word.isalpha() and max(word) <= "ÿ":
            ids = self.owner.letters(self.prefix, word)
        elif self.owner.spaced and (parts := self.owner.parts(self, word)) is not None:
            return parts
        else:
            ids = self.owner.whole(self.prefix + word)
        if len(word) <= CACHE_CHARS:
            self[word] = ids
        return ids


class Encoder:
    """Encodes whole texts to the very ids of the library, as little-endian unsigned 32-bit bytes.

    ``spaced``: a byte-level vocabulary whose words carry the space before them. A text is cut only before a
    single space between two other characters, which is always a border of its pre-tokens; any other text goes to
    the library whole. Without ``spaced`` (lower case, white space dropped, words have end marks) every space is a
    border. A run of Latin letters is one pre-token, so it goes straight to the library's model.
    """

    def __init__(self, path: str, spaced: bool):
        from tokenizers import Tokenizer

        self.tokenizer, self.spaced = Tokenizer.from_file(path), spaced
        self.model, self.table = self.tokenizer.model, _byte_letters()
        self.first = _Words(self, "")
        self.rest = _Words(self, " ") if spaced else self.first
        self.line_break = self.whole("\n")
        self.lines = {k: v for k, v in self.table.items() if k != 10}  # line breaks stay as they are

    def whole(self, text: str) -> bytes:
        return array("I", self.tokenizer.encode(text, add_special_tokens=False).ids).tobytes()

    def letters(self, prefix: str, word: str) -> bytes:
        text = prefix + (word if self.spaced else word.lower())
        return array("I", [t.id for t in self.model.tokenize(text.encode().decode("latin-1").translate(self.table))]).tobytes()

    def parts(self, table: _Words, word: str) -> bytes | None:
        """Ids of a word of the spaced kind from those of its own pre-tokens, where their borders are certain.

        Signs behind letters are a pre-token, and so is a line break between two characters that are no white space.
        """
        if (m := _SIGNED.fullmatch(word)) is not None:
            return table[m[1]] + self.first[m[2]]
        if "\n" in word:
            lines = word.split("\n")
            if all(x and not x[0].isspace() and not x[-1].isspace() for x in lines):
                return self.line_break.join([table[lines[0]], *map(self.first.__getitem__, lines[1:])])
        return None

    def lookup(self, words: list[str]) -> tuple[list[bytes | None], list[int]]:
        """Ids of distinct words that follow a border, and which have none of their own; unseen runs of letters in blocks."""
        table = self.rest
        found = list(map(table.get, words))
        unseen = [i for i, x in enumerate(found) if x is None]
        tokenize = self.model.tokenize
        for lo in range(0, len(unseen), BLOCK_WORDS):
            table.turn()
            older, runs = table.older, []
            for i in unseen[lo : lo + BLOCK_WORDS]:
                w = words[i]
                if w.isalpha() and len(w) <= CACHE_CHARS and (w.isascii() or max(w) <= "ÿ"):
                    if (ids := older.get(w)) is None:
                        runs.append(i)
                    else:
                        found[i] = table[w] = ids
            if runs:
                text = "\n".join([table.prefix + words[i] for i in runs])
                lines = (text if self.spaced else text.lower()).encode().decode("latin-1").translate(self.lines).split("\n")
                for i, line in zip(runs, lines, strict=True):
                    found[i] = table[words[i]] = array("I", [t.id for t in tokenize(line)]).tobytes()
        for i in unseen:
            if found[i] is None:
                found[i] = table[words[i]]
        return found, [i for i in unseen if found[i] is None]

    def __call__(self, text: str | None) -> bytes:
        if not text:
            return b""
        if self.spaced:
            head, *tail = text.split(" ")
            try:
                return self.first[head] + b"".join(map(self.rest.__getitem__, tail))
            except TypeError:
                return self.whole(text)
        return b"".join(map(self.first.__getitem__, text.replace("\n", " ").split(" ")))


    def slices(self, texts, end_id: int):
        """(first row, behind the last, ids, counts) of successive rows of an Arrow string column, end ids included.

        The words of a slice are made distinct first, so a word costs a look-up once a slice; the ids of all words are
        then gathered as arrays. Slices hold about ``SLICE_BYTES`` of text (one longer text is a slice).
        """
        import pyarrow as pa
        import pyarrow.compute as pc

        sizes = pc.fill_null(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        ends, lo = np.cumsum(sizes), 0
        while lo < len(texts):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + SLICE_BYTES, side="right")))
            part = pc.fill_null(texts.slice(lo, hi - lo), "")
            lists = pc.split_pattern(part if self.spaced else pc.replace_substring(part, "\n", " "), " ")
            offsets = lists.offsets.to_numpy().astype(np.int64)
            offsets -= offsets[0]
            words = lists.flatten().dictionary_encode()
            at = words.indices.to_numpy(zero_copy_only=False).astype(np.int64)
            # a run of letters and one mark behind it are split before the merges: look up the letters alone
            marked = pc.match_substring_regex(words.dictionary, r"^[A-Za-zÀ-ÖØ-öø-ÿ]+[.,]$")
            bare = pc.if_else(marked, pc.utf8_slice_codeunits(words.dictionary, 0, -1), words.dictionary).dictionary_encode()
            found, unfixed = self.lookup(bare.dictionary.to_numpy(zero_copy_only=False).tolist())
            n_bare, flags = len(found), marked.to_numpy(zero_copy_only=False)
            found += [self.whole("."), self.whole(",")]
            second = np.where(flags, n_bare + pc.ends_with(words.dictionary, ",").to_numpy(zero_copy_only=False), -1)[at]
            first = bare.indices.to_numpy(zero_copy_only=False).astype(np.int64)[at]
            whole = []
            if self.spaced:
                bad = np.zeros(len(found), bool)
                bad[unfixed] = True
                heads = [self.first[w] for w in words.dictionary.take(pa.array(at[offsets[:-1]])).to_pylist()]
                odd = np.fromiter((x is None for x in heads), bool, len(heads))
                if bad.any():
                    inner = bad[first]
                    inner[offsets[:-1]] = False
                    odd |= np.add.reduceat(inner, offsets[:-1]) > 0
                odd[sizes[lo:hi] == 0] = False
                first[offsets[:-1]] = len(found) + np.arange(len(heads))  # a text's first word has no space before it
                second[offsets[:-1]] = -1
                whole = np.flatnonzero(odd).tolist()
                found = [x or b"" for x in [*found, *heads]]
            more = second >= 0
            place = np.arange(len(first)) + np.cumsum(more) - more
            line = np.empty(len(first) + int(more.sum()), np.int64)
            line[place], line[place[more] + 1] = first, second[more]
            lengths = np.fromiter(map(len, found), np.int64, len(found)) // 4
            starts, ids = np.cumsum(lengths) - lengths, np.frombuffer(b"".join(found), "<u4")
            each = lengths[line]
            behind = np.cumsum(each)
            flat = ids[np.repeat(starts[line] - (behind - each), each) + np.arange(int(behind[-1]))]
            counts = np.add.reduceat(each, place[offsets[:-1]])
            if whole:  # texts whose words do not fix their ids go to the library
                rows = np.split(flat, np.cumsum(counts)[:-1])
                for k in whole:
                    rows[k] = np.frombuffer(self.whole(part[k].as_py()), "<u4")
                    counts[k] = len(rows[k])
                flat = np.concatenate(rows)
            yield lo, hi, np.insert(flat, np.cumsum(counts), np.uint32(end_id)), counts + 1
            lo = hi


def encoder(name: str, spaced: bool) -> Encoder:
    """One encoder a worker process and vocabulary; ``name`` is a file of the public set or a path."""
    take_over("tokens")
    hold("tokens", _OPEN.clear)
    if (name, spaced) not in _OPEN:
        _OPEN[name, spaced] = Encoder(name if "/" in name else vocabulary(name), spaced)
    return _OPEN[name, spaced]
