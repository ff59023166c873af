"""Ids of whole texts by the ``tokenizers`` library, remembering the pieces of text it has seen.

A byte-level model never joins what stands on both sides of a blank between two visible
characters, and a model that drops white space never joins across any; the text is cut there, each
distinct piece goes through the library once, and the ids of a text are those of its pieces in
order.  A tokenizer of any other make gets whole texts, and so does a text that holds the string of an
added token such as an end mark, which the library gives one id.
"""

from __future__ import annotations

import json
import os
import re
from array import array
from contextlib import suppress
from functools import lru_cache
from itertools import islice

import numpy as np

#: Pieces that one worker remembers; when full it starts anew.
MOST_PIECES = 1_200_000
#: Of those, so many that were seen first stay when it starts anew: the frequent ones.
FIRST_PIECES = 400_000
LONGEST_PIECE = 64
#: White space other than blank and line feed; a superset of what any model's pattern takes for it.
_OTHER_SPACE = [c for c in map(chr, range(0x3001)) if c.isspace() and c not in " \n"]
_SEPARATOR = "\x01"
_BETWEEN = re.compile(r"(?<=\S)(?= \S)")


def model_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


class Encoder:
    """``encode`` gives the ids of each text as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.vocabulary = self.library.get_vocab_size()
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        #: strings that the library looks for before it cuts a text, in any case of letters
        self.added = [t["content"].lower() for t in made.get("added_tokens") or [] if t["content"]]
        before, clean = made.get("pre_tokenizer") or {}, made.get("normalizer")
        steps = before.get("pretokenizers", [])
        if before.get("type") == "ByteLevel" and before.get("use_regex") and not before.get("add_prefix_space") and clean is None:
            self.cut, self.lead = self._at_blanks, " "
        elif steps and steps[0].get("type") == "Split" and steps[0].get("behavior") == "Removed" and steps[0].get("invert") and r"\s" in str(steps[0]["pattern"]):
            self.cut, self.lead = self._without_blanks, ""
        else:
            self.cut, self.lead = None, ""
        self.known: dict[str, bytes] = {}
        blank = self.library.encode(" a", add_special_tokens=False).tokens[0][0]  # how the model writes one
        self.leads = np.zeros(self.vocabulary + 1, bool)
        for token, k in self.library.get_vocab().items():
            self.leads[k] = token.startswith(blank)
        alone = self.library.encode(_SEPARATOR, add_special_tokens=False).ids
        self.separator = alone[0] if len(alone) == 1 else -1
        self.marks = {c: self._ids([c])[0] for c in ".,;:|"}
        feed = self.library.encode("\n", add_special_tokens=False).ids
        self.feed = feed[0] if len(feed) == 1 else -1

    @staticmethod
    def _at_blanks(text: str) -> list[str]:
        """The pieces after the first lack their leading blank; the first one may have any."""
        if "  " not in text and "\n " not in text and " \n" not in text and text[0] != " " and text[-1] != " " and not any(c in text for c in _OTHER_SPACE):
            # a line feed between visible characters is a token of its own, and ends the piece before it
            return text.replace("\n", " \n").split(" ")
        first, *rest = _BETWEEN.split(text)
        return [first, *(p[1:] for p in rest)]

    @staticmethod
    def _without_blanks(text: str) -> list[str]:
        with suppress(UnicodeEncodeError):  # in Latin-1 the model's normal form is lower case and nothing else
            text.encode("latin-1")
            text = text.lower()
        return ["", *text.replace("\n", " ").split(" ")]

    def _new(self, pieces: list[str]) -> dict[str, bytes]:
        """Ids of pieces; a Latin word and the mark after it are never one token, so words are looked up without it."""
        out: dict[str, bytes] = {}
        marked, whole, after_feed = [], set(), []
        for p in pieces:
            if self.lead and p[:1] == "\n":
                after_feed.append(p)
            elif p[-1:] in self.marks and p[:-1].isalpha() and p < "\u0250" and max(p) < "\u0250":
                marked.append(p)
                if p[:-1] not in self.known:
                    whole.add(p[:-1])
            else:
                whole.add(p)
        out |= self._told_apart([*whole])
        for p in marked:
            out[p] = (self.known.get(p[:-1]) or out[p[:-1]]) + self.marks[p[-1]]
        if after_feed:
            ids = np.array(self.library.encode_batch_fast(["".join(after_feed)], add_special_tokens=False)[0].ids, "<u4")
            out |= self._sliced(after_feed, ids, np.flatnonzero(ids == self.feed)) or dict(zip(after_feed, self._ids(after_feed), strict=True))
        return out

    @staticmethod
    def _sliced(pieces: list[str], ids: np.ndarray, at: np.ndarray, skip: int = 0) -> dict[str, bytes] | None:
        """What begins at each place belongs to each piece; None if there aren't as many."""
        if len(at) != len(pieces):
            return None
        data, at = ids.tobytes(), at.tolist()
        return {p: data[4 * a : 4 * (b - skip)] for p, a, b in zip(pieces, at, [*at[1:], len(ids) + skip], strict=True)}

    def _told_apart(self, pieces: list[str]) -> dict[str, bytes]:
        """Many pieces go through the library as one text, and are told apart in what it returns."""
        if not pieces:
            return {}
        if self.lead:  # each piece begins with the only blank it has
            ids = np.array(self.library.encode_batch_fast([self.lead + self.lead.join(pieces)], add_special_tokens=False)[0].ids, "<u4")
            found = self._sliced(pieces, ids, np.flatnonzero(self.leads[ids]))
        elif any(_SEPARATOR in p for p in pieces):
            found = None
        else:
            ids = np.array(self.library.encode_batch_fast([f" {_SEPARATOR} ".join(pieces)], add_special_tokens=False)[0].ids, "<u4")
            found = self._sliced(pieces, ids, np.concatenate([[0], np.flatnonzero(ids == self.separator) + 1]), 1)
        return found or dict(zip(pieces, self._ids([self.lead + p for p in pieces]), strict=True))

    def _ids(self, pieces: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.library.encode_batch_fast(pieces, add_special_tokens=False)]

    def encode(self, texts: list[str]) -> list[bytes]:
        if self.cut is None:
            return self._ids(texts) if texts else []
        whole = [k for k, t in enumerate(texts) if self._holds_added(t)]
        if whole:
            rest = set(whole)
            cut = iter(self._by_pieces([t for k, t in enumerate(texts) if k not in rest]))
            uncut = iter(self._ids([texts[k] for k in whole]))
            return [next(uncut if k in rest else cut) for k in range(len(texts))]
        return self._by_pieces(texts)

    def _holds_added(self, text: str) -> bool:
        if not self.added:
            return False
        low = text.lower()
        return any(t in low for t in self.added)

    def _by_pieces(self, texts: list[str]) -> list[bytes]:
        cuts = [self.cut(t) if t else [""] for t in texts]
        firsts = iter(self._ids([c[0] for c in cuts if c[0]]))
        heads = [next(firsts) if c[0] else b"" for c in cuts]
        flat = [p for c in cuts for p in c[1:]]
        if len(self.known) > MOST_PIECES:
            self.known = dict(islice(self.known.items(), FIRST_PIECES))
        found = [*map(self.known.get, flat)]
        absent = [k for k, ids in enumerate(found) if ids is None]
        if absent:
            missing = list({flat[k] for k in absent})
            new = self._new(missing)
            self.known.update((p, ids) for p, ids in new.items() if len(p) <= LONGEST_PIECE)
            for k in absent:
                found[k] = new[flat[k]]
        out, at = [], 0
        for head, c in zip(heads, cuts, strict=True):
            to = at + len(c) - 1
            out.append(head + b"".join(found[at:to]))
            at = to
        return out


@lru_cache(maxsize=2)
def encoder(path: str) -> Encoder:
    """One for each worker process and model."""
    return Encoder(path)
