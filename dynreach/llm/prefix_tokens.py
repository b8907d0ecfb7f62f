"""Token counts by a prefix dynamic programme over byte-level BPE.

For every prefix of a pre-token there is exactly one token that the encoding of the
prefix ends with: the one whose pairing with the last token of the shorter prefix
survives re-encoding. The programme keeps that token and the count for each prefix, so
``count[i] = count[i - len(token)] + 1``. Counts at all prefixes answer truncation and
budget questions without encoding again.

Defined cases: null or empty text has no tokens; an added special string inside a text is
one token, as the tokenizer library does by default; texts are never cut; repeated rows give
repeated results; extra columns of the input are ignored.
"""

from __future__ import annotations

import json
import re
from bisect import bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Entries that a worker keeps before it starts its table of units anew.
CACHE_UNITS = 1_500_000
#: Longer units are counted without being kept.
CACHE_CHARS = 64
#: Characters of text whose units are held at once.
GROUP_CHARS = 8_000_000
#: The rank of merges that don't exist.
NEVER = 1 << 60


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in for each byte in byte-level vocabulary files."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    stand_in = {b: chr(b) for b in plain}
    for rank, b in enumerate(x for x in range(256) if x not in set(plain)):
        stand_in[b] = chr(256 + rank)
    return stand_in


def blank(c: str) -> bool:
    """White space as the pre-token pattern sees it."""
    return c.isspace() and not "\x1c" <= c <= "\x1f"


class PrefixCounter:
    """Counts of tokens at every prefix, from a byte-level BPE file of the tokenizers library."""

    def __init__(self, path: str, pattern: str):
        import regex

        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        raw = {s: b for b, s in byte_alphabet().items()}
        as_bytes = lambda s: bytes(raw[c] for c in s)
        self.vocab = {}
        special = {t["content"] for t in spec["added_tokens"]}
        for word, i in spec["model"]["vocab"].items():
            if word not in special:
                self.vocab[as_bytes(word)] = i
        self.bytes_of = {i: w for w, i in self.vocab.items()}
        merges = (m.split(" ") if isinstance(m, str) else m for m in spec["model"]["merges"])
        self.rank = {(as_bytes(a), as_bytes(b)): r for r, (a, b) in enumerate(merges)}
        #: token -> the two tokens it is merged from, and the rank of that merge
        self.parts = {}
        for (a, b), r in self.rank.items():
            self.parts.setdefault(self.vocab[a + b], (self.vocab[a], self.vocab[b], r))
        self.joint = {(self.vocab[a], self.vocab[b]): r for (a, b), r in self.rank.items()}
        self.backward = self._backward_trie()
        self.special = regex.compile("|".join(map(regex.escape, sorted(special)))) if special else None
        self.split = regex.compile(pattern)
        self.boundary = re.compile(" (?=\\S)")
        self.irregular = re.compile(" (?!\\S)")
        self.pairs: dict[tuple[int, int], bool] = {}
        self.whole: dict[int, bool] = {}
        self.edges: dict[tuple[int, int], list[tuple[int, int]]] = {}
        self.kept: dict[str, dict[str, int]] = {"": {}, " ": {}}

    def merge(self, word: bytes) -> list[bytes]:
        """Plain rank-by-rank merging; used to learn which pairs stand."""
        parts = [word[i : i + 1] for i in range(len(word))]
        while len(parts) > 1:
            ranked = [(self.rank.get((a, b), NEVER), i) for i, (a, b) in enumerate(zip(parts, parts[1:]))]
            r, i = min(ranked)
            if r == NEVER:
                break
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        return parts

    def _backward_trie(self) -> dict:
        """Tokens by their bytes from the last to the first; key -1 holds the token."""
        root: dict = {}
        for w, i in self.vocab.items():
            node = root
            for byte in reversed(w):
                node = node.setdefault(byte, {})
            node[-1] = i
        return root

    def edge(self, token: int, side: int) -> list[tuple[int, int]]:
        """Parts of a token at its left (0) or right (1) end, each with the rank at which it is merged away."""
        found = self.edges.get((token, side))
        if found is None:
            found, x, gone = [], token, NEVER
            while True:
                found.append((x, gone))
                if x not in self.parts:
                    break
                x, gone = self.parts[x][side], self.parts[x][2]
            self.edges[token, side] = found
        return found

    def stands(self, left: int, right: int) -> bool:
        """Whether left, right is what their bytes encode to: no merge across the seam comes
        while both of its parts exist. Of equal ranks the one further left comes first."""
        known = self.pairs.get((left, right))
        if known is None:
            if len(self.pairs) > CACHE_UNITS:
                self.pairs.clear()
            joint, known = self.joint, self.stands_alone(left) and self.stands_alone(right)
            for x, x_gone in self.edge(left, 1):
                for y, y_gone in self.edge(right, 0):
                    r = joint.get((x, y), NEVER)
                    if r < x_gone and r <= y_gone and r != NEVER:
                        known = False
            self.pairs[left, right] = known
        return known

    def stands_alone(self, token: int) -> bool:
        known = self.whole.get(token)
        if known is None:
            w = self.bytes_of[token]
            known = self.whole[token] = self.merge(w) == [w]
        return known

    def programme(self, word: bytes, count: list[int] | None = None, last: list[int] | None = None) -> list[int]:
        """count[i] for every i in 0..len(word): tokens of word[:i] as one pre-token.

        count and last may hold the states of a prefix already; they are carried on in place.
        """
        count, last = ([0], [-1]) if count is None else (count, last)
        root, pairs, stands = self.backward, self.pairs, self.stands
        for end in range(len(count), len(word) + 1):
            node, start = root, end
            while True:
                start -= 1
                node = node[word[start]]
                token = node.get(-1)
                if token is None:
                    continue
                if start == 0:
                    if self.stands_alone(token):
                        break
                else:
                    fits = pairs.get((last[start], token))
                    if fits if fits is not None else stands(last[start], token):
                        break
            count.append(count[start] + 1)
            last.append(token)
        return count

    def learn(self, units: set[str], lead: str, into: dict[str, int]) -> None:
        """Counts new units. Their pre-tokens run in sorted order, so that those with a common
        prefix share its states."""
        cut = {u: self.split.findall(lead + u) for u in units}
        known: dict[str, int] = {}
        word, count, last = b"", [0], [-1]
        for p in sorted({p for ps in cut.values() for p in ps}):
            new, k = p.encode(), 0
            for x, y in zip(word, new):
                if x != y:
                    break
                k += 1
            del count[k + 1 :], last[k + 1 :]
            word = new
            known[p] = self.programme(word, count, last)[-1]
        for u, ps in cut.items():
            into[u] = sum(map(known.__getitem__, ps))

    def pieces(self, text: str) -> list[tuple[str, bool]]:
        """Text between special strings, and the special strings themselves (True)."""
        if self.special is None or not self.special.search(text):
            return [(text, False)]
        out, at = [], 0
        for m in self.special.finditer(text):
            out += [(text[at : m.start()], False), (m.group(), True)]
            at = m.end()
        return [p for p in [*out, (text[at:], False)] if p[0]]

    def units(self, text: str) -> tuple[str, list[str]]:
        """The head of a text, then what follows each blank at which pre-tokens always part."""
        cut = self.boundary.split(text) if self.irregular.search(text) else text.split(" ")
        return cut[0], cut[1:]

    def counts(self, texts: list[str | None]) -> list[int]:
        out, group, held = [0] * len(texts), [], 0
        for i, text in enumerate(texts):
            if text:
                group.append(i)
                held += len(text)
            if group and (held >= GROUP_CHARS or i + 1 == len(texts)):
                self._count_group(texts, group, out)
                group, held = [], 0
        return out

    def _count_group(self, texts: list[str | None], group: list[int], out: list[int]) -> None:
        units, new, long = [], {"": set(), " ": set()}, {}
        for i in group:
            for piece, special in self.pieces(texts[i]):
                if special:
                    out[i] += 1
                else:
                    head, rest = self.units(piece)
                    units.append((i, head, rest))
                    new[""].add(head)
                    new[" "].update(rest)
        for lead, kept in self.kept.items():
            missing = new[lead].difference(kept)
            long[lead] = [u for u in missing if len(u) > CACHE_CHARS]
            if len(kept) + len(missing) > CACHE_UNITS:
                kept.clear()
                missing = new[lead]
                long[lead] = [u for u in missing if len(u) > CACHE_CHARS]
            self.learn(missing, lead, kept)
        first, later = self.kept[""], self.kept[" "].__getitem__
        for i, head, rest in units:
            out[i] += first[head] + sum(map(later, rest))
        for lead in self.kept:
            for u in long[lead]:
                self.kept[lead].pop(u, None)

    def count(self, text: str | None) -> int:
        return self.counts([text])[0]

    def prefixes(self, text: str | None) -> list[int]:
        """Tokens of text[:i] for every i in 0..len(text), each as if encoded on its own.

        Inside a special string the prefix holds ordinary characters, which join what precedes them.
        """
        out, plain, plain_base = [0], "", 0
        for piece, special in self.pieces(text or ""):
            if special:
                inner = self._plain_prefixes(plain + piece)[len(plain) + 1 : -1]
                out += [*(plain_base + c for c in inner), out[-1] + 1]
                plain, plain_base = "", out[-1]
            else:
                plain, plain_base = piece, out[-1]
                out += [plain_base + c for c in self._plain_prefixes(piece)[1:]]
        return out

    def _plain_prefixes(self, text: str) -> list[int]:
        """A prefix that ends in white space counts the whole run as one pre-token."""
        out = [0] * (len(text) + 1)
        base, run, run_base = 0, 0, 0
        for m in self.split.finditer(text):
            p, s = m.group(), m.start()
            if s == 0 or not blank(text[s - 1]):
                run, run_base = s, base
            at = self._by_char(p)
            for k in range(1, len(p) + 1):
                out[s + k] = base + at[k]
            blanks = len(p) if blank(p[-1]) else int(blank(p[0]))
            if blanks:
                joint = self._by_char(text[run : s + blanks])
                for k in range(1, blanks + 1):
                    out[s + k] = run_base + joint[s - run + k]
            elif p[0] == "'" and len(p) > 1 and p[1].isalpha():
                for k in range(1, len(p)):
                    out[s + k] = base + sum(self.programme(c.encode())[-1] for c in (p[0], p[1:k]) if c)
            base += at[-1]
        return out

    def _by_char(self, word: str) -> list[int]:
        by_byte = self.programme(word.encode())
        out, at = [0], 0
        for c in word:
            at += len(c.encode())
            out.append(by_byte[at])
        return out

    def longest_prefix(self, text: str | None, budget: int) -> int:
        """Characters of the longest prefix that has at most so many tokens."""
        counts = self.prefixes(text)
        return max(i for i, c in enumerate(counts) if c <= budget)

    def first_over(self, text: str | None, budget: int) -> int:
        """Characters of the shortest prefix over the budget; -1 if none is."""
        counts = self.prefixes(text)
        high = [0]
        for c in counts[1:]:
            high.append(max(high[-1], c))
        i = bisect_right(high, budget)
        return i if i < len(high) else -1


def _counter(path: str, pattern: str, kept: dict = {}) -> PrefixCounter:  # noqa: B006  one per worker
    if (path, pattern) not in kept:
        kept[path, pattern] = PrefixCounter(path, pattern)
    return kept[path, pattern]


def default_tokenizer() -> tuple[str, str]:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.PATTERN


def token_counts(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit: int = 512, path: str | None = None, pattern: str | None = None
) -> DataFrame:
    """(id, n_bytes, n_tokens, over_limit) of every row; one scan, no shuffle."""
    found = default_tokenizer()
    path, pattern = path or found[0], pattern or found[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(path, pattern)
        for batch in batches:
            counts = counter.counts(batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(counts, pa.int64())], [id_col, "n_bytes", "n_tokens"])

    rows = docs.select(id_col, text_col, F.octet_length(F.coalesce(text_col, F.lit(""))).cast("long").alias("n_bytes"))
    kind = docs.schema[id_col].dataType.simpleString()
    return rows.mapInArrow(run, f"{id_col} {kind}, n_bytes long, n_tokens long").withColumn("over_limit", F.col("n_tokens") > limit)


def prefix_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, pattern: str | None = None) -> DataFrame:
    """(id, counts): counts[i] = tokens of the first i characters."""
    found = default_tokenizer()
    path, pattern = path or found[0], pattern or found[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = _counter(path, pattern)
        for batch in batches:
            counts = [counter.prefixes(t) for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.list_(pa.int32()))], [id_col, "counts"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(id_col, text_col).mapInArrow(run, f"{id_col} {kind}, counts array<int>")
