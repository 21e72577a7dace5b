"""Language identification by cross parsing: the language whose sample parses a text into fewest phrases wins.

For each language a suffix automaton of a bounded labelled sample gives, from any place of a text, the
longest stretch that occurs in the sample. Taken one after the other these stretches parse the text; their
number, times the bits that name a place of the sample and divided by the text's length, estimates the cross
entropy in bits a symbol. Texts are lower-cased, and runs of anything but letters become one space.

So that a short sample is no bargain, a phrase costs no less than a letter of the alphabet of all samples
does, and a letter that a sample lacks costs such a letter beside its phrase. A label whose sample has no
letter is no language.

A null text or one without a letter is ``und`` with score 0. Ties go to the language first in order.
Repeated rows are predicted each by itself; without labelled rows everything is ``und``; an empty table
gives an empty result; extra columns are not read.
"""

from __future__ import annotations

from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from factorclust.llm.shared import FORGET, crc_mod, tidy

#: Bounds of the fit: characters of labelled text a language and of all, rows a language, languages.
SAMPLE_CHARS, TOTAL_CHARS, SAMPLE_ROWS, LANGUAGES = 32_000, 2_000_000, 64, 1_000
#: Letters of the least alphabet.
ALPHABET = 27
#: A text is of no known language if its best parse takes more than so many times the bits of spelling it, and a
#: margin of bits. Text of several languages stays near 1 (random letters: 2, an unlearned script: 4).
UNLIKELY, MARGIN = 1.5, 64
#: Entries of the table of transitions by common letters; rarer letters are found by bisection.
DENSE = 1 << 24
#: Symbols after which a second parse of a text starts beside the first; both are joined where they meet.
SEGMENT = 1024
#: Symbols and languages parsed side by side.
TOGETHER, ABREAST = 1 << 20, 16
UNDETERMINED = "und"

_letters: list[np.ndarray] = []
_built: dict[tuple, Parser] = {}
FORGET.append(_built.clear)


def is_letter() -> np.ndarray:
    if not _letters:
        _letters.append(np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000))
    return _letters[0]


def normalise(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(code points of all texts with one space, 32, for each run of other characters; where each text begins)."""
    flat = "\0".join((t or "").replace("\0", " ") for t in texts).lower() + "\0"
    code = np.frombuffer(flat.encode("utf-32-le", "replace"), np.uint32)
    end = code == 0
    gap = ~is_letter()[code] & ~end
    keep = ~end & ~(gap & np.concatenate([[True], (gap | end)[:-1]]))
    code = np.where(gap, np.uint32(32), code)
    before = np.cumsum(keep)
    ends = before[np.flatnonzero(end)]
    return code[keep], np.concatenate([[0], ends])


def automaton(text: np.ndarray, common: int) -> tuple[np.ndarray, dict[int, dict[int, int]]]:
    """The suffix automaton of ``text``: states by ``common`` + 1 symbols, -1 where no transition is (and in the last
    column), and the transitions by symbols of ``common`` or more, by state."""
    width = common + 1
    none = array("i", [-1]) * width
    table, rare = array("i", none), {}
    link, length, last = [-1], [0], 0

    def go(s: int, c: int) -> int:
        return table[s * width + c] if c < common else rare.get(s, {}).get(c, -1)

    def put(s: int, c: int, to: int) -> None:
        if c < common:
            table[s * width + c] = to
        else:
            rare.setdefault(s, {})[c] = to

    for c in text.tolist():
        new = len(length)
        table.extend(none)
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and go(p, c) < 0:
            put(p, c, new)
            p = link[p]
        if p >= 0:
            q = go(p, c)
            if length[q] == length[p] + 1:
                link[new] = q
            else:
                twin = len(length)
                table.extend(table[q * width : (q + 1) * width])
                if q in rare:
                    rare[twin] = dict(rare[q])
                length.append(length[p] + 1)
                link.append(link[q])
                link[q] = link[new] = twin
                while p >= 0 and go(p, c) == q:
                    put(p, c, twin)
                    p = link[p]
        last = new
    return np.frombuffer(table, np.int32).reshape(-1, width), rare


class Parser:
    """The automata of all languages: transitions by common letters in one table, by others in sorted keys.

    A state is the number of its row's first entry in the table.
    """

    def __init__(self, samples: dict[str, str]):
        texts = {k: normalise([v])[0] for k, v in sorted(samples.items())}
        texts = {k: t for k, t in texts.items() if (t != 32).any()}
        self.languages = list(texts)
        found, n = np.unique(np.concatenate([*texts.values(), np.zeros(0, np.uint32)]), return_counts=True)
        found = found[np.argsort(-n, kind="stable")]
        self.letters = len(found)
        self.symbol = np.full(0x110000, self.letters, np.int32)  # the last one: letters that no sample has
        self.symbol[found] = np.arange(len(found))
        # an automaton has less than two states a symbol
        self.common = max(1, min(self.letters, DENSE // max(1, 2 * sum(map(len, texts.values())) + 2)))
        self.width = self.common + 1  # the last entry stands for other letters
        self.lacks = np.ones((self.letters + 1, len(texts)), bool)
        tables, triples, roots, at = [], [], [], 0
        for k, t in enumerate(texts.values()):
            table, rare = automaton(self.symbol[t], self.common)
            roots.append(at * self.width)
            self.lacks[: self.common, k] = table[0, : self.common] < 0
            self.lacks[list(rare.get(0, ())), k] = False
            nowhere = table < 0
            table += at
            table *= self.width
            table[nowhere] = -1
            tables.append(table.ravel())
            triples += [((s + at) * (self.letters + 1) + c, (to + at) * self.width) for s, row in rare.items() for c, to in row.items()]
            at += len(table)
        self.table = np.concatenate([*tables, np.full(self.width, -1, np.int32)])
        self.dead = at * self.width  # where a letter leads that its sample lacks: whatever follows begins a phrase
        triples.sort()
        self.keys, self.values = np.array([x for x, _ in triples], np.int64), np.array([x for _, x in triples], np.int32)
        self.root = np.array(roots, np.int32)
        self.letter_bits = float(np.log2(max(ALPHABET, self.letters)))
        self.bits = np.array([max(self.letter_bits, np.log2(len(t))) for t in texts.values()])

    def _go(self, state: np.ndarray, by: np.ndarray, rare: bool) -> np.ndarray:
        """Where symbols lead from states of the same shape; -1 where nowhere."""
        to = self.table[state + np.minimum(by, self.common)]
        if rare and len(self.keys):
            few = (by >= self.common) & (by < self.letters) & (state != self.dead)
            if few.any():
                key = (state[few] // self.width).astype(np.int64) * (self.letters + 1) + by[few]
                at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
                to[few] = np.where(self.keys[at] == key, self.values[at], -1)
        return to

    def _step(self, state: np.ndarray, root: np.ndarray, by: np.ndarray, rare: bool) -> tuple[np.ndarray, np.ndarray]:
        """(next states, whether a phrase begins here)."""
        to = self._go(state, by, rare)
        miss = to < 0
        if miss.any():
            again = self._go(root[miss], by[miss], rare)
            to[miss] = np.where(again < 0, self.dead, again)
        return to, miss

    def phrases(self, code: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """Phrases of each text (rows) in each language (columns)."""
        symbols = np.concatenate([self.symbol[code], np.zeros(SEGMENT, np.int32)])
        rare = bool((symbols >= self.common).any())
        parts = [self._phrases(symbols, begin, self.root[k : k + ABREAST], rare) for k in range(0, len(self.languages), ABREAST)]
        return np.concatenate(parts, 1) if parts else np.zeros((len(begin) - 1, 0), np.int64)

    def _phrases(self, symbols: np.ndarray, begin: np.ndarray, root: np.ndarray, rare: bool) -> np.ndarray:
        """Each segment is parsed from its start; then each parse goes on into the next segment until it begins a
        phrase where that one's parse does, from where on both are the same."""
        size = np.diff(begin)
        parts = -(-size // SEGMENT)
        total, n_lang = int(parts.sum()), len(root)
        if not total:
            return np.zeros((len(size), n_lang), np.int64)
        owner = np.repeat(np.arange(len(size)), parts)
        start = begin[:-1][owner] + (np.arange(total) - np.repeat(np.cumsum(parts) - parts, parts)) * SEGMENT
        long = np.minimum(SEGMENT, begin[1:][owner] - start)
        mark = np.zeros((int(begin[-1]), n_lang), bool)
        order = np.argsort(-long, kind="stable")
        active = np.searchsorted(-long[order], -np.arange(int(long.max())), "left")  # segments longer than i
        state = np.repeat(root[None, :], total, 0)
        fresh = state.copy()
        first = start[order]
        for i, m in enumerate(active.tolist()):
            by = np.broadcast_to(symbols[first[:m] + i][:, None], (m, n_lang))
            state[:m], miss = self._step(state[:m], fresh[:m], by, rare)
            mark[first[:m] + i] = miss if i else True
        ends = np.empty_like(state)
        ends[order] = state
        # (segment, language) whose parse is to be entered with the state of the one before it
        into = np.flatnonzero(np.concatenate([[False], owner[1:] == owner[:-1]]))
        meets, extra = np.zeros((total, n_lang), np.int64), np.zeros((total, n_lang), np.int64)
        apart = np.zeros((total, n_lang), bool)
        seg, lang = np.repeat(into, n_lang), np.tile(np.arange(n_lang), len(into))
        came = ends[into - 1].ravel()
        while len(seg):
            meets[seg, lang], extra[seg, lang], apart[seg, lang], left = self._enter(symbols, mark, start[seg], long[seg], lang, came, root, rare)
            ends[seg[apart[seg, lang]], lang[apart[seg, lang]]] = left
            # the first segment of a text that was left apart settles what its successor is entered with
            goes_on = apart & np.concatenate([owner[1:] == owner[:-1], [False]])[:, None]
            s, k = np.nonzero(goes_on)
            _, one = np.unique(owner[s] * n_lang + k, return_index=True)
            apart[s[one], k[one]] = False
            seg, lang, came = s[one] + 1, k[one], ends[s[one], k[one]]
        sums = np.zeros((len(mark) + 1, n_lang), np.int32)
        np.cumsum(mark, axis=0, out=sums[1:])
        which = np.arange(n_lang)[None, :]
        mine = sums[start + long] - sums[start[:, None] + meets, which] + extra
        out = np.zeros((len(size), n_lang), np.int64)
        np.add.at(out, owner, mine)
        return out

    def _enter(self, symbols, mark, start, long, lang, state, root, rare):
        """(symbols until the parses meet, phrases begun before that, whether they stayed apart, states of those that did)."""
        meets, extra = long.copy(), np.zeros(len(start), np.int64)
        live, state = np.arange(len(start)), state.copy()
        over = np.zeros(len(start), state.dtype)
        i = 0
        while len(live):
            done = long[live] <= i
            if done.any():
                over[live[done]] = state[done]
                live, state = live[~done], state[~done]
                if not len(live):
                    break
            at = start[live] + i
            state, miss = self._step(state, root[lang[live]], symbols[at], rare)
            met = miss & mark[at, lang[live]]
            extra[live[miss & ~met]] += 1
            if met.any():
                meets[live[met]] = i
                live, state = live[~met], state[~met]
            i += 1
        stayed = meets == long
        return meets, extra, stayed, over[stayed]

    def predict(self, texts: list[str | None]) -> list[tuple[str, float, float, bool]]:
        """(language, score, bits a symbol, whether it is of a known language) of each text.

        The score is 1 less the winner's share of the runner-up's bits.
        """
        code, begin = normalise(texts)
        letters = np.concatenate([[0], np.cumsum(code != 32)])
        has = letters[begin[1:]] > letters[begin[:-1]]
        if not self.languages:
            return [(UNDETERMINED, 0.0, 0.0, bool(h)) for h in has]
        size = np.diff(begin)
        whole = self.phrases(code, begin) * self.bits
        symbols = self.symbol[code]
        for k in range(len(self.languages)):
            lacks = np.concatenate([[0], np.cumsum(self.lacks[symbols, k])])
            whole[:, k] += (lacks[begin[1:]] - lacks[begin[:-1]]) * self.letter_bits
        cost = whole / np.maximum(1, size)[:, None]
        best = np.argmin(cost, 1)
        low = cost[np.arange(len(cost)), best]
        known = whole[np.arange(len(cost)), best] <= UNLIKELY * size * self.letter_bits + MARGIN
        if len(self.languages) > 1:
            second = np.partition(cost, 1, 1)[:, 1]
            score = np.where(second > 0, 1 - low / np.where(second > 0, second, 1), 0.0)
        else:
            score = np.ones(len(cost))
        return [(self.languages[b], float(s), float(x), bool(k)) if h else (UNDETERMINED, 0.0, 0.0, False) for b, s, x, h, k in zip(best, score, low, has, known, strict=True)]


def parser(samples: tuple[tuple[str, str], ...]) -> Parser:
    """One parser a worker."""
    if samples not in _built:
        _built.clear()
        _built[samples] = Parser(dict(samples))
    return _built[samples]


def is_held_out(key: str = "doc_id", folds: int = 5):
    return F.coalesce(crc_mod(key, folds) == 0, F.lit(True))


def learn(documents: DataFrame, chars: int = SAMPLE_CHARS, rows: int = SAMPLE_ROWS, folds: int = 5) -> tuple[tuple[str, str], ...]:
    """A bounded sample of labelled text with letters for each language, in an order that a hash of doc_id gives.

    The first pass counts labels (narrow columns); the second reads the texts of a few times ``rows`` rows.
    """
    known = documents.where(~is_held_out(folds=folds) & F.col("lang").isNotNull()).select(F.col("doc_id"), F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    counts = known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).limit(LANGUAGES + 1).collect()
    if len(counts) > LANGUAGES:
        raise ValueError(f"more than {LANGUAGES} languages are labelled")
    if not counts:
        return ()
    chars = min(chars, TOTAL_CHARS // len(counts))
    whole = 1 << 20
    draw = F.pmod(F.xxhash64(F.col("doc_id").cast("string")), F.lit(whole))
    limit = F.create_map(*[x for r in counts for x in (F.lit(r.lang), F.lit(min(whole, -(-8 * rows * whole // r.n))))])
    some = known.withColumn("draw", draw).where((F.col("draw") < limit[F.col("lang")]) & F.col("text").rlike(r"\p{L}"))
    first = some.withColumn("nth", F.row_number().over(Window.partitionBy("lang").orderBy("draw", "doc_id", F.crc32(F.col("text").cast("binary"))))).where(F.col("nth") <= rows)
    got: dict[str, list[str]] = {}
    for r in first.select("lang", "nth", F.substring("text", 1, chars).alias("text")).orderBy("lang", "nth").toLocalIterator():
        have = got.setdefault(r.lang, [])
        if sum(map(len, have)) < chars:
            have.append(r.text)
    return tuple((k, " ".join(v)[:chars]) for k, v in sorted(got.items()))


def predictor(samples: tuple[tuple[str, str], ...], documents: DataFrame):
    """A function of a list of texts for executors; the samples are broadcast (TOTAL_CHARS at most)."""
    held = documents.sparkSession.sparkContext.broadcast(samples)

    def predict(texts: list[str | None]) -> list[tuple[str, float, float, bool]]:
        p, out, lot, size = parser(held.value), [], [], 0
        for t in texts:
            lot.append(t)
            size += len(t or "")
            if size >= TOGETHER:
                out += p.predict(lot)
                lot, size = [], 0
        return out + (p.predict(lot) if lot else [])

    return predict


def identify(documents: DataFrame, samples: tuple[tuple[str, str], ...] | None = None, folds: int = 5) -> DataFrame:
    """doc_id, held_out, lang_pred, score, bits for every document."""
    predict = predictor(learn(documents, folds=folds) if samples is None else samples, documents)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = predict(b.column(2).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *[pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.string(), pa.float64(), pa.float64()))]], names=["doc_id", "held_out", "lang_pred", "score", "bits"])

    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), is_held_out(folds=folds).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(tidy(run), "doc_id long, held_out boolean, lang_pred string, score double, bits double")


def keep_identified(documents: DataFrame, samples: tuple[tuple[str, str], ...] | None = None) -> DataFrame:
    """The documents of a language that can be told, with all their columns.

    What has no letter goes, and what the best parse needs far more bits for than spelling by letters would, beyond a
    margin that no short text reaches: text of an unlearned script, or strings of random letters. Without labelled
    rows only what has no letter goes.
    """
    predict = predictor(learn(documents) if samples is None else samples, documents)
    at = documents.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield b.filter(pa.array([known for _, _, _, known in predict(b.column(at).to_pylist())], pa.bool_()))

    return documents.mapInArrow(tidy(run), documents.schema)
