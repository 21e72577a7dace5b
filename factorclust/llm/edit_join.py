"""Line dedup by a segment-partition edit join (native: DataFrame functions only).

Lines of at most ``threshold`` edits apart share one of threshold + 1 even segments of the shorter line, at a
place that the lengths and the number of the segment bound. Each distinct line indexes its segments and
probes the substrings that could be segments of lines as long or shorter by up to the threshold. Where very many
lines share a segment, what is left of them is cut into segments again, and so on: the rest of two such lines has
no more edits than the lines, so no pair is lost, and none is made but of lines that share a segment at each level.
Where more than a few lines share one, each is placed against a pivot among them: from where it first differs to where
it is more than the threshold apart, from the front and from the back. A line agrees with the pivot up to where it first
differs, so another one of at most ``threshold`` edits to it is no further from the pivot up to there: of such two, the
places overlap. Only lines whose places do meet, so near copies of one line that differ in other places make no pairs.
Counts of some letters, which an edit changes by two at most, thin out the pairs; a banded bit-parallel automaton
over both lines' characters decides. Lines connected in this way are one class; of all its lines in the corpus only
the first, by doc_id and place, stays.

Lines are compared without the characters of ``blank`` at their ends (spaces, if nothing else is asked for); lines of
such characters alone stay and are no one's copy. Lines shorter than ``least`` characters are copies only if equal.
Rows without doc_id come last. Rows equal in doc_id and text are one document, and both keep the same lines. Null
texts stay null; a text whose lines all go is empty. Tables without rows give no rows; extra columns are kept as they
are, but for columns named as the two counts, which these replace.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from factorclust.llm.shared import components, cut, free_name

THRESHOLD, LEAST = 1, 16
#: Thresholds that grow with the length of the shorter line: (least length, edits).
GROWN = ((16, 1), (64, 2), (128, 3))
Threshold = int | tuple[tuple[int, int], ...]
#: Letters that are counted before a pair is verified; each count is kept modulo 256.
COUNTED = "etaoin"
#: Distinct candidate lines up to which their ids are broadcast to the scan of the texts (8 MB); more are shuffled.
BROADCAST_IDS = 1_000_000
#: Lines that share a segment beyond which they are placed against one of them before they meet.
FEW = 16
#: Lines that share a segment beyond which what is left of them is segmented again, and how often that is done.
CROWD, DEEPEST = 512, 6
#: Characters of a cell of places; halvings of a search for a place (lines of up to 4 million characters are searched to the end).
CELL, HALVINGS = 16, 22
#: Characters at the ends of lines that don't count, if asked for.
WHITE = " \t\r\f\v\u00a0"
#: A class is hot with more than one line in so many.
HOT = 10_000
_LAST = (1 << 63) - 1


def segments(length: Column, parts: int) -> Iterator[tuple[Column, Column]]:
    """(start from 0, length) of the even segments of a line; the later ones take the odd characters."""
    base = F.floor(length / parts).cast("int")
    extra = (length - base * parts).cast("int")
    for i in range(parts):
        long = F.when(extra > parts - 1 - i, 1).otherwise(0)
        yield base * i + F.greatest(F.lit(0), extra - (parts - i)), base + long


def _key(length: Column, i: int, piece: Column) -> Column:
    return F.xxhash64(length, F.lit(i), piece)


def index_keys(line: Column, length: Column, threshold: int) -> list[Column]:
    return [_key(length, i, F.substring(line, at + 1, n)) for i, (at, n) in enumerate(segments(length, threshold + 1))]


def _shifts(threshold: int) -> list[tuple[int, int, int]]:
    """(characters less, segment, shift): where a segment of a line not longer than this one may stand in it."""
    return [(less, i, shift) for less in range(threshold + 1) for i in range(threshold + 1) for shift in range(max(-i, less - threshold + i), min(i, less + threshold - i) + 1)]


def probe_keys(line: Column, length: Column, threshold: int) -> list[Column]:
    """Keys of all substrings that may be such a segment, in the order of _shifts; null outside the line."""
    at = {less: list(segments(length - less, threshold + 1)) for less in range(threshold + 1)}
    out = []
    for less, i, shift in _shifts(threshold):
        start, n = at[less][i]
        begin = start + shift
        out.append(F.when((begin >= 0) & (begin + n <= length), _key((length - less).cast("int"), i, F.substring(line, begin + 1, n))))
    return out


def letter_counts(line: Column) -> Column:
    whole = F.octet_length(line)
    packed = F.lit(0).cast("long")
    for i, c in enumerate(COUNTED):
        n = F.pmod(whole - F.octet_length(F.replace(line, F.lit(c), F.lit(""))), F.lit(256)).cast("long")
        packed = packed.bitwiseOR(F.shiftleft(n, 8 * i))
    return packed


def counts_apart(a: Column, b: Column) -> Column:
    """A lower bound of twice the edit distance."""
    total = F.lit(0).cast("long")
    for i in range(len(COUNTED)):
        x = F.abs(F.shiftrightunsigned(a, 8 * i).bitwiseAND(F.lit(255)) - F.shiftrightunsigned(b, 8 * i).bitwiseAND(F.lit(255)))
        total = total + F.least(x, F.lit(256) - x)
    return total


def edit_distance(pattern: Column, text: Column, threshold: int) -> Column:
    """The edit distance of two strings, or null above the threshold.

    Field e of the state has a bit for each diagonal of the band that e edits reach; a character of the text
    moves all diagonals at once. Both strings are split once, as the variable of a lambda.
    """
    both = F.array(F.struct(F.split(pattern, "").alias("p"), F.split(text, "").alias("t")))
    return F.transform(both, lambda s: _distance(s["p"], s["t"], threshold))[0]


def _distance(pattern: Column, text: Column, threshold: int) -> Column:
    width = 2 * threshold + 1
    full = F.lit((1 << width) - 1).cast("long")
    m, n = F.size(pattern), F.size(text)
    bit = lambda cond, b: F.when(cond, F.lit(1 << b).cast("long")).otherwise(F.lit(0).cast("long"))
    start = F.struct(*[F.lit(sum(1 << (threshold + d) for d in range(e + 1))).cast("long").alias(f"r{e}") for e in range(threshold + 1)])

    def step(state: Column, i: Column) -> Column:
        same = F.lit(0).cast("long")
        for b in range(width):
            same = same.bitwiseOR(bit(F.coalesce(F.get(pattern, i + (b - threshold)) == F.get(text, i), F.lit(False)), b))
        new: list[Column] = []
        for e in range(threshold + 1):
            r = state[f"r{e}"].bitwiseAND(same)
            if e:
                before = state[f"r{e - 1}"]
                r = r.bitwiseOR(before).bitwiseOR(F.shiftright(before, 1)).bitwiseOR(F.shiftleft(new[e - 1], 1)).bitwiseAND(full)
            new.append(r)
        return F.struct(*[x.alias(f"r{e}") for e, x in enumerate(new)])

    last = m - n + threshold  # the diagonal where both strings are used up

    def reached(end: Column) -> Column:
        return F.coalesce(*[F.when(_bit_at(end[f"r{e}"], last, width), F.lit(e)) for e in range(threshold + 1)])

    return F.aggregate(F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>")), start, step, reached)


def _bit_at(value: Column, at: Column, width: int) -> Column:
    """Whether bit ``at`` (a column, 0..width-1) is set."""
    mask = F.lit(0).cast("long")
    for b in range(width):
        mask = F.when(at == b, F.lit(1 << b).cast("long")).otherwise(mask)
    return value.bitwiseAND(mask) != 0


def lines_of(rows: DataFrame, blank: str = " ") -> DataFrame:
    """(row, doc, text) -> row, doc, at, line, id of every line that isn't blank."""
    each = rows.select("row", "doc", F.posexplode(F.split("text", "\n", -1)).alias("at", "raw"))
    line = F.trim("raw")
    other = [c for c in blank if c != " "]
    if other:  # trimming a set of characters is slow, and few lines need it
        line = F.when(reduce(Column.__or__, [line.startswith(c) | line.endswith(c) for c in other]), F.btrim("raw", F.lit(blank))).otherwise(line)
    return each.select("row", "doc", "at", line.alias("line")).where("line <> ''").withColumn("id", F.xxhash64("line"))


def similar(lines: DataFrame, threshold: Threshold = THRESHOLD, least: int = LEAST) -> DataFrame:
    """(a, b): ids of distinct lines at most ``threshold`` edits apart, each pair once.

    Where thresholds are given by length, each class of lengths is joined at its own, with longer lines too.
    """
    if isinstance(threshold, int):
        return _similar(lines, threshold, least, None)
    ends = [at for at, _ in threshold[1:]] + [None]
    found = [_similar(lines, edits, max(least, at), end) for (at, edits), end in zip(threshold, ends, strict=True) if end is None or end > least]
    return reduce(DataFrame.unionByName, found)


def _similar(lines: DataFrame, threshold: int, least: int, end: int | None) -> DataFrame:
    """Pairs whose shorter line has ``least`` characters or more, and less than ``end``.

    The keys are made where the lines are read, so the join moves numbers; texts are read again for the
    lines of crowds, and for those of the pairs that are left to verify.
    """
    parts, probes = threshold + 1, len(_shifts(threshold))
    length = F.char_length("line")
    fits = length >= max(least, threshold + 1)
    long = lines.where(fits if end is None else fits & (length < end + threshold)).select("id", "line", length.alias("n"))
    index_at, probe_at = index_keys(F.col("line"), F.col("n"), threshold), probe_keys(F.col("line"), F.col("n"), threshold)
    keyed = long.select("id", "n", letter_counts(F.col("line")).alias("counts"), *[k.alias(f"k{i}") for i, k in enumerate(index_at)], *[k.alias(f"p{i}") for i, k in enumerate(probe_at)]).distinct()
    keyed = cut(keyed, "line-keys")
    shorter = keyed if end is None else keyed.where(F.col("n") < end)
    index = shorter.select("id", "counts", F.posexplode(F.array(*[f"k{i}" for i in range(parts)])).alias("nth", "key"))
    probe = keyed.select("id", "counts", F.posexplode(F.array(*[f"p{i}" for i in range(probes)])).alias("nth", "key")).where("key is not null")
    found, several = _meet(index, probe, threshold)
    pairs = cut(found, "pairs")
    if several is not None:
        met = cut(index.join(several, "key").select("id", "counts", "nth", "key"), "crowd-index")
        seek = cut(probe.join(several, "key", "left_semi").select("id", "counts", "nth", "key"), "crowd-probe")
        texts = texts_of(long, met.select("id").union(seek.select("id")), "crowded-lines")
        of = F.col("id").alias("of")  # the lines themselves are the rest
        crowds = _within_crowds(met.select("*", of), seek.select("*", of), texts.select(of, F.col("line").alias("rest")), several, threshold)
        pairs = reduce(DataFrame.unionByName, [pairs, *crowds]).distinct()
    texts = texts_of(lines, pairs.select(F.col("a").alias("id")).union(pairs.select("b")), "candidate-lines")
    chars = lambda name, to: texts.select(F.col("id").alias(name), F.col("line").alias(to))
    both = pairs.join(chars("a", "la"), "a").join(chars("b", "lb"), "b")
    # the built-in distance is quick to tell most pairs that are too far apart; the automaton decides on the others
    near = (F.levenshtein("la", "lb", threshold) >= 0) & edit_distance(F.col("la"), F.col("lb"), threshold).isNotNull()
    return both.where(near).select("a", "b")


def texts_of(lines: DataFrame, ids: DataFrame, what: str) -> DataFrame:
    """(id, line) of some lines, each once; ids that are few go to where the texts are read, so no other text is moved."""
    ids = ids.select(F.col("id").alias("want")).distinct()
    some = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    wanted = lines.join(F.broadcast(ids) if some else ids, lines["id"] == ids["want"], "left_semi")
    return cut(wanted.groupBy("id").agg(F.first("line").alias("line")), what)


def _meet(index: DataFrame, probe: DataFrame, threshold: int) -> tuple[DataFrame, DataFrame | None]:
    """((a, b) of lines that share a key, but for keys of more than FEW lines; those keys with their lines' number, or None if there are none)."""
    several = cut(index.groupBy("key").agg(F.count(F.lit(1)).alias("lines")).where(F.col("lines") > min(FEW, CROWD)), "several")
    n = several.limit(BROADCAST_IDS + 1).count()
    some = F.broadcast(several) if n <= BROADCAST_IDS else several
    alone = index if n == 0 else index.join(some, "key", "left_anti")
    return _pairs(alone, probe, threshold), (some if n else None)


def _pairs(index: DataFrame, probe: DataFrame, threshold: int, places: bool = False) -> DataFrame:
    longer = F.element_at(F.array(*[F.lit(less > 0) for less, _, _ in _shifts(threshold)]), F.col("first") + 1)
    more = [(f"a_{c}", f"b_{c}", c) for c in ("front", "reach", "back", "far")] if places else []
    left = index.select(F.col("id").alias("a"), F.col("counts").alias("ca"), "key", *[F.col(c).alias(x) for x, _, c in more])
    first = F.col("first") if "first" in probe.columns else F.col("nth")
    right = probe.select(F.col("id").alias("b"), F.col("counts").alias("cb"), "key", first.alias("first"), *[F.col(c).alias(y) for _, y, c in more])
    near = (longer | (F.col("a") < F.col("b"))) & (counts_apart(F.col("ca"), F.col("cb")) <= 2 * threshold)
    if places:
        for at, to in (("front", "reach"), ("back", "far")):
            near = near & (F.col(f"a_{at}") <= F.col(f"b_{to}")) & (F.col(f"b_{at}") <= F.col(f"a_{to}"))
    return left.join(right, (left["key"] == right["key"]) & near).select("a", "b").distinct()


def _first_difference(line: Column, pivot: Column) -> Column:
    """How many characters the two strings begin with alike."""
    both = F.least(F.char_length(line), F.char_length(pivot))
    alike = lambda at, n: (at + n <= both) & (F.substring(line, at + 1, n) == F.substring(pivot, at + 1, n))
    return F.aggregate(F.array(*[F.lit(1 << b) for b in reversed(range(HALVINGS))]), F.lit(0), lambda at, n: F.when(alike(at, n), at + n).otherwise(at))


def _reach(line: Column, pivot: Column, front: Column, threshold: int) -> Column:
    """A beginning of the pivot, in characters, beyond which none is within ``threshold`` edits of a beginning of the line."""
    shifts = F.array(*[F.lit(s) for s in sorted(range(-threshold, threshold + 1), key=abs)])
    within = lambda n: F.exists(shifts, lambda s: F.levenshtein(F.substring(line, front + 1, n + s), F.substring(pivot, front + 1, n), threshold) >= 0)

    def halve(state: Column, _: Column) -> Column:
        mid = F.floor((state["lo"] + state["hi"]) / 2).cast("int")
        return F.when(state["hi"] - state["lo"] <= 1, state).when(within(mid - front), F.struct(mid.alias("lo"), state["hi"].alias("hi"))).otherwise(F.struct(state["lo"].alias("lo"), mid.alias("hi")))

    start = F.struct(front.alias("lo"), (F.char_length(pivot) + 1).alias("hi"))
    return F.aggregate(F.array(*[F.lit(i) for i in range(HALVINGS)]), start, halve, lambda s: s["hi"] - 1)


def _against_pivots(index: DataFrame, probe: DataFrame, texts: DataFrame, keys: DataFrame, threshold: int) -> DataFrame:
    """Pairs of lines that share one of the keys: those whose places against the key's pivot overlap.

    The pivot is the line that shares its segments with most others, so one with few changes of its own. Rows move as
    numbers; a text moves once for each pivot that it is placed against.
    """
    index = index.join(keys, "key")
    weight = index.groupBy("id").agg(F.sum("lines").alias("weight"))
    chosen = index.join(weight, "id").groupBy("key").agg(F.max_by("of", F.struct("weight", "id")).alias("pivot_of"))
    pivots = cut(chosen, "pivots")
    front, back = F.col("front"), F.col("back")
    line, pivot = F.col("rest"), F.col("pivot")
    index, probe = index.join(pivots, "key"), probe.join(pivots, "key")
    once = index.select("pivot_of", "of").union(probe.select("pivot_of", "of")).distinct()  # most lines meet a pivot by several keys
    once = once.join(texts.select(F.col("of").alias("pivot_of"), F.col("rest").alias("pivot")), "pivot_of").join(texts, "of")
    once = once.withColumn("front", _first_difference(line, pivot)).withColumn("back", _first_difference(F.reverse(line), F.reverse(pivot)))
    once = cut(once.select("pivot_of", "of", "front", "back", _reach(line, pivot, front, threshold).alias("reach"), _reach(F.reverse(line), F.reverse(pivot), back, threshold).alias("far")), "places")

    def placed(rows: DataFrame) -> DataFrame:
        return cut(rows.join(once, ["pivot_of", "of"]).drop("pivot_of", "of"), "placed")

    cell = lambda place: F.floor(place / CELL).cast("int")
    with_cell = lambda rows, c: rows.withColumn("cell", c).withColumn("key", F.xxhash64("key", "cell")).drop("cell")
    whole = lambda rows: with_cell(rows, F.explode(F.sequence(cell(front), cell(F.col("reach")))))
    first = lambda rows: with_cell(rows, cell(front))
    a, b = placed(index), placed(probe)
    return _pairs(whole(a), first(b), threshold, True).unionByName(_pairs(first(a), whole(b), threshold, True)).distinct()


def _without(rest: Column, at: Column, n: Column) -> Column:
    return F.concat(F.substring(rest, F.lit(1), at), F.substring(rest, at + n + 1, F.char_length(rest)))


def _within_crowds(index: DataFrame, probe: DataFrame, texts: DataFrame, several: DataFrame, threshold: int) -> Iterator[DataFrame]:
    """Pairs of lines that share keys of several lines: rows are (id, counts, nth, key, of), with nth the segment or shift of the key in
    what rests of the line; texts are (of, rest), ``of`` the rest's hash."""
    shifts = _shifts(threshold)
    probe = probe.withColumn("first", F.col("nth"))  # tells whose lines are longer, whatever is cut off later
    for level in range(DEEPEST + 1):
        some = several if level == DEEPEST else several.where(F.col("lines") <= CROWD)
        if not some.isEmpty():
            yield cut(_against_pivots(index, probe.join(some, "key", "left_semi"), texts, some, threshold), "pairs")
        crowded = several.where(F.col("lines") > CROWD).select("key")
        if level == DEEPEST or crowded.isEmpty():
            return
        length = F.char_length("rest")
        pick = lambda options: F.element_at(F.array(*options), F.col("nth") + 1)
        own = list(segments(length, threshold + 1))
        of_shorter = {less: list(segments(length - less, threshold + 1)) for less in range(threshold + 1)}
        index = index.join(crowded, "key", "left_semi").join(texts, "of").withColumn("rest", _without(F.col("rest"), pick([at for at, _ in own]), pick([n for _, n in own])))
        begin, size = pick([of_shorter[less][i][0] + shift for less, i, shift in shifts]), pick([of_shorter[less][i][1] for less, i, shift in shifts])
        probe = probe.join(crowded, "key", "left_semi").join(texts, "of").withColumn("rest", _without(F.col("rest"), begin, size))
        below = lambda keys: F.transform(F.array(*keys), lambda k: F.when(k.isNotNull(), F.xxhash64(F.col("key"), k)))
        of = F.xxhash64("rest").alias("of")
        rests = index.select(of, "rest").union(probe.select(of, "rest"))
        index = cut(index.select("id", "counts", of, F.posexplode(below(index_keys(F.col("rest"), length, threshold))).alias("nth", "key")), "crowd-index")
        deeper = probe_keys(F.col("rest"), length, threshold)
        probe = cut(probe.select("id", "counts", of, "first", F.posexplode(below(deeper)).alias("nth", "key")).where("key is not null"), "crowd-probe")
        texts = cut(rests.groupBy("of").agg(F.first("rest").alias("rest")), "crowded-lines")
        found, several = _meet(index, probe, threshold)
        yield cut(found, "pairs")
        if several is None:
            return


def removed(rows: DataFrame, threshold: Threshold = THRESHOLD, least: int = LEAST, blank: str = " ") -> DataFrame:
    """(row, gone): the places of the lines that go from each document, where there are any."""
    lines = lines_of(rows, blank)
    labels = components(similar(lines, threshold, least))
    places = lines.select("row", "doc", "at", "id")
    classed = cut(places.join(labels, places["id"] == labels["node"], "left").select("row", "doc", "at", F.coalesce("comp", "id").alias("class")), "places")
    owners = cut(classed.groupBy("class").agg(F.min("doc").alias("owner"), F.count(F.lit(1)).alias("n")).where("n > 1"), "owners")
    # classes with more than one in HOT lines: fewer than HOT, so their rows need no shuffle; the others are small
    total = classed.count()
    hot = owners.where(F.col("n") * HOT > total).select("class", "owner")
    cold = owners.where(F.col("n") * HOT <= total).select("class", "owner")
    hot_copies = classed.join(F.broadcast(hot), "class")
    hot_first = hot_copies.where("doc = owner").groupBy("class").agg(F.min("at").alias("first"))
    cold_copies = classed.join(F.broadcast(hot.select("class")), "class", "left_anti").join(cold, "class")
    cold_first = cold_copies.where("doc = owner").groupBy("class").agg(F.min("at").alias("first"))
    copies = hot_copies.join(F.broadcast(hot_first), "class").unionByName(cold_copies.join(cold_first, "class"))
    goes = copies.where((F.col("doc") != F.col("owner")) | (F.col("at") != F.col("first")))
    return goes.groupBy("row").agg(F.collect_set("at").alias("gone"))  # no more than a document's own lines


def dedup(documents: DataFrame, threshold: Threshold = THRESHOLD, least: int = LEAST, blank: str = " ", counts: tuple[str, str] = ("n_lines", "n_removed")) -> DataFrame:
    """The documents with the text their first lines leave, and the two counts."""
    text = F.col("text").cast("string")
    key = F.xxhash64(F.col("doc_id").cast("long"), text)
    rows = documents.select(key.alias("row"), F.coalesce(F.col("doc_id").cast("long"), F.lit(_LAST)).alias("doc"), text.alias("text"))
    row, places = free_name(documents.columns, "row"), free_name(documents.columns, "gone")
    gone = removed(rows, threshold, least, blank).select(F.col("row").alias(row), F.col("gone").alias(places))
    lines = F.split(text, "\n", -1)
    stay = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col(places))
    left = F.when(F.col(places).isNull(), text).otherwise(F.array_join(F.transform(stay, lambda i: F.get(lines, i)), "\n"))
    found = documents.withColumn(row, key).hint("merge").join(gone, row, "left")
    return found.select(
        *[left.alias("text") if c == "text" else F.col(f"`{c}`") for c in documents.columns if c not in counts],
        F.when(text.isNull(), 0).otherwise(F.size(lines)).cast("long").alias(counts[0]), F.coalesce(F.size(places), F.lit(0)).cast("long").alias(counts[1]),
    )
