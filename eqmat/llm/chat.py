"""Chat formatting: a hidden Markov model over the lines of a transcript recovers who speaks, then turns are rendered.

A line is in one of six states: it begins or continues a turn of the system, the user or the assistant. What is seen of
it is its speaker marker, whether a blank line stands before it and its length. The most likely states are found by
Viterbi in chunks: each chunk of a conversation first gives the best score from every entry state to every exit state,
these small tables are combined along the conversation, and with the states at its ends fixed each chunk is decoded by
itself. So the result is the exact best path and no conversation is gathered in one place.

All rates are counted on conversations with known roles, and no conversation is parsed by a model that has seen its
roles: two models are fitted, each on the conversations of one fold, and each parses the other fold.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqmat.storage import saved

ROLES = ("system", "user", "assistant")
STATES = 6  # 2 * role + (0: begins, 1: continues)
CHUNK = 256  # turns
CHUNK_BYTES = 8 << 20
OUT_ROWS = 4096
#: Names that markers use for each role, and the marker forms.
NAMES = {"system": ("System", "Context", "Instructions"), "user": ("User", "Human", "Customer", "Q", "You"), "assistant": ("Assistant", "AI", "Bot", "Agent", "A")}
FORMS = ("{}: ", "[{}] ", "### {}:\n", "**{}:** ", "<|{}|>\n", "{}> ")
#: What is assumed before anything is counted, as one turn or line of each kind: how roles follow each other and begin a
#: conversation, and that a line goes on with its turn.
FOLLOWS = np.array([[0.01, 0.94, 0.05], [0.01, 0.09, 0.90], [0.01, 0.90, 0.09]])
FIRST = np.array([0.25, 0.65, 0.10])
GOES_ON = 0.7
DOUBT = 0.1  # part of what is assumed in the counted rates of turns: other transcripts may run otherwise
SYMBOLS = 24  # marker (4) x blank before (2) x length (3)
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"


def _marker_pattern(role: str) -> str:
    names = "|".join(NAMES[role])
    return rf"(?i)^\s*(?:(?:#{{1,4}}\s*|\*\*|\[|<\|)(?:{names})(?::\*\*|\*\*:?|\]:?|\|>|:|\s*$)|(?:{names})\s*[:>])\s*"


def _first_marker(role: str) -> str:
    """The marker at the start of a text of several lines, with blank lines before it and the space or line end after."""
    names = "|".join(NAMES[role])
    return rf"(?i)\A\s*(?:(?:#{{1,4}}\s*|\*\*|\[|<\|)(?:{names})(?::\*\*|\*\*:?|\]:?|\|>|:|(?=[^\S\n]*(?:\n|\z)))|(?:{names})[^\S\n]*[:>])[ \n]?"


def symbols(raw: Column) -> Column:
    """What is seen of each line of a text that follows an empty line: an array of numbers below SYMBOLS. A line has a
    blank line before it if the line that precedes it is blank; blank lines themselves count as having none, for they
    begin no turn, but for the first line of a text that is blank altogether."""
    lines = F.split(raw, "\n", -1)
    blank = lambda c: F.regexp_like(c, F.lit(r"^\s*$"))

    def one(line: Column, before: Column) -> Column:
        marker = F.lit(0)
        for k, role in enumerate(ROLES):
            marker = F.when(F.regexp_like(line, F.lit(_marker_pattern(role))), F.lit(k + 1)).otherwise(marker)
        n = F.length(line)
        size = F.when(n < 40, 0).when(n < 200, 1).otherwise(2)
        return (marker * 6 + F.when(blank(before) & ~blank(line), 3).otherwise(0) + size).cast("int")

    seen = F.slice(F.zip_with(lines, F.concat(F.array(F.lit("")), lines), one), 1, F.size(lines))
    return F.when(blank(raw), F.transform(lines, lambda _, i: F.when(i == 0, 3).otherwise(0).cast("int"))).otherwise(seen)


def stripped(raw: Column, role: Column, begins: Column) -> Column:
    """The text of a part without the one marker that stands at its start, if that is a marker of the role that was
    recovered; a part that goes on with a turn has none."""
    out = raw
    for name in ROLES:
        out = F.when(begins & (role == name), F.regexp_replace(raw, F.lit(_first_marker(name)), F.lit(""))).otherwise(out)
    return out


def escaped(text: Column) -> Column:
    """A frame token inside a text gets a backslash (one more where it has some), so that it frames nothing."""
    return F.regexp_replace(text, r"<(\\*)\|(im_start|im_end)\|>", r"<$1\\|$2|>")


def unescaped(text: Column) -> Column:
    """The text that was escaped."""
    return F.regexp_replace(text, r"<(\\*)\\\|(im_start|im_end)\|>", r"<$1|$2|>")


def as_transcript(conversations: DataFrame) -> DataFrame:
    """conversations(conv_id, turn, role, text) as people paste them: conv_id, turn, role, raw. Each conversation has a
    marker form and names of its own, and one turn in eight has no marker. A null role has none, a null text is empty."""
    h = F.xxhash64(F.col("conv_id"))
    form, out = F.pmod(h, F.lit(len(FORMS))), None
    for k, shape in enumerate(FORMS):
        name = F.lit("")
        for role, names in NAMES.items():
            name = F.when(F.col("role") == role, F.element_at(F.array(*map(F.lit, names)), (F.pmod(F.shiftright(h, 8), F.lit(len(names))) + 1).cast("int"))).otherwise(name)
        head, tail = shape.split("{}")
        marked = F.concat(F.lit(head), name, F.lit(tail))
        out = marked if out is None else F.when(form == k, marked).otherwise(out)
    bare = (F.pmod(F.xxhash64("conv_id", "turn"), F.lit(8)) == 0) | F.coalesce(~F.col("role").isin(*ROLES), F.lit(True))
    return conversations.select("conv_id", "turn", "role", F.concat(F.when(bare, F.lit("")).otherwise(out), F.coalesce("text", F.lit(""))).alias("raw"))


class SpeakerModel:
    """Log probabilities of states at the start, of transitions and of symbols."""

    def __init__(self, emissions: np.ndarray | None = None, moves: np.ndarray | None = None, starts: np.ndarray | None = None):
        """Counts of symbols by state, of transitions between states and of first states; what is left out is assumed: a
        marker nearly decides, and turns begin after blank lines."""
        if emissions is None:
            emissions = np.ones((STATES, SYMBOLS))
            for s in range(STATES):
                for o in range(SYMBOLS):
                    marker, blank = o // 6, o // 3 % 2
                    emissions[s, o] = (30 if marker == s // 2 + 1 and s % 2 == 0 else 5 if marker == 0 else 0.1) * (5 if blank == (s % 2 == 0) else 0.2)
        if moves is None:
            moves = np.zeros((STATES, STATES))
            for a in range(STATES):
                moves[a, a // 2 * 2 + 1] = GOES_ON
                moves[a, ::2] = (1 - GOES_ON) * FOLLOWS[a // 2]
        if starts is None:
            starts = np.zeros(STATES)
            starts[::2] = FIRST
        with np.errstate(divide="ignore"):
            self.emit = np.log(emissions / emissions.sum(axis=1, keepdims=True))
            self.move, self.start = np.log(moves / moves.sum(axis=1, keepdims=True)), np.log(starts / starts.sum())

    def chunk_scores(self, seen: list[int], first: bool) -> tuple[np.ndarray, np.ndarray]:
        """(6, 6) best score of a path through the chunk from the state before it to its last state, and the first state
        of that path. A first chunk starts from the initial states, whatever its entry state. Ties go to the lower."""
        score = np.broadcast_to(self.start + self.emit[:, seen[0]], (STATES, STATES)).copy() if first else self.move + self.emit[:, seen[0]]
        begun = np.broadcast_to(np.arange(STATES), (STATES, STATES))
        for o in seen[1:]:
            both = score[:, :, None] + self.move[None]
            best = both.argmax(axis=1)
            score = np.take_along_axis(both, best[:, None, :], 1)[:, 0, :] + self.emit[:, o]
            begun = np.take_along_axis(begun, best, 1)
        return score, begun

    def path(self, seen: list[int], entry: int, exit_: int) -> list[int]:
        """Best states of a chunk between fixed ends; entry -1: the conversation begins here; ties go to the lower."""
        score = (self.start if entry < 0 else self.move[entry]) + self.emit[:, seen[0]]
        back = []
        for o in seen[1:]:
            both = score[:, None] + self.move
            back.append(both.argmax(axis=0))
            score = both.max(axis=0) + self.emit[:, o]
        states = [exit_]
        for b in reversed(back):
            states.append(int(b[states[-1]]))
        return states[::-1]


Models = tuple[SpeakerModel, SpeakerModel]


def fold(conv: Column) -> Column:
    """0 or 1 by the conversation's id; a null id is 0."""
    return F.coalesce(F.pmod(F.crc32(conv.cast("string").cast("binary")), F.lit(2)), F.lit(0)).cast("int")


def train(transcript: DataFrame) -> Models:
    """Models for the conversations of fold 0 and 1 of transcript(conv_id, turn, role, raw), each counted on the other
    fold only: symbols of lines in each state, how lines go on, which role follows which and comes first. A few hundred
    numbers come to the driver. Each state has half a line a symbol and one turn beforehand, spread as assumed, so that a
    few lines do not blur the markers; rates of turns keep DOUBT of what is assumed. Rows without one of ROLES teach nothing, those without conv_id or turn no order."""
    rows = transcript.where(F.col("role").isin(*ROLES)).select("conv_id", "turn", "role", fold(F.col("conv_id")).alias("fold"), symbols(F.col("raw")).alias("seen"))
    rows = saved(rows, "seen")
    blank = SpeakerModel()
    emit = [0.5 * SYMBOLS * np.exp(blank.emit) for _ in range(2)]
    move, start = [np.exp(blank.move) for _ in range(2)], [np.exp(blank.start) for _ in range(2)]
    lines = rows.select("fold", "role", F.posexplode("seen").alias("i", "o")).groupBy("fold", "role", (F.col("i") > 0).alias("later"), "o").agg(F.count("*").alias("n"))
    for r in lines.collect():
        role, of = ROLES.index(r["role"]), emit[1 - r["fold"]]
        of[2 * role + int(r["later"]), r["o"]] += r["n"]
        if not r["later"] and r["o"] >= 6 and r["o"] // 3 % 2:  # people also paste a marked turn right after the line before
            of[2 * role, r["o"] - 3] += r["n"]
    # A turn of n lines goes on once from its beginning, n - 2 times after that, and then another turn begins.
    n = F.size("seen")
    turns = rows.where("conv_id is not null and turn is not null").groupBy("conv_id", "turn", "fold").agg(F.min(F.struct("role", n.alias("n"))).alias("t")).select("conv_id", "turn", "fold", "t.*")
    after = turns.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("role").alias("next"))
    before = turns.select("conv_id", (F.col("turn") + 1).alias("turn"), F.lit(True).alias("later"))
    seen = turns.join(after, ["conv_id", "turn"], "left").join(before, ["conv_id", "turn"], "left")
    counts = seen.groupBy("fold", "role", "next", F.coalesce("later", F.lit(False)).alias("later"), (F.col("n") > 1).alias("long")).agg(F.count("*").alias("k"), F.sum("n").alias("lines"))
    for r in counts.collect():
        role, k = ROLES.index(r["role"]), r["k"]
        moves, last = move[1 - r["fold"]], 2 * role + int(r["long"])
        if r["long"]:
            moves[2 * role, 2 * role + 1] += k
            moves[2 * role + 1, 2 * role + 1] += r["lines"] - 2 * k
        if r["next"]:
            moves[last, 2 * ROLES.index(r["next"])] += k
        if not r["later"]:
            start[1 - r["fold"]][2 * role] += k

    def mixed(counts: np.ndarray, assumed: np.ndarray) -> np.ndarray:
        return (1 - DOUBT) * counts / counts.sum(axis=-1, keepdims=True) + DOUBT * np.exp(assumed)

    return tuple(SpeakerModel(e, mixed(m, blank.move), mixed(s, blank.start)) for e, m, s in zip(emit, move, start, strict=True))


def _model_of(model: SpeakerModel | Models, conv: str) -> SpeakerModel:
    if isinstance(model, SpeakerModel):
        return model
    return model[0 if conv.startswith("\x00") else zlib.crc32(conv.encode()) % 2]


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[tuple[tuple, list[tuple]]]:
    """Rows that share their first columns, which stand together."""
    rows = (row for b in batches for row in zip(*[c.to_pylist() for c in b.columns], strict=True))
    for key, group in groupby(rows, key=lambda row: row[:keys]):
        yield key, list(group)


def _batches(rows: Iterator[tuple], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Rows in batches of about OUT_ROWS rows or CHUNK_BYTES of text."""
    out, held = [], 0
    for row in rows:
        out.append(row)
        held += sum(len(x) for x in row if isinstance(x, str))
        if len(out) >= OUT_ROWS or held >= CHUNK_BYTES:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)
            out, held = [], 0
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out, strict=True), schema, strict=True)], schema=schema)


_KEY = [("conv", pa.string()), ("chunk", pa.int64()), ("cut", pa.int64()), ("slot", pa.int64())]
_TABLES = pa.schema([*_KEY, ("score", pa.list_(pa.float64())), ("begun", pa.list_(pa.int8()))])
_ENDS = pa.schema([*_KEY, ("entry", pa.int32()), ("exit", pa.int32()), ("next", pa.int32())])
_PARTS = pa.schema([("conv", pa.string()), ("turn_no", pa.int64()), ("part", pa.int32()), ("raw", pa.string()), ("role", pa.string()), ("begins", pa.bool_()), ("ends", pa.bool_()), ("copies", pa.int64())])


def _tables(model: SpeakerModel | Models):
    def rows(batches):
        for key, group in _groups(batches, 5):
            score, begun = _model_of(model, key[0]).chunk_scores([o for r in group for o in r[-1]], key[4])
            yield *key[:4], score.ravel().tolist(), begun.ravel().tolist()

    return lambda batches: _batches(rows(batches), _TABLES)


def _ends(batches):
    def rows():
        for _, group in _groups(batches, 1):
            best, back = np.zeros(STATES), []
            for r in group:
                both = best[:, None] + np.array(r[4]).reshape(STATES, STATES)
                back.append(both.argmax(axis=0).astype(np.int8))
                best = both.max(axis=0)
            exits, state = [], int(best.argmax())
            for b in reversed(back):
                exits.append(state)
                state = int(b[state])
            exits = exits[::-1]
            entries = [-1, *exits[:-1]]
            firsts = [r[5][max(entry, 0) * STATES + exit_] for r, entry, exit_ in zip(group, entries, exits, strict=True)]
            for r, entry, exit_, next_ in zip(group, entries, exits, [*firsts[1:], 0], strict=True):
                yield *r[:4], entry, exit_, next_

    return _batches(rows(), _ENDS)


def _turns(raw: str, states: list[int]) -> list[tuple[str, int]]:
    """The lines of raw cut where a state begins a turn: text and first state of each part. Blank lines that stand
    before the first other line of a part are no part of their own. The texts joined by line ends give raw."""
    parts: list[tuple[list[str], int]] = []
    for line, state in zip(raw.split("\n"), states, strict=True):
        if parts and state % 2:
            parts[-1][0].append(line)
        elif parts and not "".join(parts[-1][0]).strip(" \t\n\x0b\f\r"):
            own = parts[-1][0]
            own.append(line)
            parts[-1] = (own, state)
        else:
            parts.append(([line], state))
    return [("\n".join(lines), state) for lines, state in parts]


def _decode(model: SpeakerModel | Models):
    def rows(batches):
        for key, group in _groups(batches, 7):
            states = iter(_model_of(model, key[0]).path([o for r in group for o in r[-1]], key[4], key[5]))
            parts = [(r, k, text, s) for r in group for k, (text, s) in enumerate(_turns(r[9], [next(states) for _ in r[-1]]))]
            follow = [p[3] % 2 == 0 for p in parts[1:]] + [key[6] % 2 == 0]
            for (r, k, text, s), ends in zip(parts, follow, strict=True):
                yield key[0], r[7], k, text, ROLES[s // 2], s % 2 == 0, ends, r[10]

    return lambda batches: _batches(rows(batches), _PARTS)


NO_TURN = -(1 << 62)


def _chunks(blocks: DataFrame, chunk: int, chunk_bytes: int) -> DataFrame:
    """Add chunk, cut, slot, which are in order of the blocks (turn_no, place): ``chunk`` turns that stand together, or,
    where those have very many rows or bytes, one turn and, of that, a range of places."""
    blocks = blocks.withColumn("chunk", F.floor(F.col("turn_no") / chunk))
    by_turn = saved(blocks.groupBy("conv", "chunk", "turn_no").agg(F.count("*").alias("n"), F.sum(F.octet_length("raw").cast("long")).alias("b")), "turns")
    wide = by_turn.groupBy("conv", "chunk").agg(F.sum("n").alias("cn"), F.sum("b").alias("cb")).where((F.col("cn") > 4 * chunk) | (F.col("cb") > chunk_bytes))
    slots = F.greatest(F.lit(1), F.ceil(F.col("n") / chunk), F.least(F.col("n"), F.ceil(F.col("b") / chunk_bytes)))
    wide = saved(by_turn.join(wide, ["conv", "chunk"]).select("conv", "turn_no", slots.alias("slots")), "wide")
    whole = F.lit(0).cast("long")
    if wide.isEmpty():
        return blocks.withColumns({"cut": F.lit(NO_TURN), "slot": whole})
    share = (F.shiftrightunsigned("place", 32).cast("double") + 0.5) / (1 << 32)
    cut = blocks.join(wide, ["conv", "turn_no"], "left")
    own = F.col("slots").isNotNull()
    return cut.withColumns({"cut": F.when(own, F.col("turn_no")).otherwise(NO_TURN), "slot": F.when(own, F.floor(share * F.col("slots"))).otherwise(whole)}).drop("slots")


def parse(transcript: DataFrame, model: SpeakerModel | Models, chunk: int = CHUNK, chunk_bytes: int = CHUNK_BYTES) -> DataFrame:
    """transcript(conv_id, turn, raw) -> conv_id, turn, part, raw, role, begins, ends (whether the part opens and closes
    a turn), copy.

    The text of a conversation is its blocks with an empty line between them. It is read line by line, and a turn is cut
    where the decoded state begins one, wherever in a block that is: a block comes out as one row for each turn in it,
    numbered by part from 0; its first part goes on with the turn before if begins is false. Blocks stand in order of
    turn (null first), then of a hash of their text. Equal rows are read as one block, whose rows come out for each of
    them: copy 1 stands in the conversation, the others are turns by themselves (their ends begin and end). Each row
    without a conv_id is a conversation of its own. A null raw is empty. An empty table gives no rows. Chunks are bounded
    by ``chunk`` turns and, but for single longer texts, ``chunk_bytes``, also where one conversation or one turn holds
    most rows.
    """
    kinds = {f.name: f.dataType for f in transcript.schema}
    turn = F.coalesce(F.col("turn").cast("long"), F.lit(NO_TURN))
    text = F.coalesce("raw", F.lit(""))
    lone = F.concat(F.lit("\x00"), F.lower(F.hex(F.xxhash64(turn, text))), F.sha2(text, 224))
    blocks = transcript.select(F.coalesce(F.col("conv_id").cast("string"), lone).alias("conv"), turn.alias("turn_no"), text.alias("raw")).groupBy("conv", "turn_no", "raw").agg(F.count("*").alias("copies"))
    # Places are in the order of unsigned numbers.
    blocks = saved(blocks.withColumn("place", F.xxhash64("raw")).withColumn("seen", symbols(F.col("raw"))), "blocks")
    key = ["conv", "chunk", "cut", "slot"]
    blocks = _chunks(blocks, chunk, chunk_bytes)
    firsts = blocks.groupBy("conv").agg(F.min(F.struct(*key[1:])).alias("lowest")).select("conv", "lowest.*", F.lit(True).alias("lowest"))
    parts = int(transcript.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = [*key, "turn_no", F.shiftrightunsigned("place", 32), "place", "raw"]
    marked = blocks.join(firsts, key, "left").withColumn("first", F.col("lowest").isNotNull())
    tables = marked.repartition(parts, *key).sortWithinPartitions(*order).select(*key, "first", "seen")
    tables = tables.mapInArrow(_tables(model), "conv string, chunk long, cut long, slot long, score array<double>, begun array<tinyint>")
    # One small row for each chunk of a conversation meets here.
    ends = saved(tables.repartition(parts, "conv").sortWithinPartitions(*key).mapInArrow(_ends, "conv string, chunk long, cut long, slot long, entry int, exit int, next int"), "ends")
    ready = blocks.join(ends, key).repartition(parts, *key).sortWithinPartitions(*order)
    out = ready.select(*key, "entry", "exit", "next", "turn_no", "place", "raw", "copies", "seen").mapInArrow(_decode(model), "conv string, turn_no long, part int, raw string, role string, begins boolean, ends boolean, copies long")
    out = out.withColumn("copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))))
    return out.select(
        F.when(~F.col("conv").startswith("\x00"), F.col("conv")).cast(kinds["conv_id"]).alias("conv_id"), F.when(F.col("turn_no") != NO_TURN, F.col("turn_no")).cast(kinds["turn"]).alias("turn"),
        "part", "raw", "role", (F.col("begins") | (F.col("copy") > 1)).alias("begins"), (F.col("ends") | (F.col("copy") > 1)).alias("ends"), "copy",
    )


def rendered(role: Column, raw: Column, begins: Column, ends: Column) -> Column:
    """The canonical form of a part: its role in a fixed frame, its text without the marker and with frame tokens
    escaped. A part that goes on with a turn has no opening but the empty line before it, one whose turn goes on has no
    closing; so the parts of a conversation in order are whole frames, one for each turn."""
    head = F.when(begins, F.concat(F.lit(OPEN), role, F.lit("\n"))).otherwise(F.lit("\n\n"))
    return F.concat(head, escaped(stripped(raw, role, begins)), F.when(ends, F.lit(CLOSE + "\n")).otherwise(F.lit("")))


def format_conversations(conversations: DataFrame) -> DataFrame:
    """conversations(conv_id, turn, role, text) -> conv_id, turn, part, copy, role (recovered), rendered: written as
    transcripts, parsed by models that have not seen their roles, and rendered, one row for each turn that is found.
    Turns found in one text have the turn of its row and are numbered by part; see parse() for order, equal rows, nulls
    and empty tables. Other columns are not looked at."""
    transcript = saved(as_transcript(conversations), "transcript")
    parsed = parse(transcript.select("conv_id", "turn", "raw"), train(transcript))
    return parsed.select("conv_id", "turn", "part", "copy", "role", rendered(F.col("role"), F.col("raw"), F.col("begins"), F.col("ends")).alias("rendered"))
