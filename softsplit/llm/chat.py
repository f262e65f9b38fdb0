"""Chat formatting: a hidden Markov model over speaker-marker and line features recovers the roles of a
transcript's units by Viterbi, and each unit is rendered as a canonical turn.

A unit is a turn of a conversation table or a line of a raw transcript. Long conversations are cut into
chunks: best scores between every role at a chunk's entry and exit are made for all chunks at once, joined
along each conversation, and then each chunk's own path is traced, so no task holds a whole conversation.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window, functions as F

from ._store import Workspace
from .langid import crc_fold

#: Words before a colon, or in tag brackets, that mark a speaker.
MARKERS = {
    "system": ("system", "instruction", "instructions", "context"),
    "user": ("user", "human", "customer", "client", "question", "q", "me"),
    "assistant": ("assistant", "bot", "ai", "agent", "model", "answer", "a"),
}
_MARK = r"^\s*(?:<\|?|\[|#+\s*|\*\*)?\s*([A-Za-z]+)\s*(?:\|?>|\]|\*\*)?\s*(?::|\n|\|>|>)"
LEVELS = 16
FEATURES = ("marker", "length", "lines", "mark", "first", "list")


def feature_codes(text: Column, first: Column) -> list[Column]:
    """A code below LEVELS for each of FEATURES."""
    text = F.coalesce(text, F.lit(""))
    word = F.lower(F.regexp_extract(text, _MARK, 1))
    marker = F.lit(0)
    for k, names in enumerate(MARKERS.values(), 1):
        marker = F.when(word.isin(*names), F.lit(k)).otherwise(marker)
    clean = F.rtrim(text)
    lines = F.size(F.split(text, "\n"))
    return [
        marker,
        F.least(F.floor(F.log2(F.length(text) + 1)).cast("int"), F.lit(LEVELS - 1)),
        F.least(lines, F.lit(4)),
        F.when(clean.endswith("?"), 1).when(clean.endswith("."), 2).when(clean.endswith(":"), 3).otherwise(0),
        first.cast("int"),
        text.rlike(r"(?m)^\s*(?:[-*]|\d+[.)]|```)").cast("int"),
    ]


def units_of_lines(transcripts: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Units (conv_id, turn, text) of raw transcripts: their lines that are not blank."""
    lines = F.posexplode(F.split(F.coalesce(F.col(text_col), F.lit("")), "\n"))
    return transcripts.select(F.col(id_col).alias("conv_id"), lines.alias("turn", "text")).filter(F.trim("text") != "")


class RoleModel:
    """Log probabilities: start (roles), step (roles x roles), emit (features x LEVELS x roles)."""

    def __init__(self, roles: list[str], start: np.ndarray, step: np.ndarray, emit: np.ndarray):
        self.roles, self.start, self.step, self.emit = roles, start, step, emit

    @staticmethod
    def fit(units: DataFrame, smooth: float = 1.0) -> RoleModel:
        """From units (conv_id, turn, role, code) by counting; neighbours are turns with successive numbers."""
        known = units.filter(F.col("role").isNotNull())
        placed = known.filter(F.col("turn").isNotNull()).groupBy("conv_id", "turn", "role").count()  # repeated turns are not paired row by row
        before = placed.select("conv_id", (F.col("turn") + 1).alias("turn"), F.col("role").alias("was"), F.col("count").alias("times"))
        steps = placed.join(before, ["conv_id", "turn"]).groupBy("was", "role").agg(F.sum(F.col("count") * F.col("times")).alias("count")).collect()
        return RoleModel.of_counts(known, steps, smooth)

    @staticmethod
    def of_counts(known: DataFrame, steps: list, smooth: float) -> RoleModel:
        """From units (role, code), none of null role, and rows (was, role, count) of steps."""
        codes = F.posexplode("code").alias("feature", "level")
        emits = known.select("role", codes).groupBy("role", "feature", "level").count().collect()
        starts = known.filter(F.col("code")[FEATURES.index("first")] == 1).groupBy("role").count().collect()
        roles = sorted({r["role"] for r in emits})
        at = {r: k for k, r in enumerate(roles)}
        n = max(len(roles), 1)
        start, step, emit = np.full(n, smooth), np.full((n, n), smooth), np.full((len(FEATURES), LEVELS, n), smooth)
        for r in starts:
            start[at[r["role"]]] += r["count"]
        for r in steps:
            step[at[r["was"]], at[r["role"]]] += r["count"]
        for r in emits:
            emit[r["feature"], r["level"], at[r["role"]]] += r["count"]
        return RoleModel(roles, np.log(start / start.sum()), np.log(step / step.sum(1, keepdims=True)), np.log(emit / emit.sum(1, keepdims=True)))

    def scores(self, codes: np.ndarray) -> np.ndarray:
        return sum(self.emit[k, codes[:, k]] for k in range(len(FEATURES)))


def _walk(model: RoleModel, scores: np.ndarray, at: np.ndarray, opens: np.ndarray):
    """Best scores (chunk x entry x exit) and back pointers of all chunks, stepping together.

    The entry of a chunk is the role before it; chunks that open a conversation start freely, whatever the entry.
    """
    n = len(model.start)
    sizes = np.diff(at)
    order = np.argsort(-sizes, kind="stable")
    begin, size = at[:-1][order], sizes[order]
    best = np.zeros((len(order), n, n))
    back: list = []
    for t in range(int(size[0]) if len(size) else 0):
        live = int(np.searchsorted(-size, -t, "left"))
        gain = scores[begin[:live] + t][:, None, :]
        if t == 0:
            first = np.where(opens[order][:live, None, None], model.start[None, None, :], model.step[None])
            best[:live] = first + gain
            back.append(None)
            continue
        ways = best[:live, :, :, None] + model.step
        back.append(ways.argmax(2).astype(np.int8))
        best[:live] = ways.max(2) + gain
    return order, begin, size, best, back


def _chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Whole chunks of batches sorted by (conv_id, chunk, turn), some at a time, and their offsets."""
    wait: list[pa.RecordBatch] = []
    for batch in [*batches, None]:
        if batch is not None and not batch.num_rows:
            continue
        if batch is not None:
            wait.append(batch)
            if sum(b.num_rows for b in wait) < 50_000:
                continue
        if not wait:
            return
        table = pa.Table.from_batches(wait).combine_chunks()
        key = table.column("key").to_numpy()
        cuts = np.flatnonzero(key[1:] != key[:-1]) + 1
        if batch is not None:  # the last chunk may go on
            if not len(cuts):
                continue
            wait = table.slice(int(cuts[-1])).to_batches()
            table, cuts = table.slice(0, int(cuts[-1])), cuts[:-1]
        else:
            wait = []
        yield table, np.concatenate([[0], cuts, [table.num_rows]])


def _codes(table: pa.Table) -> np.ndarray:
    return table.column("code").combine_chunks().flatten().to_numpy().reshape(-1, len(FEATURES))


def recover_roles(units: DataFrame, model: RoleModel, ws: Workspace, chunk: int = 4096) -> DataFrame:
    """units (conv_id, turn, code and more) with role_pred, by the best path of each conversation."""
    spark = units.sparkSession
    if not model.roles:
        return units.withColumn("role_pred", F.lit(None).cast("string"))
    shared = spark.sparkContext.broadcast(model)
    n = len(model.roles)
    units = units.withColumn("chunk", F.coalesce(F.floor(F.col("turn") / chunk), F.lit(-1)).cast("long"))
    units = units.withColumn("key", F.xxhash64("conv_id", "chunk"))
    order = ["key", "conv_id", "chunk", "turn", "code"]
    dealt = units.repartition("conv_id", "chunk").sortWithinPartitions(*order)

    def ends(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, at in _chunks(batches):
            heads = table.take(pa.array(at[:-1]))
            # free of where a conversation starts: the first chunk is told apart when chunks are joined
            scores = shared.value.scores(_codes(table))
            for kind in (False, True):
                order, _, _, best, _ = _walk(shared.value, scores, at, np.full(len(at) - 1, kind))
                out = np.empty_like(best)
                out[order] = best
                cols = [heads.column("conv_id").combine_chunks(), heads.column("chunk").combine_chunks(), pa.array([kind] * len(out))]
                cols.append(pa.array(list(out.reshape(len(out), -1)), pa.list_(pa.float64())))
                yield pa.RecordBatch.from_arrays(cols, names=["conv_id", "chunk", "opens", "best"])

    kind = units.schema["conv_id"].dataType.simpleString()
    made = ws.save(dealt.select("conv_id", "chunk", "key", "code").mapInArrow(ends, f"conv_id {kind}, chunk long, opens boolean, best array<double>"), "ends")
    first = Window.partitionBy("conv_id").orderBy("chunk")
    made = made.withColumn("nth", F.dense_rank().over(first)).filter("opens = (nth = 1)")

    def join_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Entry and exit role of each chunk; a conversation's chunks follow each other, the first with opens."""
        rows: list[dict] = []

        def finish() -> pa.RecordBatch:
            into = [np.zeros(n)]
            ways = []
            for k, r in enumerate(rows):
                best = np.array(r["best"]).reshape(n, n)
                paths = into[-1][:, None] + best if k else best
                ways.append(paths.argmax(0))
                into.append(paths.max(0))
            state, out = int(into[-1].argmax()), []
            for k in reversed(range(len(rows))):
                entry = int(ways[k][state])
                out.append((rows[k]["conv_id"], rows[k]["chunk"], entry, state, k == 0))
                state = entry
            kinds = (conv_type, pa.int64(), pa.int32(), pa.int32(), pa.bool_())
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=["conv_id", "chunk", "entry", "leave", "opens"])

        conv_type = None
        for batch in batches:
            conv_type = batch.column("conv_id").type
            for r in batch.to_pylist():
                if r["opens"] and rows:
                    yield finish()
                    rows = []
                rows.append(r)
        if rows:
            yield finish()

    paths = made.repartition("conv_id").sortWithinPartitions("conv_id", "chunk").select("conv_id", "chunk", "opens", "best")
    paths = paths.mapInArrow(join_chunks, f"conv_id {kind}, chunk long, entry int, leave int, opens boolean")
    paths = paths.select(F.col("conv_id").alias("c"), F.col("chunk").alias("k"), "entry", "leave", "opens")
    told = units.join(paths, F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("chunk") == F.col("k"))).drop("c", "k")
    told = told.repartition("conv_id", "chunk").sortWithinPartitions(*order, *[c for c in units.columns if c not in order])
    keep = [c for c in units.columns if c not in ("chunk", "key", "code")]

    def trace(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table, at in _chunks(batches):
            heads = [table.column(c).to_numpy()[at[:-1]] for c in ("entry", "leave", "opens")]
            order, begin, size, _, back = _walk(shared.value, shared.value.scores(_codes(table)), at, heads[2])
            entry, state = heads[0][order], heads[1][order].copy()
            label = np.empty(table.num_rows, np.int64)
            for t in reversed(range(len(back))):
                live = int(np.searchsorted(-size, -t, "left"))
                label[begin[:live] + t] = state[:live]
                if t:
                    state[:live] = back[t][np.arange(live), entry[:live], state[:live]]
            said = pa.array(np.array(shared.value.roles, object)[label], pa.string())
            yield from table.select(keep).append_column("role_pred", said).to_batches(max_chunksize=10_000)

    schema = units.select(*keep).schema.add("role_pred", "string")
    return told.mapInArrow(trace, schema)


def _lines(text: Column) -> Column:
    return F.split(F.coalesce(text, F.lit("")), "\n")


def _line_codes(lines: Column, opens: Column) -> Column:
    """The codes of each line; with `opens` the first line is the first of a conversation."""
    return F.transform(lines, lambda line, i: F.array(*[c.cast("int") for c in feature_codes(line, (i == 0) & opens)]))


#: What a line state adds to its role: the first line of a turn, or a later one.
BEGIN, INSIDE = "|begin", "|inside"


def fit_lines(turns: DataFrame, smooth: float = 1.0) -> RoleModel:
    """A model of transcript lines from turns (conv_id, turn, role, text).

    Each role has two states, for the first line of a turn and for later ones. Blank lines have no state.
    """
    least = turns.groupBy("conv_id").agg(F.min("turn").alias("least")).withColumnRenamed("conv_id", "c")
    rows = turns.filter(F.col("role").isNotNull()).join(least, F.col("conv_id").eqNullSafe(F.col("c")))
    lines = F.filter(_lines(F.col("text")), lambda x: F.trim(x) != "")
    codes = _line_codes(lines, F.coalesce(F.col("turn") == F.col("least"), F.lit(True)))
    state = F.concat("role", F.when(F.col("nth") == 0, F.lit(BEGIN)).otherwise(F.lit(INSIDE)))
    known = rows.select("role", F.posexplode(codes).alias("nth", "code")).select(state.alias("role"), "code")
    sized = rows.select("conv_id", "turn", "role", F.size(lines).alias("n")).filter("n > 0")
    held = sized.groupBy("role").agg(F.count_if(F.col("n") > 1).alias("second"), F.sum(F.greatest(F.col("n") - 2, F.lit(0))).alias("later"))
    steps = []
    for r in held.collect():
        steps.append({"was": r["role"] + BEGIN, "role": r["role"] + INSIDE, "count": r["second"]})
        steps.append({"was": r["role"] + INSIDE, "role": r["role"] + INSIDE, "count": r["later"]})
    last = F.concat("role", F.when(F.col("n") > 1, F.lit(INSIDE)).otherwise(F.lit(BEGIN)))
    ended = sized.filter(F.col("turn").isNotNull()).groupBy("conv_id", (F.col("turn") + 1).alias("turn"), last.alias("was")).agg(F.count(F.lit(1)).alias("times"))
    begun = sized.groupBy("conv_id", "turn", F.concat("role", F.lit(BEGIN)).alias("role")).count()
    across = begun.join(ended, ["conv_id", "turn"]).groupBy("was", "role").agg(F.sum(F.col("count") * F.col("times")).alias("count"))
    steps = [r for r in [*steps, *across.collect()] if r["count"]]  # a state that no line has needs no step
    return RoleModel.of_counts(known, steps, smooth)


def parse_transcripts(transcripts: DataFrame, model: RoleModel, id_col: str = "id", text_col: str = "text") -> DataFrame:
    """(conv_id, turn, role_pred, text, rendered): the turns of raw transcripts, one transcript a row.

    The model is one of fit_lines. A turn begins at each line that the best path calls a first line or gives another
    role, and has the blank lines up to the next one. Turns are numbered from 0. A transcript is read whole by one
    task and rows are never grouped, so null and repeated ids are parsed row by row. A null, empty or blank text
    has no turns; without a learned role a transcript is one turn of role null; other columns are not read.
    """
    shared = transcripts.sparkSession.sparkContext.broadcast(model)
    kind = transcripts.schema[id_col].dataType.simpleString()
    units = F.filter(F.transform(_lines(F.col(text_col)), lambda x, i: F.struct(i.alias("place"), x.alias("line"))), lambda u: F.trim(u["line"]) != "")
    rows = transcripts.select(F.col(id_col).alias("conv_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"), units.alias("units")).filter(F.size("units") > 0)
    rows = rows.select("conv_id", "text", "units.place", F.flatten(_line_codes(F.col("units.line"), F.lit(True))).alias("code"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        names = [x.removesuffix(BEGIN).removesuffix(INSIDE) for x in model.roles]
        opens = np.array([x.endswith(BEGIN) for x in model.roles] or [False])
        role = np.array([names.index(x) for x in names] or [0])
        for batch in batches:
            for r in range(batch.num_rows):
                place = batch.column("place")[r].values.to_numpy(zero_copy_only=False)
                label = np.zeros(len(place), np.int64)
                if model.roles:
                    codes = batch.column("code")[r].values.to_numpy(zero_copy_only=False).reshape(-1, len(FEATURES))
                    _, _, _, best, back = _walk(model, model.scores(codes), np.array([0, len(place)]), np.array([True]))
                    label[-1] = best[0, 0].argmax()
                    for t in range(len(place) - 1, 0, -1):
                        label[t - 1] = back[t][0, 0, label[t]]
                cuts = np.concatenate([[0], np.flatnonzero(opens[label[1:]] | (role[label[1:]] != role[label[:-1]])) + 1])
                lines = batch.column("text")[r].as_py().split("\n")
                ends = [*place[cuts[1:]], len(lines)]
                said = ["\n".join(lines[a:b]) for a, b in zip(place[cuts], ends)]
                roles = [names[k] if names else None for k in label[cuts]]
                ids = pa.array([batch.column("conv_id")[r].as_py()] * len(cuts), batch.column("conv_id").type)
                cols = [ids, pa.array(range(len(cuts)), pa.int64()), pa.array(roles, pa.string()), pa.array(said, pa.string())]
                yield pa.RecordBatch.from_arrays(cols, names=["conv_id", "turn", "role_pred", "text"])

    got = rows.mapInArrow(run, f"conv_id {kind}, turn long, role_pred string, text string")
    return got.withColumn("rendered", rendered(F.col("role_pred"), F.col("text")))


def rendered(role: Column, text: Column) -> Column:
    """The canonical form of a turn: role line, text without a leading marker and outer blanks, end line."""
    marked = F.lower(F.regexp_extract(F.coalesce(text, F.lit("")), _MARK, 1)).isin(*[w for ws in MARKERS.values() for w in ws])
    body = F.when(marked, F.regexp_replace(text, _MARK, "")).otherwise(F.coalesce(text, F.lit("")))
    return F.concat(F.lit("<|"), F.coalesce(role, F.lit("unknown")), F.lit("|>\n"), F.trim(body), F.lit("\n<|end|>\n"))


def format_chats(
    turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", folds: int = 5, chunk: int = 4096
) -> DataFrame:
    """conv_id, turn, held_out, role, role_pred and rendered of each row of `turns`.

    The model counts conversations outside fold 0 of `folds` by crc32(conv_id); true roles are no input of a
    prediction. A turn is first when its number is the smallest of its conversation. Null texts are empty, null roles teach nothing, null
    conversations are one conversation, null turns come first; turns of equal number follow by their feature codes,
    then role and text, so reruns agree; an empty table gives no rows; other columns are not read.
    """
    ws = Workspace(turns.sparkSession, "chat")
    rows = turns.select(
        F.col(conv_col).alias("conv_id"), F.col(turn_col).cast("long").alias("turn"), F.col(role_col).alias("role"), F.col(text_col).alias("text")
    )
    least = rows.groupBy("conv_id").agg(F.min("turn").alias("least")).withColumnRenamed("conv_id", "c")
    first = F.coalesce(F.col("turn") == F.col("least"), F.lit(True))
    units = rows.join(least, F.col("conv_id").eqNullSafe(F.col("c"))).select(
        "conv_id", "turn", "role", "text", F.array(*[c.cast("int") for c in feature_codes(F.col("text"), first)]).alias("code")
    )
    units = ws.save(units, "units")
    fold = crc_fold(F.col("conv_id"), folds) == 0
    model = RoleModel.fit(units.filter(~fold).select("conv_id", "turn", "role", "code"))
    got = recover_roles(units, model, ws, chunk)
    return got.select("conv_id", "turn", fold.alias("held_out"), "role", "role_pred", rendered(F.col("role_pred"), F.col("text")).alias("rendered"))
