"""Language identification by cross-parsing entropy.

For every language a suffix automaton of labelled text recognises exactly the substrings of that
text. A document is cut greedily into longest phrases that the automaton knows; the language that
needs the fewest phrases, each priced at log2 of its reference length, wins. The automata are
flattened into one table of (state, byte class) -> next state in which the restart after a phrase
is folded, so a batch of documents is parsed in lockstep: one gather per byte position moves all
documents through all automata.

Texts are lower-cased, and runs of bytes that belong to no word become one gap. Long texts are parsed
in segments of SEGMENT bytes side by side, each as if a phrase began there; then the phrase that is
open at a segment's end is carried on into the next segment until both parses are in one state, from
where on they agree. So the phrases are those of one parse of the whole text.

The labelled sample: of each language whole texts, first those of at most SHORT bytes, in the order
of a digest of their ids, until REFERENCE_BYTES are reached or REFERENCE_DOCS taken.

Defined cases: null text and text without a letter give `und` with score 0; rows without a
language teach nothing; ties go to the language first in code point order; with one language
learned the score is 1; repeated rows are predicted each; very long texts are parsed whole; other
columns pass through stage() whatever their names, and identify() refuses kept columns that are
called like its new ones; an empty table gives an empty result; without any labelled row every text
is `und`.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from driftlattice.llm.shared import TOKEN_BYTE, row_slices, text_buffer, text_filter, text_map

#: Bounds of the labelled sample that each automaton is built from, in whole texts.
REFERENCE_BYTES = 24_000
REFERENCE_DOCS = 48
SHORT = 4_000
SEGMENT = 512
FOLDS, HELD = 4, 2


def fold(folds: int = FOLDS):
    return F.pmod(F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")), F.lit(folds))


def folded_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """Lower-cased letters with single gaps (byte 32) between words, as buffer and offsets."""
    raw, offsets = text_buffer(pc.utf8_lower(column))
    keep = TOKEN_BYTE[raw] & ~((raw >= 48) & (raw <= 57))
    out = np.where(keep, raw, np.uint8(32))
    gap = ~keep
    again = np.zeros(len(raw), bool)
    again[1:] = gap[1:] & gap[:-1]
    again[offsets[offsets < len(raw)]] = False
    places = np.concatenate([[0], np.cumsum(~again)])
    return out[~again], places[offsets]


def suffix_automaton(text: bytes) -> list[dict[int, int]]:
    """Transitions of the automaton that accepts all substrings of `text`; state 0 is the root."""
    move: list[dict[int, int]] = [{}]
    link, length = [-1], [0]
    last = 0
    for c in text:
        new = len(move)
        move.append({})
        length.append(length[last] + 1)
        link.append(0)
        p = last
        while p >= 0 and c not in move[p]:
            move[p][c] = new
            p = link[p]
        if p >= 0:
            q = move[p][c]
            if length[q] == length[p] + 1:
                link[new] = q
            else:
                twin = len(move)
                move.append(dict(move[q]))
                length.append(length[p] + 1)
                link.append(link[q])
                while p >= 0 and move[p].get(c) == q:
                    move[p][c] = twin
                    p = link[p]
                link[q] = link[new] = twin
        last = new
    return move


def parse_tables(references: dict[str, bytes]) -> dict:
    """All automata as one flat table; entry = next state times the number of classes, negative (~) where a phrase ends."""
    langs = sorted(references)
    used = sorted({b for text in references.values() for b in text})
    classes = np.full(256, len(used), np.int32)  # bytes that no reference has share a class
    classes[used] = np.arange(len(used))
    width = len(used) + 2
    pad = width - 1
    blocks, roots, base = [], [], 0
    for lang in langs:
        moves = suffix_automaton(references[lang])
        n = len(moves)
        table = np.full((n, width), -1, np.int64)
        for s, to in enumerate(moves):
            for c, t in to.items():
                table[s, classes[c]] = t
        root = np.where(table[0] >= 0, table[0], 0)
        nxt = np.where(table >= 0, (table + base) * width, ~((root + base) * width)[None, :])
        nxt[:, pad] = (np.arange(n) + base) * width
        blocks.append(nxt)
        roots.append(base * width)
        base += n
    flat = np.concatenate(blocks).ravel()
    return {
        "langs": langs, "classes": classes, "pad": pad, "roots": np.array(roots, np.int64),
        "table": flat.astype(np.int32) if len(flat) < 2**31 else flat,
        "price": np.log2([max(2, len(references[x])) for x in langs]),
    }


def count_phrases(model: dict, raw: np.ndarray, offsets: np.ndarray, segment: int = SEGMENT) -> np.ndarray:
    """Phrases per text and language."""
    size = np.diff(offsets)
    langs = len(model["langs"])
    parts = -(-size // segment)
    text = np.repeat(np.arange(len(size)), parts)
    if not len(text):
        return np.zeros((len(size), langs), np.int64)
    nth = np.arange(len(text)) - np.repeat(np.cumsum(parts) - parts, parts)
    start = offsets[:-1][text] + nth * segment
    length = np.minimum(segment, offsets[1:][text] - start)
    classes, table = model["classes"][raw].astype(np.int64), model["table"]
    states, ended = np.empty((len(raw), langs), table.dtype), np.empty((len(raw), langs), bool)
    order = np.argsort(-length, kind="stable")  # long lanes first: finished ones fall off the end
    state = np.repeat(model["roots"][None, :], len(text), 0).astype(np.int64)
    live = np.searchsorted(-length[order], -np.arange(1, length.max() + 1), "right")
    lead = start[order]
    for step, n in enumerate(live):
        at = lead[:n] + step
        nxt = table[state[:n] + classes[at][:, None]]
        ended[at] = nxt < 0
        state[:n] = np.where(nxt < 0, ~nxt, nxt)
        states[at] = state[:n]
    ends = np.concatenate([np.zeros((1, langs), np.int64), np.cumsum(ended, 0, dtype=np.int64)])
    stop = start + length
    phrases = ends[stop] - ends[start]
    final = states[stop - 1].astype(np.int64)
    # carry the open phrase over each segment border; a segment's end may change, then its next one is done again
    lane = np.repeat(np.flatnonzero(nth > 0), langs)
    lang = np.tile(np.arange(langs), len(lane) // langs)
    while len(lane):
        place, now, count = start[lane], final[lane - 1, lang], np.zeros(len(lane), np.int64)
        new_final, new_count = np.empty(len(lane), np.int64), np.empty(len(lane), np.int64)
        open_ = np.arange(len(lane))
        while len(open_):
            at, k = place[open_], lang[open_]
            nxt = table[now[open_] + classes[at]]
            count[open_] += nxt < 0
            now[open_] = np.where(nxt < 0, ~nxt, nxt)
            place[open_] += 1
            met = states[at, k] == now[open_]
            over = place[open_] == stop[lane[open_]]
            for which, is_met in ((met, True), (over & ~met, False)):
                row = open_[which]
                new_count[row] = count[row] + (ends[stop[lane[row]], lang[row]] - ends[place[row], lang[row]])
                new_final[row] = states[stop[lane[row]] - 1, lang[row]] if is_met else now[row]
            open_ = open_[~met & ~over]
        phrases[lane, lang] = new_count
        moved = new_final != final[lane, lang]
        final[lane, lang] = new_final
        lane, lang = lane[moved] + 1, lang[moved]
        inside = lane < len(text)
        lane, lang = lane[inside], lang[inside]
        lane, lang = lane[nth[lane] > 0], lang[nth[lane] > 0]
    out = np.zeros((len(size), langs), np.int64)
    np.add.at(out, text, phrases)
    return out + (size > 0)[:, None]  # the phrase still open at the end


def reference_texts(docs: DataFrame, most_docs: int = REFERENCE_DOCS, most_bytes: int = REFERENCE_BYTES, short: int = SHORT) -> dict[str, bytes]:
    """Per language the folded whole texts of a bounded sample of its documents.

    docs: (doc_id, text, lang), learning rows only. Ranks run on narrow rows and keep at most
    `most_docs` a language in every task before anything is shuffled.
    """
    size = F.octet_length(F.col("text").cast("string"))
    order = Window.partitionBy("lang").orderBy(F.col("size") > short, "digest", "doc_id", "size")
    rows = docs.where("lang IS NOT NULL AND text IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", "lang", size.alias("size"), F.md5(F.col("doc_id").cast("string")).alias("digest"))
    ranked = rows.where("size > 0").withColumn("r", F.row_number().over(order)).where(F.col("r") <= most_docs)
    before = F.coalesce(F.sum("size").over(Window.partitionBy("lang").orderBy("r").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ids = [r[0] for r in ranked.withColumn("before", before).where(F.col("before") < most_bytes).select("doc_id").collect()]
    if not ids:
        return {}
    picked = docs.where(F.col("doc_id").isin(ids) & F.col("lang").isNotNull()).select("doc_id", "lang", F.col("text").cast("string").alias("text")).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id", "text").collect()
    each: dict[str, list[bytes]] = {}
    for row in picked:
        raw, _ = folded_bytes(pa.array([row.text], pa.string()))
        each.setdefault(row.lang, []).append(raw.tobytes())
    return {lang: b" ".join(texts) for lang, texts in each.items()}


def predictor(m: dict | None):
    """texts -> their languages and scores."""

    def predict(texts: pa.Array) -> tuple[list[str], list[float]]:
        if m is None:
            return ["und"] * len(texts), [0.0] * len(texts)
        lettered = pc.fill_null(pc.match_substring_regex(texts, r"\p{L}"), False).to_numpy(zero_copy_only=False)
        names, scores = [], []
        for a, b in row_slices(texts):
            bits = count_phrases(m, *folded_bytes(texts.slice(a, b - a))) * m["price"]
            best = np.argmin(bits, 1)
            top = bits[np.arange(b - a), best]
            if bits.shape[1] > 1:
                second = np.partition(bits, 1, 1)[:, 1]
                sure = second / np.maximum(top + second, 1e-9)
            else:
                sure = np.ones(b - a)
            names += [m["langs"][k] if ok else "und" for k, ok in zip(best, lettered[a:b])]
            scores += [float(s) if ok else 0.0 for s, ok in zip(sure, lettered[a:b])]
        return names, scores

    return predict


def shared_model(spark: SparkSession, references: dict[str, bytes]):
    return spark.sparkContext.broadcast(parse_tables(references) if references else None)


def identify(docs: DataFrame, references: dict[str, bytes], keep=("doc_id",)) -> DataFrame:
    """docs(text, *keep) -> (*keep, lang_pred, score); only the text is looked at."""
    model = shared_model(docs.sparkSession, references)

    def run():
        predict = predictor(model.value)

        def columns(texts):
            names, scores = predict(texts)
            return pa.array(names, pa.string()), pa.array(scores, pa.float64())

        return columns

    return text_map(docs, keep, "lang_pred string, score double", run)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    references = reference_texts(docs.where(fold() != HELD).select("doc_id", "text", "lang"))
    return identify(docs.select("doc_id", "text"), references).select("doc_id", (fold() == HELD).alias("held_out"), "lang_pred", "score")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: documents without a recognisable language go; columns stay as they are."""
    model = shared_model(spark, reference_texts(docs.where(fold() != HELD).select("doc_id", "text", "lang")))

    def run():
        predict = predictor(model.value)
        return lambda texts: np.array([name != "und" for name in predict(texts)[0]], bool)

    return text_filter(docs, run)
