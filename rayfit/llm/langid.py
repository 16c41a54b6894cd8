"""Language identification of mixed-language text.

Training counts byte trigrams of lower-cased words by language (and letters by script); a word's score in a language is
the sum of its trigrams' smoothed log probabilities. Of a text, the scripts of its letters narrow the candidates: a
language stays if training saw a fair share of its letters in a script that the text uses. Viterbi over the words
with a penalty for each switch then labels spans. The text's language is the one with most letters in its spans.

A path that never switches is best if no run of words can win more than its two switches (one at either end of the text)
cost; that is tested at once for all words, and only the other texts, the mixed ones, go through the recursion."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, slices
from .textkit import Words

BUCKETS = 1 << 17
#: Training reads at most about so many rows, chosen by a hash of their text.
TRAIN_ROWS = 20_000
PENALTY = 12.0
#: First code points of ranges, and the script of each.
SCRIPTS = [(0x41, "latin"), (0x250, "other"), (0x370, "greek"), (0x400, "cyrillic"), (0x530, "other"), (0x590, "hebrew"), (0x600, "arabic"), (0x780, "other"), (0x900, "devanagari"), (0x980, "other"), (0xE00, "thai"), (0xE80, "other"), (0x1100, "hangul"), (0x1200, "other"), (0x1E00, "latin"), (0x1F00, "greek"), (0x2000, "other"), (0x3040, "kana"), (0x3100, "other"), (0x3400, "han"), (0xA000, "other"), (0xAC00, "hangul"), (0xD7B0, "other")]
NAMES = sorted({s for _, s in SCRIPTS})
UNDETERMINED = "und"
#: A script counts for a language or a text from this share of letters.
SHARE = 0.02


def _script_of_bytes(words: Words) -> np.ndarray:
    """Letters by script of each row: rows x len(NAMES). A letter is an ASCII one or any character from U+00C0 on."""
    raw = words.raw
    lead = raw >= 0xC3
    code = np.zeros(len(raw), np.int32)
    ascii_letter = ((raw | 0x20) >= 97) & ((raw | 0x20) <= 122) & (raw < 128)
    code[ascii_letter] = 0x41
    at = np.flatnonzero(lead)
    if len(at):
        last = len(raw) - 1
        c = [raw[np.minimum(at + k, last)].astype(np.int32) for k in range(4)]
        two = ((c[0] & 0x1F) << 6) | (c[1] & 0x3F)
        three = ((c[0] & 0x0F) << 12) | ((c[1] & 0x3F) << 6) | (c[2] & 0x3F)
        code[at] = np.where(c[0] < 0xE0, two, np.where(c[0] < 0xF0, three, 0x20000))
    where = np.flatnonzero(code)
    starts = np.array([a for a, _ in SCRIPTS])
    kinds = np.array([NAMES.index(s) for _, s in SCRIPTS])[np.searchsorted(starts, code[where], "right") - 1]
    row = np.searchsorted(words.edge, where, "right") - 1
    return np.bincount(row * len(NAMES) + kinds, minlength=words.rows * len(NAMES)).reshape(words.rows, len(NAMES))


def _trigrams(words: Words) -> tuple[np.ndarray, np.ndarray]:
    """The bucket of the three bytes around each byte of each word, and where each word's buckets start."""
    inked = np.zeros(len(words.data) + 2, np.uint64)
    inside = np.zeros(len(words.data) + 1, np.int8)
    np.add.at(inside, words.start, 1)
    np.add.at(inside, words.end, -1)
    inside = np.cumsum(inside[:-1]).astype(bool)
    inked[1:-1] = np.where(inside, words.data, 0)
    before, after = inked[:-2].copy(), inked[2:].copy()
    before[words.start] = after[words.end - 1] = 0  # the last word of a row touches the first one of the next
    code = (before << np.uint64(16)) | (inked[1:-1] << np.uint64(8)) | after
    bucket = ((code[inside] * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - 17)).astype(np.int64)
    return bucket, np.r_[0, np.cumsum(words.end - words.start)][:-1].astype(np.int64)


class Model:
    def __init__(self, langs: list[str], table: np.ndarray, scripts: np.ndarray):
        self.langs, self.table, self.scripts = langs, table, scripts  # table: BUCKETS x L; scripts: L x len(NAMES) booleans


def fit(docs: DataFrame, label: str = "lang", text: str = "text", rows: int = TRAIN_ROWS) -> Model:
    """From rows with a label; of more than rows of them, about rows by a hash of the text. Scores need at least one label."""
    spark = docs.sparkSession
    ship(spark)
    known = docs.filter(F.col(label).isNotNull() & F.col(text).isNotNull()).select(F.col(label).alias("lang"), F.col(text).alias("text"))
    total = known.count()
    if total > rows:
        known = known.filter(F.pmod(F.xxhash64("text"), F.lit(total)) < rows)

    def count(batches):
        for batch in batches:
            lang = np.array(batch.column(0).to_pylist(), object)
            sums: dict = {}
            for low, high in slices(batch.column(1)):
                w = Words(batch.column(1), low, high)
                bucket, at = _trigrams(w)
                length = np.diff(np.r_[at, len(bucket)])
                by = lang[low:high][np.repeat(w.row, length)] if len(at) else np.zeros(0, object)
                script = _script_of_bytes(w)
                for name in set(lang[low:high]):
                    own = sums.setdefault(name, [np.zeros(BUCKETS, np.int64), np.zeros(len(NAMES), np.int64)])
                    own[0] += np.bincount(bucket[by == name], minlength=BUCKETS)
                    own[1] += script[lang[low:high] == name].sum(0)
            for name, (grams, script) in sums.items():
                full, used = np.flatnonzero(grams), np.flatnonzero(script)
                yield pa.record_batch([pa.array([name] * (len(full) + len(used)), pa.string()), pa.array(np.r_[full, BUCKETS + used]), pa.array(np.r_[grams[full], script[used]])], ["lang", "bucket", "n"])

    got = known.mapInArrow(count, "lang string, bucket long, n long").groupBy("lang", "bucket").agg(F.sum("n").alias("n")).toArrow()
    names = got["lang"].to_pylist()
    langs = sorted(set(names))
    if not langs:
        return Model([], np.zeros((BUCKETS, 0), np.float32), np.zeros((0, len(NAMES)), bool))
    lang = np.array([langs.index(x) for x in names])
    bucket, n = got["bucket"].to_numpy(), got["n"].to_numpy()
    grams = np.zeros((BUCKETS + len(NAMES), len(langs)))
    grams[bucket, lang] = n
    script = grams[BUCKETS:].T
    grams = grams[:BUCKETS]
    smooth = grams + 0.5
    table = np.log(smooth / (grams.sum(0) + 0.5 * 20_000))
    return Model(langs, (table - table.mean(1, keepdims=True)).astype(np.float32), script >= SHARE * np.maximum(1, script.sum(1, keepdims=True)))


def viterbi(e: np.ndarray, penalty: float) -> np.ndarray:
    """The best label of each word (rows of e) under a cost for each change of label; ties go to staying, then to the first."""
    n, k = e.shape
    best = int(np.argmax(e.sum(0)))
    gain = e - e[:, best : best + 1]
    gain[:, best] = -np.inf
    d = gain.max(1) if k > 1 else np.full(n, -1.0)
    c = np.r_[0.0, np.cumsum(d)]
    if c[1:].max() <= penalty and (c[-1] - c[:-1]).max() <= penalty and (c - np.minimum.accumulate(c)).max() <= 2 * penalty:
        return np.full(n, best, np.int64)
    score, back = e[0].astype(float).copy(), np.zeros((n, k), np.int64)
    own = np.arange(k)
    for t in range(1, n):
        top = int(np.argmax(score))
        moved = score[top] - penalty
        back[t] = np.where(score >= moved, own, top)
        score = np.maximum(score, moved) + e[t]
    path = np.zeros(n, np.int64)
    path[-1] = int(np.argmax(score))
    for t in range(n - 1, 0, -1):
        path[t - 1] = back[t, path[t]]
    return path


def label(docs: DataFrame, model: Model, key: str = "doc_id", text: str = "text", penalty: float = PENALTY, spans: bool = False) -> DataFrame:
    """(key, lang_pred, score [, spans]) for every row.

    score: the share of the text's letters that lie in spans of lang_pred; spans: array of (first word, words, lang).
    A text that is null, or has no letter, is UNDETERMINED with score 0; with no language learned, every text is."""
    ship(docs.sparkSession)
    langs, wide = model.langs, "array<struct<first:int,words:int,lang:string>>"
    sent = docs.sparkSession.sparkContext.broadcast((model.table, model.scripts))  # BUCKETS x languages, whatever the corpus

    def run(batches):
        table, scripts = sent.value
        for batch in batches:
            ids, body, lettered = batch.column(0), batch.column(1), batch.column(2).to_numpy(zero_copy_only=False)
            for low, high in slices(body):
                w = Words(body, low, high)
                bucket, at = _trigrams(w)
                script = _script_of_bytes(w)
                e = np.add.reduceat(table[bucket], at, axis=0) if len(at) else np.zeros((0, len(langs)), np.float32)
                letters = np.r_[0, np.cumsum(((w.data >= 97) & (w.data <= 122)) | (w.data >= 0xC3))]
                weight = letters[w.end] - letters[w.start]
                names, scores, held = [], [], []
                for r in range(high - low):
                    a, b = w.first[r], w.first[r + 1]
                    own = weight[a:b]
                    if not lettered[low + r] or b == a or not langs:
                        names.append(UNDETERMINED)
                        scores.append(0.0)
                        held.append([])
                        continue
                    uses = script[r] >= max(1, SHARE * script[r].sum())
                    able = np.flatnonzero((scripts & uses).any(1)) if scripts.shape[0] else np.arange(len(langs))
                    able = able if len(able) else np.arange(len(langs))
                    path = able[viterbi(np.where(own[:, None] > 0, e[a:b][:, able], 0), penalty)]
                    share = np.bincount(path, weights=own, minlength=len(langs)) if own.sum() else np.bincount(path, minlength=len(langs)).astype(float)
                    top = int(np.argmax(share))
                    names.append(langs[top])
                    scores.append(float(share[top] / share.sum()))
                    if spans:
                        cut = np.flatnonzero(np.r_[True, path[1:] != path[:-1]])
                        held.append([{"first": int(c), "words": int(n), "lang": langs[path[c]]} for c, n in zip(cut, np.diff(np.r_[cut, len(path)]), strict=True)])
                out = [ids.slice(low, high - low), pa.array(names, pa.string()), pa.array(scores, pa.float64())]
                if spans:
                    out.append(pa.array(held, pa.list_(pa.struct([("first", pa.int32()), ("words", pa.int32()), ("lang", pa.string())]))))
                yield pa.record_batch(out, ["key", "lang_pred", "score", "spans"][: len(out)])

    body = F.coalesce(F.col(text), F.lit(""))
    kind = dict(docs.dtypes)[key]
    out = docs.select(F.col(key).alias("key"), body.alias("text"), body.rlike(r"\p{L}").alias("lettered")).mapInArrow(run, f"key {kind}, lang_pred string, score double" + f", spans {wide}" * spans)
    return out.withColumnRenamed("key", key)
