"""Brown class-based bigrams: exchange clustering, class transitions and word emissions, smoothed.

All counts cover the whole training part of the corpus. The most frequent `types` words are put into classes by
exchange: each word in turn moves to the class that raises the likelihood of the class bigrams most. All other words
follow in parallel, each into the class that raises it most against the counts of those classes. A text's probability is
the product over its tokens of class given class before and word given class. Words without a training token have
classes by their written form, with the counts of the words that training has once. What a worker holds is bounded: the
counts and classes of `held` frequent words; those of the rarer words of a text are joined.

train() and score() are the smaller model, in which words beyond the `held` have classes by their written form too.
"""

from __future__ import annotations

import string
import uuid
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dyngraph.llm.common import scope, written
from dyngraph.llm.quality_ftrl import held_out

END = "\n"  # the end token: no word holds white space
TYPES = 1024
CLASSES = 32
ROUNDS = 4
HELD = 200_000
FLUSH = 300_000
FORMS = 8
HOLE = (1 << 16) - 1
_marks = frozenset(string.punctuation.encode())
_cache: dict = {}


def tokens(text: str | None) -> list[bytes]:
    """The words of a text with A-Z in lower case; bytes, so that only ASCII counts as white space."""
    return (text or "").encode("utf-8", "replace").lower().split()


def form(word: bytes) -> int:
    """Class by written form: what it ends with, and whether all is ASCII."""
    last = word[-1]
    return 2 * (0 if last == 46 else 1 if last == 44 else 2 if last in _marks else 3) + (not word.isascii())


def form_sql(token):
    """form() as an expression."""
    last = F.substring(token, -1, 1)
    kind = F.when(last == ".", 0).when(last == ",", 1).when(token.rlike(r"[!-/:-@\[-`{-~]$"), 2).otherwise(3)
    return 2 * kind + token.rlike(r"[^\x00-\x7F]").cast("int")


def _count(batches):
    seen: Counter = Counter()

    def rows():
        out = pa.RecordBatch.from_arrays([pa.array([w.decode() for w in seen], pa.string()), pa.array(list(seen.values()), pa.int64())], names=["token", "n"])
        seen.clear()
        return out

    for b in batches:
        for t in b.column("text").to_pylist():
            seen.update(tokens(t))
            seen[END.encode()] += 1
            if len(seen) > FLUSH:
                yield rows()
    if seen:
        yield rows()


class _Ids(dict):
    """Words to ids: the given ones by place, others by form behind them."""

    def __init__(self, words: list[bytes]):
        super().__init__((w, i) for i, w in enumerate(words))
        self.words = words

    def __missing__(self, word):
        if len(self) > FLUSH:
            self.clear()
            self.update((w, i) for i, w in enumerate(self.words))
        i = self[word] = len(self.words) + form(word)
        return i


def _pairs(words: list[bytes]):
    def pairs(batches):
        ids, size = _Ids(words), len(words) + FORMS + 1
        end, total = size - 1, np.zeros(size * size, np.int64)
        for b in batches:
            flat = [end]
            for t in b.column("text").to_pylist():
                flat += map(ids.__getitem__, tokens(t))
                flat.append(end)
            x = np.array(flat, np.int64)
            total += np.bincount(x[:-1] * size + x[1:], minlength=size * size)
        at = np.flatnonzero(total)
        for lo in range(0, len(at), 100_000):
            part = at[lo : lo + 100_000]
            yield pa.RecordBatch.from_arrays([pa.array(part), pa.array(total[part])], names=["cell", "n"])

    return pairs


def _xlogx(x):
    return x * np.log(np.maximum(x, 1e-300))


def exchange(pairs: np.ndarray, movable: int, classes: int = CLASSES, rounds: int = ROUNDS) -> np.ndarray:
    """Class of each id: the first `movable` ids (by falling frequency) are clustered, each other id is a class of its own behind them."""
    fixed = len(pairs) - movable
    of = np.concatenate([np.arange(movable) % classes, classes + np.arange(fixed)])
    size = classes + fixed
    member = np.zeros((len(pairs), size))
    member[np.arange(len(pairs)), of] = 1
    m = member.T @ pairs @ member
    out_total, in_total = pairs.sum(1), pairs.sum(0)
    for _ in range(rounds):
        moved = 0
        for w in range(movable):
            r = np.bincount(of, pairs[w], size)
            c = np.bincount(of, pairs[:, w], size)
            s, old = pairs[w, w], of[w]
            r[old] -= s
            c[old] -= s
            m[old] -= r
            m[:, old] -= c
            m[old, old] -= s
            f = _xlogx(m)
            gain = (_xlogx(m + r) - f).sum(1) + (_xlogx(m + c[:, None]) - f).sum(0)
            d = np.diag(m)
            gain += _xlogx(d + r + c + s) - _xlogx(d + r) - _xlogx(d + c) + _xlogx(d)
            # marginals count every transition of a class, the ones to w included
            ro, co = np.bincount(of, out_total, size), np.bincount(of, in_total, size)
            ro[old] -= out_total[w]
            co[old] -= in_total[w]
            gain -= _xlogx(ro + out_total[w]) - _xlogx(ro) + _xlogx(co + in_total[w]) - _xlogx(co)
            new = int(np.argmax(gain[:classes]))
            if gain[new] <= gain[old] + 1e-9:
                new = old
            m[new] += r
            m[:, new] += c
            m[new, new] += s
            moved += new != old
            of[w] = new
        if not moved:
            break
    return of


def best_classes(starts: np.ndarray, at: np.ndarray, n: np.ndarray, m: np.ndarray, classes: int) -> np.ndarray:
    """The class whose bigram likelihood each word raises most; ties to the lower class.

    A word's entries begin at `starts`: n times it stands behind class `at`, or before class `at` less the width of m.
    """
    behind = at < len(m)
    cell = np.concatenate([m[:, :classes], m[:classes].T])
    gain = np.add.reduceat(_xlogx(cell[at] + n[:, None]) - _xlogx(cell)[at], starts)
    for own, side in ((m.sum(1)[:classes], ~behind), (m.sum(0)[:classes], behind)):
        more = np.add.reduceat(n * side, starts)
        gain -= _xlogx(own + more[:, None]) - _xlogx(own)
    return gain.argmax(1)


def _vocabulary(shipped, key: str) -> dict:
    """Ids of the held words and classes by id, kept by the worker; the end has the id behind them."""
    if _cache.get("key") != key:
        m = shipped.value
        _cache.clear()
        words = m["words"].split(b"\n") if m["words"] else []
        ids = {w: i for i, w in enumerate(words)}
        ids[END.encode()] = len(words)
        known = np.array([*(m["classes"] + form(w) for w in words), m["classes"] + FORMS], np.int64)
        known[: len(m["class"])] = m["class"]
        _cache.update(key=key, ids=ids, words=words, known=known)
    return _cache


def _classes(texts: list, held: dict, classes: int) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """(tokens; ids, -1 for rare words; classes) of all tokens of some texts in a row."""
    flat: list[bytes] = []
    for t in texts:
        flat += tokens(t)
        flat.append(END.encode())
    at = np.fromiter((held["ids"].get(w, -1) for w in flat), np.int64, len(flat))
    cls = held["known"][at]
    rare = np.flatnonzero(at < 0)
    cls[rare] = [classes + form(flat[i]) for i in rare.tolist()]
    return flat, at, cls


def _lists(cells: np.ndarray, n: np.ndarray, per: int) -> tuple[np.ndarray, pa.ListArray]:
    """(rows that occur, their cells as n * per + place) of sorted cells row * per + place."""
    rows, starts = np.unique(cells // per, return_index=True)
    return rows, pa.ListArray.from_arrays(pa.array(np.append(starts, len(cells)), pa.int32()), pa.array(n.astype(np.int64) * per + cells % per))


def _neighbours(shipped, key: str, rare: bool):
    """(word, token, near) of the words that have no learnt class yet: held ones by id, with `rare` the others by token.

    near: counts by place (class before, or width + class after), as count * 2 * width + place.
    """

    def count(batches):
        held, m = _vocabulary(shipped, key), shipped.value
        k, per = len(m["class"]), 2 * (m["classes"] + FORMS + 1)
        rest = len(held["words"]) - k
        total = np.zeros(rest * per, np.int32)
        others: dict = {}
        waiting: list = []

        def found(rows, near, tokens_of=None):
            for lo in range(0, len(rows), 20_000):
                part = rows[lo : lo + 20_000]
                word, token = (np.full(len(part), -1), [tokens_of[i] for i in part]) if tokens_of else (part, [None] * len(part))
                yield pa.RecordBatch.from_arrays([pa.array(word, pa.int64()), pa.array(token, pa.string()), near[lo : lo + 20_000]], names=["word", "token", "near"])

        def flush():
            if others:
                cells, n = np.unique(np.concatenate(waiting), return_counts=True)
                yield from found(*_lists(cells, n, per), [w.decode() for w in others])
            others.clear()
            waiting.clear()

        for b in batches:
            texts = b.column("text").to_pylist()
            for lo in range(0, len(texts), 512):
                flat, at, cls = _classes(texts[lo : lo + 512], held, m["classes"])
                cls = np.append(cls, per // 2 - 1)  # also the class before the first token
                here = np.flatnonzero((at >= k) & (at < k + rest))
                row = (at[here] - k) * per
                cells, n = np.unique(np.concatenate([row + cls[here - 1], row + per // 2 + cls[here + 1]]), return_counts=True)
                total[cells] += n.astype(np.int32)
                here = np.flatnonzero(at < 0) if rare else here[:0]
                row = np.fromiter((others.setdefault(flat[i], len(others)) for i in here.tolist()), np.int64, len(here)) * per
                waiting += [row + cls[here - 1], row + per // 2 + cls[here + 1]]
                if len(others) > FLUSH // 4:
                    yield from flush()
        yield from flush()
        at = np.flatnonzero(total)
        if len(at):
            yield from found(*_lists(at, total[at], per))

    return count


def _placed(m: np.ndarray, classes: int):
    """(word, token, n, class) of words by their counts of all tasks."""
    per = 2 * len(m)

    def place(batches):
        for b in batches:
            for lo in range(0, len(b), 10_000):
                part = b.slice(lo, 10_000)
                lists = part.column("near").flatten()
                row = np.repeat(np.repeat(np.arange(len(part)), part.column("near").value_lengths().to_numpy()), lists.value_lengths().to_numpy())
                near = lists.flatten().to_numpy()
                cells, which = np.unique(row * per + near % per, return_inverse=True)
                n = np.bincount(which, near // per, len(cells))
                at = cells % per
                starts = np.unique(cells // per, return_index=True)[1]
                times = np.add.reduceat(n * (at < len(m)), starts).astype(np.int64)
                chosen = pa.array(best_classes(starts, at, n, m, classes), pa.int32())
                yield pa.RecordBatch.from_arrays([part.column("word"), part.column("token"), pa.array(times), chosen], names=["word", "token", "n", "class"])

    return place


def _place(texts: DataFrame, model: dict, m: np.ndarray, rare: bool) -> DataFrame:
    """(word, token, n, class) of all words behind those of the exchange, written; without `rare` of held ones only."""
    near = texts.mapInArrow(_neighbours(texts.sparkSession.sparkContext.broadcast(model), uuid.uuid4().hex, rare), "word long, token string, near array<long>")
    lists = near.groupBy("word", "token").agg(F.collect_list("near").alias("near"))
    return written(lists.mapInArrow(_placed(m, model["classes"]), "word long, token string, n long, class int"), "lm-classes")


def _transitions(shipped, key: str):
    """Counts of class bigrams, one row a task."""

    def count(batches):
        held, m = _vocabulary(shipped, key), shipped.value
        width = m["classes"] + FORMS + 1
        total = np.zeros(width * width, np.int64)
        for b in batches:
            texts = b.column("text").to_pylist()
            for lo in range(0, len(texts), 512):
                _, _, cls = _classes(texts[lo : lo + 512], held, m["classes"])
                x = np.concatenate([[width - 1], cls])
                total += np.bincount(x[:-1] * width + x[1:], minlength=width * width)
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.list_(pa.int64()))], names=["counts"])

    return count


def _frequent(words: DataFrame, held: int) -> tuple[list[bytes], np.ndarray]:
    """The `held` most frequent words and their counts; tasks send no word that is rarer than all of them."""
    times = words.groupBy("n").agg(F.count(F.lit(1)).alias("v")).orderBy(F.desc("n")).toArrow()
    n, upto = times["n"].to_numpy(), np.cumsum(times["v"].to_numpy())
    least = int(n[min(np.searchsorted(upto, held), len(n) - 1)]) if len(n) else 0
    top = words.where(F.col("n") >= least).orderBy(F.desc("n"), "token").limit(held).toArrow()
    return [t.encode() for t in top["token"].to_pylist()], top["n"].to_numpy().astype(np.int64)


def _start(learn: DataFrame, types: int, classes: int, held: int, rounds: int) -> tuple[DataFrame, dict, np.ndarray]:
    """(counts of all tokens, model with the classes of the exchange, class bigrams of these).

    The driver holds the `held` most frequent words and (types + FORMS + 1)^2 pair counts at most.
    """
    texts = learn.select("text")
    counts = texts.mapInArrow(_count, "token string, n long").groupBy("token").agg(F.sum("n").alias("n"))
    counts = written(counts, "token-counts")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1)), F.coalesce(F.sum(F.when(F.col("token") == END, F.col("n"))), F.lit(0))).first()
    frequent, n = _frequent(counts.where(F.col("token") != END), held)
    k = min(types, len(frequent))
    size = k + FORMS + 1
    cells = texts.mapInArrow(_pairs(frequent[:k]), "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    pairs = np.zeros(size * size)
    pairs[cells["cell"].to_numpy()] = cells["n"].to_numpy()
    del cells
    pairs = pairs.reshape(size, size)
    of = exchange(pairs, k, classes, rounds)
    member = np.zeros((size, classes + FORMS + 1))
    member[np.arange(size), of] = 1
    model = {"words": b"\n".join(frequent), "class": of[:k], "classes": classes, "n": n, "total": total[0], "distinct": total[1], "ends": total[2]}
    return counts, model, member.T @ pairs @ member


def _with_held(model: dict, placed: DataFrame) -> dict:
    """The model with the classes of all held words."""
    found = placed.where("word >= 0").select("word", "class").toArrow()
    first = model["class"]
    of = np.concatenate([first, np.zeros(len(model["n"]) - len(first), np.int64)])
    of[len(first) + found["word"].to_numpy()] = found["class"].to_numpy()
    return model | {"class": of}


def _summed(rows: DataFrame, width: int) -> np.ndarray:
    """The sum of the count arrays of all tasks, as a matrix."""
    sums = rows.select(F.posexplode("counts").alias("cell", "n")).groupBy("cell").agg(F.sum("n").alias("n")).collect()
    m = np.zeros(width * width)
    m[[r["cell"] for r in sums]] = [r["n"] for r in sums]
    return m.reshape(width, width)


def _smoothed(m: np.ndarray, delta: float) -> tuple[np.ndarray, np.ndarray]:
    """(tokens by class, log10 probability of class after class)."""
    seen = m.sum(0)
    unigram = (seen + 0.5) / (seen.sum() + 0.5 * len(m))
    return seen, np.log10((m + delta * unigram) / (m.sum(1, keepdims=True) + delta))


def train(learn: DataFrame, types: int = TYPES, classes: int = CLASSES, held: int = HELD, rounds: int = ROUNDS, delta: float = 1.0) -> tuple[DataFrame, dict]:
    """(counts of all tokens, model), with classes by written form for the words beyond the `held`."""
    texts, spark = learn.select("text"), learn.sparkSession
    counts, model, m = _start(learn, types, classes, held, rounds)
    words, n, width = counts.where(F.col("token") != END), model["n"], classes + FORMS + 1
    by_form = {r["f"]: r["v"] for r in words.groupBy(form_sql(F.col("token")).alias("f")).agg(F.count(F.lit(1)).alias("v")).collect()}
    for w in model["words"].split(b"\n") if len(n) else []:
        by_form[form(w)] -= 1
    if len(n) > len(model["class"]):
        model = _with_held(model, _place(texts, model, m, rare=False))
        rows = texts.mapInArrow(_transitions(spark.sparkContext.broadcast(model), uuid.uuid4().hex), "counts array<long>")
        m = _summed(rows, width)
    seen, log_t = _smoothed(m, delta)
    inside = np.bincount(model["class"], n, width) if len(n) else np.zeros(width)
    # words by form: add-one over the types of the form and one more
    rest = np.array([seen[classes + f] + by_form.get(f, 0) + 1 for f in range(FORMS)])
    emit = np.log10(n / inside[model["class"]])
    return counts, model | {"emit": emit, "log_t": log_t, "log_rest": np.log10(rest)}


def _scorer(shipped, key: str):
    def score(batches):
        m, held = shipped.value, _vocabulary(shipped, key)
        ids, classes, known_class = held["ids"], m["classes"], held["known"]
        end = classes + FORMS
        log_n = np.log10(m["n"] + 1.0)
        share = np.log10(m["total"] + m["distinct"] + 1)
        end_base = np.log10(m["ends"] + 1) - share
        for b in batches:
            cols: list[list] = [[] for _ in range(5)]
            for doc, text in zip(b.column("doc_id").to_pylist(), b.column("text").to_pylist()):
                ws = tokens(text)
                at = np.fromiter((ids.get(w, -1) for w in ws), np.int64, len(ws))
                rare = np.flatnonzero(at < 0)
                cls = np.full(len(ws) + 1, end)
                known = at >= 0
                cls[:-1][known] = known_class[at[known]]
                rare_words = [ws[i] for i in rare.tolist()]
                cls[:-1][rare] = [classes + form(w) for w in rare_words]
                prev = np.concatenate([[end], cls[:-1]])
                base = log_n[at[known]].sum() - share * len(ws) + end_base
                by_form = cls[:-1][~known] - classes
                s = m["log_t"][prev, cls].sum() + m["emit"][at[known]].sum() - m["log_rest"][by_form].sum()
                out = Counter(rare_words)
                for c, v in zip(cols, (doc, len(ws) + 1, base, s, [{"token": w.decode(), "m": x} for w, x in out.items()])):
                    c.append(v)
            kinds = (pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.list_(pa.struct([("token", pa.string()), ("m", pa.int64())])))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["doc_id", "n_tokens", "base", "part", "rare"])

    return score


def score(docs: DataFrame, counts: DataFrame, model: dict) -> DataFrame:
    """doc_id, n_tokens, n_known, train_tokens, base_score, score and perplexity of each text (null: only the end token).

    Repeated rows are scored each. The counts of rare words meet the texts in a shuffled join on the word; none of
    them is frequent, as the frequent ones are held by the workers.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select("doc_id", "text").mapInArrow(_scorer(shipped, uuid.uuid4().hex), "doc_id long, n_tokens long, base double, part double, rare array<struct<token: string, m: long>>")
    rows = written(rows.withColumn("row", F.monotonically_increasing_id()), "lm-rows")
    words = rows.select("row", F.explode("rare").alias("r")).select("row", "r.*")
    n = F.coalesce(F.col("n"), F.lit(0))
    # one token's counts are one row, so the join adds no rows
    joined = words.join(counts, "token", "left").groupBy("row").agg(F.sum(F.col("m") * F.log10(n + 1.0)).alias("log_n"), F.sum(F.when(n == 0, F.col("m")).otherwise(0)).alias("new"))
    out = rows.drop("rare").join(joined, "row", "left")
    extra, share = F.coalesce("log_n", F.lit(0.0)), F.lit(float(np.log10(model["total"] + model["distinct"] + 1)))
    result = out.select(
        "doc_id", "n_tokens", (F.col("n_tokens") - F.coalesce("new", F.lit(0)) - (0 if model["ends"] else 1)).alias("n_known"), F.lit(int(model["total"])).cast("long").alias("train_tokens"),
        (F.col("base") + extra).alias("base_score"), (F.col("part") + extra).alias("score"),
    )
    return result.withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))


def _coded(shipped, key: str):
    """Texts as class numbers of two bytes each, HOLE for words that are not held; these, each once, as tokens with their forms and places.

    A word that training has once has the number width + class * FORMS + form.
    """

    def code(batches):
        m, held = shipped.value, _vocabulary(shipped, key)
        ids, classes = held["ids"], m["classes"]
        numbers = held["known"][: len(m["n"])].copy()
        for i in np.flatnonzero(m["n"] == 1).tolist():
            numbers[i] = classes + FORMS + 1 + numbers[i] * FORMS + form(held["words"][i])
        numbers = np.append(numbers, HOLE).astype(np.uint16)
        log_n, log_n1 = np.append(np.log10(m["n"]), 0), np.append(np.log10(m["n"] + 1.0), 0)
        for b in batches:
            for lo in range(0, len(b), 512):
                part = b.slice(lo, 512)
                cols: list[list] = [[] for _ in range(6)]
                for text in part.column("text").to_pylist():
                    ws = tokens(text)
                    at = np.fromiter((ids.get(w, -1) for w in ws), np.int64, len(ws))
                    rare: dict = {}
                    places = [rare.setdefault(ws[i], len(rare)) for i in np.flatnonzero(at < 0).tolist()]
                    values = (numbers[at].tobytes(), np.array(places, np.int32).tobytes(), bytes(map(form, rare)), [w.decode() for w in rare], float(log_n[at].sum()), float(log_n1[at].sum()))
                    for c, v in zip(cols, values):
                        c.append(v)
                kinds = (pa.binary(), pa.binary(), pa.binary(), pa.list_(pa.string()), pa.float64(), pa.float64())
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), part.column("learnt"), *[pa.array(c, t) for c, t in zip(cols, kinds)]], names=["doc_id", "learnt", "codes", "places", "forms", "rare", "log_n", "log_n1"])

    return code


def _filled(classes: int):
    """The rows of _coded with the numbers of the words that are not held, and how many of the tokens are new."""
    width = classes + FORMS + 1

    def fill(batches):
        for b in batches:
            lists = b.column("known")
            ends = np.concatenate([[0], np.cumsum(lists.value_lengths().fill_null(0).to_numpy())])
            i, n, cls = (lists.flatten().field(j).to_numpy() for j in range(3))
            codes, new, log_n, log_n1 = [], [], b.column("log_n").to_numpy().copy(), b.column("log_n1").to_numpy().copy()
            rows = (b.column(c).to_pylist() for c in ("codes", "places", "forms"))
            for r, (text, places, forms) in enumerate(zip(*rows)):
                x = np.frombuffer(text, np.uint16)
                places = np.frombuffer(places, np.int32)
                new.append(0)
                if len(places):
                    form_of = np.frombuffer(forms, np.uint8).astype(np.int64)
                    number, times = classes + form_of, np.zeros(len(form_of))
                    of = slice(ends[r], ends[r + 1])
                    j = i[of]
                    times[j] = n[of]
                    number[j] = np.where(n[of] == 1, width + cls[of] * FORMS + form_of[j], cls[of])
                    x = x.copy()
                    x[x == HOLE] = number[places]
                    here = times[places]
                    new[-1] = int((here == 0).sum())
                    log_n[r] += np.log10(np.maximum(here, 1)).sum()
                    log_n1[r] += np.log10(here + 1).sum()
                codes.append(x.tobytes())
            yield pa.RecordBatch.from_arrays(
                [b.column("doc_id"), b.column("learnt"), pa.array(codes, pa.binary()), pa.array(new, pa.int64()), pa.array(log_n), pa.array(log_n1)],
                names=["doc_id", "learnt", "codes", "new", "log_n", "log_n1"],
            )

    return fill


def _both(text: bytes, classes: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(classes of the tokens between two ends, classes that they had as new words, whether training has the word once)."""
    width = classes + FORMS + 1
    x = np.frombuffer(text, np.uint16).astype(np.int64)
    x = np.concatenate([[width - 1], x, [width - 1]])
    once = x >= width
    return np.where(once, (x - width) // FORMS, x), np.where(once, classes + (x - width) % FORMS, x), once


def _transitions_coded(classes: int):
    """Counts of class bigrams, one row a task; each word that training has once counts once more as a new word of its form."""
    width = classes + FORMS + 1

    def count(batches):
        total = np.zeros(width * width, np.int64)
        for b in batches:
            for text in b.column("codes").to_pylist():
                cls, new, once = _both(text, classes)
                a, z = once[:-1], once[1:]
                cells = [cls[:-1] * width + cls[1:], (cls[:-1] * width + new[1:])[z], (new[:-1] * width + cls[1:])[a], (new[:-1] * width + new[1:])[a & z]]
                total += np.bincount(np.concatenate(cells), minlength=width * width)
        yield pa.RecordBatch.from_arrays([pa.array([total], pa.list_(pa.int64()))], names=["counts"])

    return count


def _scored_coded(classes: int, log_t: np.ndarray, log_in: np.ndarray):
    def score(batches):
        for b in batches:
            size, part = [], []
            for text in b.column("codes").to_pylist():
                cls = _both(text, classes)[0]
                size.append(len(cls) - 1)
                part.append(float(log_t[cls[:-1], cls[1:]].sum() - log_in[cls[1:]].sum()))
            keep = ["doc_id", "new", "log_n", "log_n1"]
            yield pa.RecordBatch.from_arrays([*[b.column(c) for c in keep], pa.array(size, pa.int64()), pa.array(part)], names=[*keep, "n_tokens", "part"])

    return score


def fit(docs: DataFrame, learnt, types: int = TYPES, classes: int = CLASSES, held: int = HELD, rounds: int = ROUNDS, delta: float = 1.0) -> tuple[DataFrame, dict]:
    """(all texts as class numbers, model) with a learnt class for every word of the texts for which the condition `learnt` holds.

    The classes and counts of words that are not held meet the texts in a shuffled join on the word.
    """
    spark = docs.sparkSession
    learn = docs.where(learnt)
    counts, model, m = _start(learn, types, classes, held, rounds)
    placed = _place(learn.select("text"), model, m, rare=True)
    inside = np.bincount(model["class"], model["n"][: len(model["class"])], classes) if len(model["class"]) else np.zeros(classes)
    for r in placed.groupBy("class").agg(F.sum("n").alias("n")).collect():
        inside[r["class"]] += r["n"]
    model = _with_held(model, placed)
    schema = "doc_id long, learnt boolean, codes binary, places binary, forms binary, rare array<string>, log_n double, log_n1 double"
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", learnt.alias("learnt")).mapInArrow(_coded(spark.sparkContext.broadcast(model), uuid.uuid4().hex), schema)
    rows = written(rows.withColumn("row", F.monotonically_increasing_id()), "lm-rows")
    # a word has one class, so the join adds no rows
    words = rows.select("row", F.posexplode("rare").alias("i", "token")).join(placed.where("word < 0").select("token", "n", "class"), "token")
    known = words.groupBy("row").agg(F.collect_list(F.struct("i", "n", "class")).alias("known"))
    filled = rows.drop("rare").join(known, "row", "left").drop("row").mapInArrow(_filled(classes), "doc_id long, learnt boolean, codes binary, new long, log_n double, log_n1 double")
    filled = written(filled, "lm-filled")
    bigrams = filled.where("learnt").select("codes").mapInArrow(_transitions_coded(classes), "counts array<long>")
    seen, log_t = _smoothed(_summed(bigrams, classes + FORMS + 1), delta)
    # new words: as many of a form as training has once, and one more
    log_in = np.log10(np.concatenate([np.maximum(inside, 1), seen[classes : classes + FORMS] + 1, [1]]))
    return filled, model | {"log_t": log_t, "log_in": log_in}


def evaluate(docs: DataFrame, **options) -> DataFrame:
    """Learns from the documents outside the held-out fold (a null doc_id is not learnt from) and scores all; null texts are the end token only."""
    with scope(docs.sparkSession) as inner:
        filled, m = fit(docs, F.col("doc_id").isNotNull() & ~held_out(7, 2), **options)
        inner.keep(filled)
    rows = filled.mapInArrow(_scored_coded(m["classes"], m["log_t"], m["log_in"]), "doc_id long, new long, log_n double, log_n1 double, n_tokens long, part double")
    share = float(np.log10(m["total"] + m["distinct"] + 1))
    result = rows.select(
        "doc_id", held_out(7, 2).alias("held_out"), "n_tokens", (F.col("n_tokens") - F.col("new") - (0 if m["ends"] else 1)).alias("n_known"), F.lit(int(m["total"])).cast("long").alias("train_tokens"),
        (F.col("log_n1") - F.lit(share) * F.col("n_tokens") + F.lit(float(np.log10(m["ends"] + 1)))).alias("base_score"), (F.col("part") + F.col("log_n")).alias("score"),
    )
    return result.withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))
