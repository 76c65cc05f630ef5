"""Language-model scoring by prediction by partial matching over bytes.

The model is a trie of byte contexts up to `order` bytes. A byte is coded in the longest known context; an
escape (method C: as likely as the context has distinct successors) leads to the next shorter one, where the
successors already ruled out are excluded; bytes never seen share what is left evenly.

`score_pretrained` trains on a part of the corpus and scores every document with the frozen trie. Nothing
that grows is collected or broadcast: documents are dealt into blocks, each block asks once for every
distinct word and (context, byte) pair it holds, the questions meet in buckets, and the answers go back. Questions
are summed up level by level, `fan_in` tables of distinct keys at a time, until `fan_in` are left for each bucket;
these are answered, and the answers go down the same levels, to each table only what it asked for. So the number of
blocks changes the number of levels, and nothing else.

A bucket holds whole branches of the trie: all pairs that end in the same two context bytes. A branch with more than
`branch_bytes` of the training text (and more than 1/4096 of it) is split by one context byte more, and so on; the
successor counts of such contexts, at most 4096 x 256 of a length, travel to every task, as do those of the two
upper levels (256 x 256).

`score_adaptive` starts an empty trie for each document and updates it after every byte.

A document's byte stream is its ASCII-lower-cased words joined by spaces and a newline as the end.

Defined cases: a null or empty text is the end alone; a null id counts as held out; rows are scored each by
itself, repeated or not; without any training row every byte costs log10(256).
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import id_remainder, keep_table, read_table, text_blocks

END = b"\n"
CHUNK = 1 << 21


class ByteTrie:
    """The model in its plainest form: counts of successors per context, as nested dictionaries."""

    def __init__(self, order: int):
        self.order = order
        self.counts: dict[bytes, dict[int, int]] = {}

    def update(self, before: bytes, symbol: int) -> None:
        for k in range(self.order + 1):
            at = self.counts.setdefault(before[len(before) - k :], {})
            at[symbol] = at.get(symbol, 0) + 1

    def log10(self, before: bytes, symbol: int) -> float:
        total, excluded = 0.0, set()
        for k in range(self.order, -1, -1):
            at = self.counts.get(before[len(before) - k :])
            if not at:
                continue
            live = {s: n for s, n in at.items() if s not in excluded}
            mass = sum(live.values()) + len(live)
            if symbol in live:
                return total + float(np.log10(live[symbol] / mass))
            if live:
                total += float(np.log10(len(live) / mass))
            excluded |= set(at)
        return total - float(np.log10(256 - len(excluded)))

    def steps(self, words: list[bytes]) -> Iterator[tuple[bytes, int]]:
        data = END * self.order + b" ".join(words) + END
        for i in range(self.order, len(data)):
            yield data[i - self.order : i], data[i]

    def train(self, words: list[bytes]) -> None:
        for before, symbol in self.steps(words):
            self.update(before, symbol)

    def score(self, words: list[bytes], adapt: bool = False) -> float:
        total = 0.0
        for before, symbol in self.steps(words):
            total += self.log10(before, symbol)
            if adapt:
                self.update(before, symbol)
        return total


def split_words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


def _streams(texts: list[list[bytes]], order: int) -> tuple[np.ndarray, np.ndarray]:
    """(pairs of all scored bytes as numbers, number of scored bytes per document). The low byte of a pair is
    the symbol, the next its closest predecessor, and so on."""
    bodies = [b" ".join(w) + END for w in texts]
    gap = END * (order - 1)
    data = np.frombuffer(END * order + gap.join(bodies), np.uint8)
    sizes = np.array([len(b) for b in bodies], np.int64)
    pairs = data[order:].astype(np.uint64)
    for j in range(1, order + 1):
        pairs |= data[order - j : len(data) - j].astype(np.uint64) << np.uint64(8 * j)
    if order > 1 and len(bodies) > 1:
        runs = np.full(2 * len(bodies) - 1, order - 1, np.int64)
        runs[::2] = sizes
        flag = np.zeros(len(runs), bool)
        flag[::2] = True
        pairs = pairs[np.repeat(flag, runs)]
    return pairs, sizes


def _chunks(texts: list[list[bytes]]) -> Iterator[tuple[int, int]]:
    at, size = 0, 0
    for i, words in enumerate(texts):
        size += sum(map(len, words)) + len(words) + 1
        if size >= CHUNK:
            yield at, i + 1
            at, size = i + 1, 0
    if at < len(texts):
        yield at, len(texts)


def _tally(texts: list[list[bytes]], order: int) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs and their counts."""
    keys, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
    for a, b in _chunks(texts):
        code, found = pd.factorize(_streams(texts[a:b], order)[0])
        keys.append(found)
        counts.append(np.bincount(code, minlength=len(found)))
    code, found = pd.factorize(np.concatenate(keys))
    return found, np.bincount(code, np.concatenate(counts), len(found)).astype(np.int64)


class HotContexts:
    """Successor counts of the contexts that are too frequent for one bucket, by context length."""

    def __init__(self):
        self.grams: dict[int, np.ndarray] = {}  # context and successor as one number, in order
        self.counts: dict[int, np.ndarray] = {}
        self.contexts: dict[int, np.ndarray] = {}

    def add(self, length: int, contexts: np.ndarray, grams: np.ndarray, counts: np.ndarray) -> None:
        turn = np.argsort(grams)
        self.contexts[length], self.grams[length], self.counts[length] = np.sort(contexts), grams[turn], counts[turn]

    def complete(self, length: int, asked: np.ndarray, grams: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Grams and counts of one length, those of hot contexts replaced by all that training holds."""
        if length not in self.contexts:
            return grams, n
        hot = self.contexts[length]
        mine = _lookup(hot, grams >> np.uint64(8))[1]
        wanted = np.unique(np.concatenate([grams[mine], asked]) >> np.uint64(8))
        give = _lookup(wanted, self.grams[length] >> np.uint64(8))[1]
        grams, n = np.concatenate([grams[~mine], self.grams[length][give]]), np.concatenate([n[~mine], self.counts[length][give]])
        turn = np.argsort(grams)
        return grams[turn], n[turn]


def _pair_bucket(pairs: np.ndarray, buckets: int, hot: HotContexts) -> np.ndarray:
    context = pairs >> np.uint64(8)
    branch, still = context & np.uint64(0xFFFF), np.ones(len(pairs), bool)
    for length in sorted(hot.contexts):
        still &= _lookup(hot.contexts[length], context & np.uint64((1 << 8 * length) - 1))[1]
        deeper = (context & np.uint64((1 << 8 * (length + 1)) - 1)) + np.uint64(length << 57)
        branch = np.where(still, deeper, branch)
    return ((branch * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(33)) % np.uint64(buckets)


def _planes(a: np.ndarray, width: int) -> bytes:
    """Numbers as planes of bytes, which compress far better than numbers in a row."""
    return np.ascontiguousarray(a.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :width].T).tobytes()


def _numbers(raw: bytes, width: int) -> np.ndarray:
    out = np.zeros((len(raw) // width, 8), np.uint8)
    out[:, :width] = np.frombuffer(raw, np.uint8).reshape(width, -1).T
    return out.reshape(-1).view("<u8").astype(np.uint64)


def _ordered_words(words, buckets: int) -> list[list[bytes]]:
    out: list[list[bytes]] = [[] for _ in range(buckets)]
    for w in words:
        out[zlib.crc32(w) % buckets].append(w)
    for x in out:
        x.sort()
    return out


def _ask(order: int, buckets: int, hot: HotContexts):
    """Questions of one block: words and pairs, with their counts in its training rows."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        block = pdf["block"].iloc[0]
        texts = [split_words(t) for t in pdf["text"]]
        held = pdf["held_out"].to_numpy(bool)
        train = [w for w, h in zip(texts, held) if not h]
        rows = []
        words: Counter = Counter()
        for w in train:
            words.update(w)
        words[END] += len(train)
        known = set(words)
        for w, h in zip(texts, held):
            if h:
                known.update(w)
        for bucket, keys in enumerate(_ordered_words(known, buckets)):
            if keys:
                counts = np.fromiter((words[w] for w in keys), np.uint64, len(keys))
                rows.append((bucket, block, b" ".join(keys), _planes(counts, 6)))
        del words, known
        pairs, counts = _tally(train, order)
        others, _ = _tally([w for w, h in zip(texts, held) if h], order)
        others = np.setdiff1d(others, pairs, assume_unique=True)
        pairs = np.concatenate([pairs, others])
        counts = np.concatenate([counts, np.zeros(len(others), np.int64)])
        where = _pair_bucket(pairs, buckets, hot)
        turn = np.lexsort((pairs, where))
        pairs, counts, where = pairs[turn], counts[turn], where[turn]
        cuts = np.searchsorted(where, np.arange(buckets + 1))
        for bucket in range(buckets):
            a, b = cuts[bucket], cuts[bucket + 1]
            if b > a:
                rows.append((buckets + bucket, block, _planes(pairs[a:b], order + 1), _planes(counts[a:b], 6)))
        return pd.DataFrame(rows, columns=["bucket", "block", "keys", "counts"])

    return run


def _lookup(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(place, found) of keys in a sorted table."""
    if len(table) == 0:
        return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return at, table[at] == keys


def pair_scores(
    asked: np.ndarray, pairs: np.ndarray, counts: np.ndarray, upper: np.ndarray, order: int, hot: HotContexts
) -> np.ndarray:
    """log10 probability of every asked pair. pairs, counts: the trained pairs of whole branches; upper[c, s]: how
    often s follows c in training; hot: what branches that are split over buckets lack.

    Successor sets are nested (what follows a long context also follows its end), so at each level only the
    sums over the set one level up have to be taken off."""
    score = np.zeros(len(asked))
    live = np.ones(len(asked), bool)
    deeper = None  # (contexts, sum of this level's counts over their successors, number of successors)
    for k in range(order, -1, -1):
        if k >= 2:
            mask = np.uint64((1 << (8 * (k + 1))) - 1)
            grams, inverse = np.unique(pairs & mask, return_inverse=True)
            grams, n = hot.complete(k, asked & mask, grams, np.bincount(inverse, counts, len(grams)))
            contexts, inverse = np.unique(grams >> np.uint64(8), return_inverse=True)
            total = np.bincount(inverse, n, len(contexts))
            distinct = np.bincount(inverse, minlength=len(contexts)).astype(float)
            at, seen = _lookup(contexts, (asked & mask) >> np.uint64(8))
            here, has = _lookup(grams, asked & mask)
            mass = np.where(seen, total[at], 0.0) if len(contexts) else np.zeros(len(asked))
            kinds = np.where(seen, distinct[at], 0.0) if len(contexts) else np.zeros(len(asked))
            own = np.where(has, n[here], 0.0) if len(grams) else np.zeros(len(asked))
            step = (grams, n)
        else:
            symbol = (asked & np.uint64(0xFF)).astype(np.int64)
            if k == 1:
                close = ((asked >> np.uint64(8)) & np.uint64(0xFF)).astype(np.int64)
                mass, kinds = upper.sum(axis=1)[close], (upper > 0).sum(axis=1)[close].astype(float)
                own = upper[close, symbol]
            else:
                single = upper.sum(axis=0)
                mass = np.full(len(asked), single.sum(), float)
                kinds = np.full(len(asked), float((single > 0).sum()))
                own = single[symbol]
            seen, has = mass > 0, own > 0
        if deeper is not None:
            keys, held_sum, held_kinds, place, was = deeper
            if k >= 2:
                # counts of this level summed over the successors of the longer context
                up_at, _ = _lookup(grams, keys & mask)
                lost = np.bincount(held_sum, n[up_at], len(held_kinds))
            elif k == 1:
                lost = np.bincount(
                    held_sum,
                    upper[((keys >> np.uint64(8)) & np.uint64(0xFF)).astype(np.int64), (keys & np.uint64(0xFF)).astype(np.int64)],
                    len(held_kinds),
                )
            else:
                lost = ((upper > 0) * single[None, :]).sum(axis=1)
            if len(held_kinds):
                mass = mass - np.where(was, lost[place], 0.0)
                kinds = kinds - np.where(was, held_kinds[place], 0.0)
        room = np.maximum(mass + kinds, 1e-300)
        hit = live & seen & has
        score[hit] += np.log10(own[hit] / room[hit])
        miss = live & seen & ~has & (kinds > 0)
        score[miss] += np.log10(kinds[miss] / room[miss])
        live &= ~hit
        if k >= 2:
            deeper = (grams, inverse, distinct, at, seen)
        elif k == 1:
            deeper = (None, None, (upper > 0).sum(axis=1).astype(float), close, seen)
    unseen = 256 - int((upper.sum(axis=0) > 0).sum())
    score[live] -= np.log10(max(unseen, 1))
    return score


def _sum_words(asked: list[list[bytes]], counts: list[np.ndarray]) -> dict[bytes, int]:
    total: dict[bytes, int] = {}
    for words, n in zip(asked, counts):
        for w, c in zip(words, n.tolist()):
            total[w] = total.get(w, 0) + c
    return total


def _sum_pairs(asked: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(distinct pairs in order, place of every asked pair among them, sums)."""
    distinct, inverse = np.unique(np.concatenate(asked), return_inverse=True)
    return distinct, inverse, np.bincount(inverse, np.concatenate(counts), len(distinct))


def _answer(order: int, buckets: int, upper: np.ndarray, hot: HotContexts):
    """Answers of one bucket to all tables that asked it; block -1 carries the distinct trained words."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        bucket = int(pdf["bucket"].iloc[0])
        pdf = pdf.sort_values("block")
        blocks = list(pdf["block"])
        counts = [_numbers(x, 6).astype(np.int64) for x in pdf["counts"]]
        if bucket < buckets:
            asked = [x.split(b" ") for x in pdf["keys"]]
            total = _sum_words(asked, counts)
            out = [_planes(np.fromiter((total[w] for w in x), np.uint64, len(x)), 6) for x in asked]
            known = sum(c > 0 for c in total.values())
            return pd.DataFrame({"bucket": bucket, "block": [*blocks, -1], "found": [*out, b""], "n": [*[0] * len(blocks), known]})
        keys = [_numbers(x, order + 1) for x in pdf["keys"]]
        distinct, inverse, n = _sum_pairs(keys, counts)
        score = pair_scores(distinct, distinct[n > 0], n[n > 0], upper, order, hot)
        cuts = np.cumsum([0, *map(len, keys)])
        out = [score[inverse[a:b]].tobytes() for a, b in zip(cuts, cuts[1:])]
        return pd.DataFrame({"bucket": bucket, "block": blocks, "found": out, "n": 0})

    return run


def _merge(order: int, buckets: int):
    """The tables of one bucket and part as one: distinct keys, in order, and their sums."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        bucket = int(pdf["bucket"].iloc[0])
        counts = [_numbers(x, 6).astype(np.int64) for x in pdf["counts"]]
        if bucket < buckets:
            total = _sum_words([x.split(b" ") for x in pdf["keys"]], counts)
            words = sorted(total)
            keys, sums = b" ".join(words), np.fromiter((total[w] for w in words), np.uint64, len(words))
        else:
            pairs, _, sums = _sum_pairs([_numbers(x, order + 1) for x in pdf["keys"]], counts)
            keys = _planes(pairs, order + 1)
        return pd.DataFrame({"bucket": bucket, "block": pdf["part"].iloc[:1], "keys": [keys], "counts": [_planes(sums, 6)]})

    return run


def _hand_down(order: int, buckets: int):
    """What a merged table was answered, to each of the tables that it was merged from."""

    def run(asked: pd.DataFrame, answer: pd.DataFrame) -> pd.DataFrame:
        if len(asked) == 0:
            return pd.DataFrame({"bucket": [], "block": [], "found": []})
        bucket, found = int(asked["bucket"].iloc[0]), answer["found"].iloc[0]
        if bucket < buckets:
            each = [x.split(b" ") for x in asked["keys"]]
            count = dict(zip(sorted(set().union(*each)), _numbers(found, 6).tolist()))
            out = [_planes(np.fromiter((count[w] for w in x), np.uint64, len(x)), 6) for x in each]
        else:
            keys = [_numbers(x, order + 1) for x in asked["keys"]]
            known, score = np.unique(np.concatenate(keys)), np.frombuffer(found, np.float64)
            out = [score[np.searchsorted(known, x)].tobytes() for x in keys]
        return pd.DataFrame({"bucket": bucket, "block": asked["block"], "found": out})

    return run


def _answers(
    asked: DataFrame, blocks: int, fan_in: int, order: int, buckets: int, upper: np.ndarray, hot: HotContexts
) -> tuple[DataFrame, int]:
    """(answers by bucket and block, distinct trained words)."""
    levels = []
    while blocks > fan_in:
        asked = keep_table(asked.withColumn("part", F.expr(f"cast(block div {fan_in} as int)")), "questions")
        levels.append(asked)
        asked = asked.groupBy("bucket", "part").applyInPandas(_merge(order, buckets), "bucket int, block int, keys binary, counts binary")
        blocks = -(-blocks // fan_in)
    made = asked.groupBy("bucket").applyInPandas(
        _answer(order, buckets, upper, hot), "bucket int, block int, found binary, n long"
    )
    answers = keep_table(made, "answers")
    kinds = answers.where("block = -1").agg(F.sum("n")).first()[0] or 0
    answers = answers.where("block >= 0").select("bucket", "block", "found")
    for asked in reversed(levels):
        above = answers.withColumnRenamed("block", "part")
        made = (
            asked.select("bucket", "part", "block", "keys")
            .groupBy("bucket", "part")
            .cogroup(above.groupBy("bucket", "part"))
            .applyInPandas(_hand_down(order, buckets), "bucket int, block int, found binary")
        )
        answers = keep_table(made, "answers")
    return answers, kinds


def _hot_counts(length: int, contexts: np.ndarray):
    """Successors of the given contexts: counts per context and byte."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        keys, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for pdf in batches:
            texts = [split_words(t) for t in pdf["text"]]
            for a, b in _chunks(texts):
                pairs, _ = _streams(texts[a:b], length)
                code, found = pd.factorize(pairs[_lookup(contexts, pairs >> np.uint64(8))[1]])
                keys.append(found)
                counts.append(np.bincount(code, minlength=len(found)))
            code, found = pd.factorize(np.concatenate(keys))
            counts = [np.bincount(code, np.concatenate(counts), len(found)).astype(np.int64)]
            keys = [found]
        yield pd.DataFrame({"key": keys[0].astype(np.int64) if len(keys[0]) else [], "n": counts[0]}, dtype="int64")

    return run


def hot_contexts(train: DataFrame, upper: np.ndarray, order: int, branch_bytes: int) -> HotContexts:
    """Contexts of two bytes or more that hold too much of the training text for one task, found from the shorter
    ones; one scan of the text for each length that has any."""
    hot = HotContexts()
    limit = max(branch_bytes, upper.sum() / 4096)
    before, after = np.nonzero(upper > limit)
    contexts = np.sort((before << 8 | after).astype(np.uint64))
    for length in range(2, order):
        if not len(contexts):
            break
        rows = train.mapInPandas(_hot_counts(length, contexts), "key long, n long").groupBy("key").agg(F.sum("n").alias("n"))
        found = rows.collect()  # at most 4096 * 256 rows
        grams, counts = np.array([r["key"] for r in found], np.uint64), np.array([r["n"] for r in found], np.int64)
        hot.add(length, contexts, grams, counts)
        contexts = np.sort(grams[counts > limit])
    return hot


def _settle(order: int, buckets: int, hot: HotContexts):
    """Scores of one block's documents from the answers."""

    def run(pdf: pd.DataFrame, answers: pd.DataFrame) -> pd.DataFrame:
        texts = [split_words(t) for t in pdf["text"]]
        found = dict(zip(answers["bucket"], answers["found"]))
        words = {w for x in texts for w in x} | {END}
        count: dict[bytes, int] = {}
        for bucket, keys in enumerate(_ordered_words(words, buckets)):
            if keys:
                count.update(zip(keys, _numbers(found[bucket], 6).astype(np.int64).tolist()))
        del words
        n_known, log_sum = [], []
        for x in texts:
            c = np.array([count[w] for w in x] + [count[END]], float)
            n_known.append(int((c > 0).sum()))
            log_sum.append(float(np.log10(c + 0.1).sum()))
        n_tokens = [len(x) + 1 for x in texts]
        del count
        parts, places = [], [np.zeros(0, np.uint64)]
        for a, b in _chunks(texts):
            pairs, sizes = _streams(texts[a:b], order)
            code, keys = pd.factorize(pairs)
            parts.append((code.astype(np.int32), keys, sizes))
            places.append(keys)
        del texts
        distinct = pd.unique(np.concatenate(places))
        where = _pair_bucket(distinct, buckets, hot)
        distinct = distinct[np.lexsort((distinct, where))]
        score = np.concatenate([np.frombuffer(found.get(buckets + i, b""), np.float64) for i in range(buckets)])
        turn = np.argsort(distinct)
        distinct, score = distinct[turn], score[turn]
        total = []
        for code, keys, sizes in parts:
            each = score[np.searchsorted(distinct, keys)][code]
            total.append(np.add.reduceat(each, np.cumsum(sizes) - sizes))
        return pd.DataFrame(
            {
                "doc_id": pdf["doc_id"],
                "held_out": pdf["held_out"],
                "n_tokens": n_tokens,
                "n_known": n_known,
                "log_sum": log_sum,
                "score": np.concatenate(total),
            }
        )

    return run


def _upper_counts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Counts of byte after byte (key 256 * before + after) and, under key -1, of tokens."""
    table, tokens = np.zeros(65536, np.int64), 0
    for pdf in batches:
        texts = [split_words(t) for t in pdf["text"]]
        tokens += sum(map(len, texts)) + len(texts)
        for a, b in _chunks(texts):
            pairs, _ = _streams(texts[a:b], 1)
            table += np.bincount(pairs.astype(np.int64), minlength=65536)
    at = np.flatnonzero(table)
    yield pd.DataFrame({"key": [*at, -1], "n": [*table[at], tokens]}, dtype="int64")


def score_pretrained(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    held_out=None,
    order: int = 5,
    block_bytes: int = 12 << 20,
    fan_in: int = 256,
    branch_bytes: int = 8 << 20,
) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row. Rows where
    held_out(id column) holds are scored only, the others also train."""
    if not 2 <= order <= 7:
        raise ValueError("order must be from 2 to 7")
    held = F.lit(False) if held_out is None else held_out(F.col(id_col))
    # at least a block a core, of 64 kB or more
    blocks = max(text_blocks(docs, text_col, block_bytes), min(docs.sparkSession.sparkContext.defaultParallelism, text_blocks(docs, text_col, 1 << 16)))
    buckets = min(4096, max(8, blocks))
    src = docs.select(
        F.col(id_col).cast("string").alias("doc_id"),
        held.alias("held_out"),
        F.coalesce(F.col(text_col), F.lit("")).alias("text"),
        F.pmod(F.xxhash64(F.col(id_col), F.col(text_col)), F.lit(blocks)).cast("int").alias("block"),
    )
    train = src.where("not held_out").select("text")
    rows = train.mapInPandas(_upper_counts, "key long, n long")
    upper, tokens = np.zeros((256, 256)), 0
    for r in rows.groupBy("key").agg(F.sum("n").alias("n")).collect():  # at most 256 * 256 + 1 rows
        if r["key"] < 0:
            tokens = r["n"]
        else:
            upper[r["key"] >> 8, r["key"] & 255] = r["n"]
    hot = hot_contexts(train, upper, order, branch_bytes)
    asked = src.groupBy("block").applyInPandas(
        _ask(order, buckets, hot), "bucket int, block int, keys binary, counts binary"
    )
    answers, kinds = _answers(asked, blocks, fan_in, order, buckets, upper, hot)
    scored = (
        src.groupBy("block")
        .cogroup(answers.groupBy("block"))
        .applyInPandas(
            _settle(order, buckets, hot),
            "doc_id string, held_out boolean, n_tokens long, n_known long, log_sum double, score double",
        )
    )
    room = float(np.log10(tokens + 0.1 * (kinds + 1)))
    return scored.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        "held_out",
        "n_tokens",
        "n_known",
        F.lit(tokens).cast("long").alias("train_tokens"),
        (F.col("log_sum") - F.col("n_tokens") * F.lit(room)).alias("base_score"),
        "score",
    )


def score_adaptive(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", order: int = 5) -> DataFrame:
    """doc_id, n_bytes, score: log10 probability of each text under a trie that starts empty."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            words = [split_words(t) for t in pdf["text"]]
            yield pd.DataFrame(
                {
                    "doc_id": pdf["doc_id"],
                    "n_bytes": [len(b" ".join(w)) + 1 for w in words],
                    "score": [ByteTrie(order).score(w, adapt=True) for w in words],
                }
            )

    src = docs.select(F.col(id_col).cast("string").alias("doc_id"), F.col(text_col).alias("text"))
    out = src.mapInPandas(run, "doc_id string, n_bytes long, score double")
    return out.withColumn("doc_id", F.col("doc_id").cast("long"))


def op1_ppm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_pretrained(read_table(spark, sf_dir, "documents"), held_out=lambda i: id_remainder(i, 10) == 0)
