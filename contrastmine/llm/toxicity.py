"""Toxicity by fuzzy lexicon: a Levenshtein automaton run over a trie of learned terms, with windows of context.

The lexicon holds words that stand in toxic training documents in many different surroundings and hardly ever in clean
ones. Counting surroundings (the word before and after) and not documents keeps copies of one document from turning its
rare words into terms. A misspelling is a word within the term's edit distance that clean training documents do not use.
Each hit is weighed by its window: quotation marks or reporting words around it mark a quotation, address marks abuse.
A logistic model over the three sums of evidence gives the score."""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import clean_text, drawn_share, held_out, stored, tidy, to_frame, whole, worker_state
from .tokens import batches
from .words import numbered

# Words of quotation and of address in the four languages of the tables.
REPORTING = frozenset("said says wrote writes called calls quote quoted word term reported alleged dit disait mot citation sagte schrieb zitat wort dijo escribio cita palabra".split())
ADDRESS = frozenset("you your youre u tu vous ton votre du dich dein ihr euch usted tus vosotros".split())
QUOTES = "\"'“”„«»‹›‘’`"
WINDOW = 5  # words of context on each side
WORD = re.compile(r"[^\W_]+")
SCORES = "doc_id long, held_out boolean, score double, hits long, quoted long"


def distance_for(term: str) -> int:
    """Edits allowed: none below five letters, one below twelve, else two."""
    return 0 if len(term) < 5 else 1 if len(term) < 12 else 2


class FuzzyTrie:
    """The intersection of the Levenshtein automata of all terms with the trie of the terms, made deterministic as it is used.

    A state is a set of (trie node, edits spent) pairs, closed under skipped letters; each pair knows the most edits that
    any term below its node allows, so dead branches go at once. States and moves are remembered."""

    def __init__(self, terms: dict[str, float], most_states: int = 40_000):
        self.most_states = most_states
        self.terms = list(terms)
        self.next: list[dict[str, int]] = [{}]
        self.term_at: list[int | None] = [None]
        self.allowed = [0]
        for k, t in enumerate(self.terms):
            node = 0
            self.allowed[0] = max(self.allowed[0], distance_for(t))
            for c in t:
                if c not in self.next[node]:
                    self.next[node][c] = len(self.next)
                    self.next.append({})
                    self.term_at.append(None)
                    self.allowed.append(0)
                node = self.next[node][c]
                self.allowed[node] = max(self.allowed[node], distance_for(t))
            self.term_at[node] = k
        self.letters = {c for n in self.next for c in n}
        self.forget()

    def forget(self) -> None:
        """Begin again without states: their number follows the words seen, not the terms."""
        self.states: list[dict[int, int]] = []
        self.moves: list[dict[str, int]] = []
        self.accepts: list[tuple[int, int] | None] = []
        self.known: dict[frozenset, int] = {}
        self.start = self._state({0: 0})

    def _state(self, pairs: dict[int, int]) -> int:
        """pairs: fewest edits by node. Closure: a term's letter that the word lacks costs one."""
        todo = list(pairs)
        while todo:
            node = todo.pop()
            e = pairs[node] + 1
            for child in self.next[node].values():
                if e <= self.allowed[child] and pairs.get(child, 99) > e:
                    pairs[child] = e
                    todo.append(child)
        key = frozenset(pairs.items())
        if key not in self.known:
            self.known[key] = len(self.states)
            self.states.append(pairs)
            self.moves.append({})
            ends = [(e, self.term_at[n]) for n, e in pairs.items() if self.term_at[n] is not None and e <= distance_for(self.terms[self.term_at[n]])]
            self.accepts.append(min(ends) if ends else None)
        return self.known[key]

    def _step(self, state: int, c: str) -> int:
        out: dict[int, int] = {}

        def offer(node, e):
            if e <= self.allowed[node] and out.get(node, 99) > e:
                out[node] = e

        for node, e in self.states[state].items():
            offer(node, e + 1)  # a letter too many
            for letter, child in self.next[node].items():
                offer(child, e if letter == c else e + 1)
        return self._state(out) if out else -1

    def match(self, word: str) -> tuple[str, int] | None:
        """(term, edits) of the nearest term within its distance."""
        if len(self.states) > self.most_states:
            self.forget()
        state = self.start
        for c in word:
            if c not in self.letters:
                c = ""  # all letters of no term behave alike
            moves = self.moves[state]
            nxt = moves.get(c)
            if nxt is None:
                nxt = moves[c] = self._step(state, c)
            if nxt < 0:
                return None
            state = nxt
        found = self.accepts[state]
        return (self.terms[found[1]], found[0]) if found else None


def words_of(text):
    return F.regexp_extract_all(F.lower(text), F.lit(r"([\p{L}\p{N}]+)"), F.lit(1))


def training_rows(docs: DataFrame, labels: DataFrame, most: int) -> DataFrame:
    """(text, toxic) of labelled documents outside the held-out fold; of more than `most` labels, about so many, drawn by a hash.

    The ids go to the documents by broadcast: about `most` of them at most."""
    marked = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & ~held_out()).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").cast("int").alias("toxic"))
    chosen = marked.where(drawn_share(min(1.0, most / max(1, marked.count())), "doc_id"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"))
    return texts.join(F.broadcast(chosen), "doc_id").select("text", "toxic")


def fit_lexicons(train: DataFrame, surroundings: int = 3, precision: float = 0.8, evidence: float = 18.0) -> tuple[dict[str, float], dict[str, float]]:
    """Terms learned from all rows, and from those that are not `rest`: the weight (log-odds, in documents) of each.

    A term stands in so many surroundings of toxic documents at least; of the documents with it, so large a share is
    toxic; and its log-likelihood ratio against chance is beyond what rare words reach by luck. Words are counted for both
    in one pass, combined before each shuffle."""
    listed = train.select("toxic", F.when(F.col("rest"), 0).otherwise(1).alias("part"), words_of("text").alias("w"))
    padded = listed.where("toxic = 1").select("part", F.concat(F.array(F.lit("")), "w", F.array(F.lit(""))).alias("w"))
    spread = padded.selectExpr("part", "explode(transform(sequence(1, greatest(size(w) - 2, 1)), i -> struct(w[i] as word, xxhash64(w[i - 1], w[i + 1]) as ctx))) as x").select("part", "x.*").where("word <> ''")
    frequent = spread.groupBy("word", "ctx").agg(F.max("part").alias("part")).groupBy("word").agg(F.count(F.lit(1)).alias("ctx_all"), F.sum("part").alias("ctx_part")).where(F.col("ctx_all") >= surroundings)
    counts = listed.select("toxic", "part", F.explode(F.array_distinct("w")).alias("word")).groupBy("word").agg(
        F.sum("toxic").alias("t_all"), F.sum(1 - F.col("toxic")).alias("c_all"), F.sum(F.col("toxic") * F.col("part")).alias("t_part"), F.sum((1 - F.col("toxic")) * F.col("part")).alias("c_part")
    )
    joined = stored(counts.where((F.col("t_all") >= 2) & (F.length("word") >= 3)).join(frequent, "word"), "terms")  # words of the bounded sample
    shares = train.agg(F.avg("toxic").alias("all"), F.avg(F.when(~F.col("rest"), F.col("toxic"))).alias("part")).first()
    found = []
    for name in ("all", "part"):
        base, t, c = shares[name], F.col(f"t_{name}"), F.col(f"c_{name}")
        if not base or base == 1:
            found.append({})
            continue
        ratio = 2 * (t * F.log(t / (t + c) / base) + F.when(c > 0, c * F.log(c / (t + c) / (1 - base))).otherwise(0.0))
        strong = joined.where((F.col(f"ctx_{name}") >= surroundings) & (t > 0)).where((t >= precision * (t + c)) & (ratio >= evidence))
        rows = strong.select("word", t.alias("t"), c.alias("c")).orderBy(F.desc("t"), "word").collect()
        found.append({r.word: float(np.log((r.t + 0.5) / (r.c + 0.5))) for r in rows})
    return found[0], found[1]


def words_before(text: str, a: int, n: int = WINDOW) -> list[str]:
    """The last n words that end before a place, however long they are."""
    reach = 64
    while True:
        found = WORD.findall(text, max(0, a - reach), a)
        if len(found) > n or reach >= a:  # one more than needed, as the first may be cut
            return found[-n:]
        reach *= 4


def words_after(text: str, b: int, n: int = WINDOW) -> list[str]:
    """The first n words that begin after a place."""
    out = []
    for m in WORD.finditer(text, b):
        out.append(m.group())
        if len(out) == n:
            break
    return out


class Scorer:
    """Evidence of a text: sums over its hits of exact terms, misspelt ones, and hits in quotation."""

    def __init__(self, terms: dict[str, float], ordinary: frozenset[str] = frozenset()):
        self.terms, self.ordinary = terms, ordinary
        self.trie = FuzzyTrie(terms)

    def hit(self, word: str) -> tuple[str, int] | None:
        found = self.trie.match(word) if len(word) > 2 else None
        return None if found and found[1] and word in self.ordinary else found

    def evidence(self, text: str, words: frozenset[str]) -> tuple[float, float, float, int, int]:
        """words: those of the text that hit."""
        exact = fuzzy = quoted = 0.0
        hits = in_quotes = 0
        low = text.lower()
        either = "|".join(map(re.escape, sorted(words, key=len, reverse=True)))
        for m in re.finditer(rf"(?<![^\W_])(?:{either})(?![^\W_])", low):
            found = self.hit(m.group())
            if not found:
                continue
            a, b = m.span()
            near = {*words_before(low, a), *words_after(low, b)}
            weight = self.terms[found[0]] * (1.25 if near & ADDRESS else 1.0)
            hits += 1
            if (a and low[a - 1] in QUOTES and low[b : b + 1] and low[b] in QUOTES) or near & REPORTING:
                quoted += weight
                in_quotes += 1
            elif found[1]:
                fuzzy += weight / (1 + found[1])
            else:
                exact += weight
        return exact, fuzzy, quoted, hits, in_quotes

    def of_texts(self, texts: list[str]) -> list[tuple[float, float, float, int, int]]:
        names, codes, bounds = numbered(texts)
        good = np.fromiter((self.hit(w) is not None for w in names), bool, len(names))
        out = [(0.0, 0.0, 0.0, 0, 0)] * len(texts)
        if good.any():
            held = np.concatenate(([0], np.cumsum(good[codes])))[bounds]
            for i in np.flatnonzero(held[1:] > held[:-1]):
                mine = codes[bounds[i] : bounds[i + 1]]
                out[i] = self.evidence(texts[i], frozenset(names[c] for c in set(mine[good[mine]].tolist())))
        return out


def scorer_of(terms: dict[str, float], ordinary: frozenset[str] = frozenset()) -> Scorer:
    """One for all tasks of a worker, so that the automaton's states are found once."""
    state, key = worker_state("scorers"), (frozenset(terms.items()), ordinary)
    if key not in state:
        if len(state) > 2:
            state.clear()
        state[key] = Scorer(terms, ordinary)
    return state[key]


def features(rows) -> np.ndarray:
    return np.array([(1.0, np.log1p(e), np.log1p(f), np.log1p(q)) for e, f, q, *_ in rows]).reshape(-1, 4)


PRIOR = np.array([-3.0, 2.0, 1.2, 0.3])  # constant, exact, misspelt, quoted: what stands where the training rows say nothing


def fit_logistic(x: np.ndarray, y: np.ndarray, n: np.ndarray, steps: int = 40, ridge: float = 0.05) -> np.ndarray:
    """Newton's method on rows that stand for n documents each, drawn towards the prior weights."""
    w = PRIOR.copy()
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        hess = x.T @ (x * (n * p * (1 - p))[:, None]) + ridge * np.eye(len(w))
        w = w - np.linalg.solve(hess, x.T @ (n * (p - y)) + ridge * (w - PRIOR))
    return w


class ToxicityModel:
    def __init__(self, terms: dict[str, float], ordinary: frozenset[str], weights: np.ndarray):
        self.terms, self.ordinary, self.weights = terms, ordinary, weights


def ordinary_words(train: DataFrame, lexicons: tuple[dict[str, float], ...]) -> list[frozenset[str]]:
    """For each lexicon, the words within its distance that clean training documents use; for the second, only those that are not `rest`."""
    schema = "which int, word string"

    def variants(frames):
        scorers = [scorer_of(terms) for terms in lexicons]
        for frame in frames:
            for which, scorer in enumerate(scorers):
                own = frame[(frame["toxic"] == 0) & ~(frame["rest"] & (which == 1))]["text"].tolist() if scorer.terms else []
                for a, b in batches(own, 4_000_000):
                    yield to_frame([(which, w) for w in numbered(own[a:b])[0] if (h := scorer.hit(w)) and h[1]], schema)

    rows = train.mapInPandas(tidy(variants), schema).distinct().collect()  # neighbours of the terms only
    return [frozenset(r.word for r in rows if r.which == k) for k in range(len(lexicons))]


def calibrate(rows: DataFrame, terms: dict[str, float], ordinary: frozenset[str]) -> np.ndarray:
    """Logistic weights of the three sums of evidence, on rows of the bounded sample that the terms were not learned from."""
    schema = "e double, f double, q double, t long"

    def measure(frames):
        scorer = scorer_of(terms, ordinary)
        for frame in frames:
            texts = frame["text"].tolist()
            found = [f for a, b in batches(texts, 4_000_000) for f in scorer.of_texts(texts[a:b])]
            yield to_frame([(round(e, 2), round(f, 2), round(q, 2), int(t)) for (e, f, q, *_), t in zip(found, frame["toxic"], strict=True)], schema)

    grouped = rows.mapInPandas(tidy(measure), schema).groupBy("e", "f", "q", "t").count().collect()
    if not grouped:
        return PRIOR
    n, y = np.array([r["count"] for r in grouped], float), np.array([r.t for r in grouped], float)
    return fit_logistic(features([(r.e, r.f, r.q) for r in grouped]), y, n)


def fit(docs: DataFrame, labels: DataFrame, most_rows: int = 200_000) -> ToxicityModel:
    """Learn from labelled rows outside the held-out fold, about `most_rows` of them at most; without any, all scores are low.

    Weights are found with terms learned from seven tenths of the texts and measured on the rest; the terms are then
    learned from all."""
    train = stored(training_rows(docs, labels, most_rows).withColumn("rest", F.pmod(F.xxhash64("text"), F.lit(10)) >= 7), "training")
    every, part = fit_lexicons(train)
    ordinary, ordinary_part = ordinary_words(train, (every, part))
    return ToxicityModel(every, ordinary, calibrate(train.where("rest"), part, ordinary_part))


def probability(rows, weights: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(features(rows) @ weights, -30, 30)))


def score(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, held_out, score, hits, quoted) per document: one map over the rows.

    Null and empty texts have no hit and the score of such; null ids are kept; repeated rows score alike; an empty table
    gives none; other columns are ignored."""
    terms, ordinary, weights = model.terms, model.ordinary, model.weights

    def work(frames):
        scorer = scorer_of(terms, ordinary)
        for frame in frames:
            texts, keys, held = frame["text"].tolist(), whole(frame["doc_id"]), frame["held_out"].tolist()
            for a, b in batches(texts, 4_000_000):
                rows = scorer.of_texts(texts[a:b])
                yield to_frame([(k, h, float(p), n, q) for k, h, p, (*_, n, q) in zip(keys[a:b], held[a:b], probability(rows, weights), rows, strict=True)], SCORES)

    chosen = docs.select(F.col("doc_id").cast("long").alias("doc_id"), clean_text().alias("text"), held_out().alias("held_out"))
    return chosen.mapInPandas(tidy(work), SCORES)


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, hits, quoted, predicted): learn from the labelled rows outside the held-out fold, score every document.

    Without labels of both classes no term is learned and all scores are low. Labels with a null id or mark are ignored,
    and of several labels of one id the toxic one counts; for documents the cases are those of score()."""
    return score(docs, fit(docs, labels)).withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def drop_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """Documents below the threshold, with all their columns: one map over the rows, which adds no column, so names cannot clash.

    Null and empty texts have the score of no hit and stay; repeated rows go or stay alike; an empty table gives none."""
    model, place = fit(docs, labels), docs.columns.index("text")
    terms, ordinary, weights = model.terms, model.ordinary, model.weights

    def calm(tables):
        import pyarrow as pa

        scorer = scorer_of(terms, ordinary)
        for batch in tables:
            texts = [t or "" for t in batch.column(place).to_pylist()]
            p = np.concatenate([np.zeros(0), *(probability(scorer.of_texts(texts[a:b]), weights) for a, b in batches(texts, 4_000_000))])
            yield batch.filter(pa.array(p < threshold, pa.bool_()))

    return docs.mapInArrow(tidy(calm), docs.schema)
