"""Plain versions of what the operators compute, straight from their contracts."""

import functools
import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SPACED = re.compile("[^\x20\x09-\x0d]+")
ALNUM = re.compile("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")


def sha(x):
    return hashlib.sha256(x.encode()).hexdigest()


def spaced(text):
    return SPACED.findall(text or "")


def tokenized(path, texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    ids = [t.encode(x or "", add_special_tokens=False).ids for x in texts]
    return ids, [t.decode(i, skip_special_tokens=False) for i in ids]


def contamination(docs, items):
    words = lambda x: ALNUM.findall((x or "").translate(LOW))
    windows = defaultdict(lambda: defaultdict(set))
    for i, x in items:
        w = words(x)
        k = min(10, len(w))
        for j in range(len(w) - k + 1 if k else 0):
            windows[k][tuple(w[j : j + k])].add(str(i))
    out = []
    for d, x in docs:
        w = words(x)
        hit, found = [False] * len(w), set()
        for k, held in windows.items():
            for j in range(len(w) - k + 1):
                if s := held.get(tuple(w[j : j + k])):
                    found |= s
                    hit[j : j + k] = [True] * k
        out.append((d, len(w), sum(hit), sorted(found)))
    return out


def jaccard(docs, n=5, percent=80):
    """(doc_id, set size, least id of the component)."""
    sets, parent = {}, {}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for d, x in docs:
        w = spaced((x or "").translate(LOW))
        sets[d] = {tuple(w[j : j + n]) for j in range(len(w) - n + 1)} if len(w) >= n else {tuple(w)} if w else set()
        parent[d] = d
    names = sorted(sets)
    for i, a in enumerate(names):
        for b in names[i + 1 :]:
            common = len(sets[a] & sets[b])
            if common and 100 * common >= percent * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return [(d, len(sets[d]), root(d)) for d in names]


def repeats(docs, window=50):
    """(doc_id, words, removed, kept text)."""
    held = [(d, spaced(x)) for d, x in docs]
    low = {}
    for d, w in sorted(held, key=lambda r: r[0]):
        for j in range(len(w) - window + 1):
            low.setdefault(tuple(w[j : j + window]), d)
    out = []
    for d, w in held:
        gone = [False] * len(w)
        for j in range(len(w) - window + 1):
            if low[tuple(w[j : j + window])] < d:
                gone[j : j + window] = [True] * window
        out.append((d, len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)))
    return out


def fold(d, of):
    return zlib.crc32(str(d).encode()) % of


def discounts(counts):
    def turing(n):
        common = 6 * n[6] / n[1]
        return [1] + [((r + 1) * n[r + 1] / (n[r] * r) - common) / (1 - common) for r in range(1, 6)]

    n = [counts.get(i, 0) for i in range(7)]
    if all(n[1:]) and 6 * n[6] < n[1] and all(0 < x <= 1 for x in turing(n)):
        return turing(n)
    x, y = [math.log(r) for r in range(1, 7)], [math.log(max(n[r], 0.5)) for r in range(1, 7)]
    mx, my = sum(x) / 6, sum(y) / 6
    slope = min(sum((a - mx) * (b - my) for a, b in zip(x, y)) / sum((a - mx) ** 2 for a in x), -1.05)
    return turing([0] + [r**slope for r in range(1, 7)])


def katz(docs, is_train, order=2):
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score), and the model's probability function and words."""
    held = [(d, not is_train(d), [*spaced((x or "").translate(LOW)), None]) for d, x in docs]
    uni, grams = Counter(), [None] + [defaultdict(Counter) for _ in range(1, order)]
    for _, out, w in held:
        if not out:
            uni.update(w)
            marked = [0, *w]
            for k in range(1, order):
                for i in range(k, len(marked)):
                    grams[k][tuple(marked[i - k : i])][marked[i]] += 1
    total, kinds = sum(uni.values()), len(uni)
    by = [discounts(Counter(uni.values()))] + [discounts(Counter(n for f in g.values() for n in f.values())) for g in grams[1:]]
    taken = sum((1 - by[0][k]) * k for k in uni.values() if k <= 5)
    unknown, scale = (taken / total, 1) if total and taken > 0 else (1 / (total + 1), total / (total + 1))

    def prob(context, w):
        if not context:
            return scale * (by[0][uni[w]] if uni[w] <= 5 else 1) * uni[w] / total if w in uni else unknown
        k = len(context)
        if context not in grams[k]:
            return prob(context[1:], w)
        t, s, weight = weights(context)
        n = grams[k][context].get(w)
        return s * (by[k][n] if n <= 5 else 1) * n / t if n else weight * prob(context[1:], w)

    @functools.cache
    def weights(context):
        k = len(context)
        f = grams[k][context]
        t = sum(f.values())
        kept = sum((by[k][n] if n <= 5 else 1) * n for n in f.values())
        share = sum(prob(context[1:], w) for w in f)
        return (t, t / (t + 1), 1 / (t + 1) / (1 - share)) if t - kept <= 1e-9 * t else (t, 1, (t - kept) / t / (1 - share))

    def text(w):
        marked = [0, *w]
        return sum(math.log10(prob(tuple(marked[max(0, i - order + 1) : i]), marked[i])) for i in range(1, len(marked)))

    rows = [(d, out, len(w), sum(x in uni for x in w), total, sum(math.log10((uni[x] + 1) / (total + kinds + 1)) for x in w), text(w)) for d, out, w in held]
    return rows, prob, uni


def chunk_ends(raw, gear, least=8, normal=24, most=96):
    """Ends of content-defined chunks: 6 leading zero bits of the hash of the last 16 bytes up to the normal size, 3 above it."""
    zeros = []
    for i in range(len(raw)):
        h = sum(int(gear[raw[i - j]]) << j for j in range(min(16, i + 1))) & 0xFFFFFFFF
        zeros.append(32 - h.bit_length())
    out, at = [], 0
    while at < len(raw):
        end = min(at + most, len(raw))
        for e in range(at + least, end):
            if zeros[e - 1] >= (6 if e <= at + normal else 3):
                end = e
                break
        out.append(end)
        at = end
    return out


def fingerprint(text, gear):
    """{(digest, length)} of the chunks."""
    raw, at, out = text.encode(), 0, set()
    for e in chunk_ends(raw, gear):
        out.add((hashlib.blake2b(raw[at:e], digest_size=4).hexdigest(), e - at))
        at = e
    return out


def likeness(a, b):
    if a == b:
        return 1.0
    total = lambda s: sum(n for _, n in s)
    return total(a & b) / min(total(a), total(b)) if a and b else 0.0


def fingerprinted(docs, gear):
    """(doc_id, n_chars, digest of the edited text, fingerprint, edited fingerprint, near_edited, near_next)."""
    said = lambda f: "".join(sorted(d + f"{n:02x}" for d, n in f))
    held = sorted(((d, x or "") for d, x in docs), reverse=True)
    marks, out = [fingerprint(x, gear) for _, x in held], []
    for i, (d, x) in enumerate(held):
        k, j = len(x) // 2, (i + 1) % len(held)
        edited = x[: len(x) - k] + held[j][1][:k]
        new = fingerprint(edited, gear)
        out.append((d, len(x), sha(edited), said(marks[i]), said(new), likeness(marks[i], new), likeness(marks[i], marks[j])))
    return sorted(out)


def kneser_ney(samples, order=5):
    """Interpolated Kneser-Ney models of characters, by language: cross-entropy a character of a text under each."""
    import unicodedata

    def letter(c):
        low = c.lower()
        return (low if len(low) == 1 else c) if unicodedata.category(c)[0] == "L" else " "

    def read(text):
        out = [" "]
        for c in map(letter, text):
            if c != " " or out[-1] != " ":
                out.append(c)
        return [" "] * (order - 2) + out

    alphabet = {c for texts in samples.values() for x in texts for c in map(letter, x) if c != " "}
    symbols = lambda text: ["?" if c != " " and c not in alphabet else c for c in read(text)]
    models = {}
    for name, texts in samples.items():
        counts = Counter()
        for x in texts:
            s = symbols(x)
            counts.update(tuple(s[i - order + 1 : i + 1]) for i in range(order - 1, len(s)))
        levels = []
        for _ in range(order):
            once, twice = (sum(v == k for v in counts.values()) for k in (1, 2))
            off, total, kinds = once / (once + 2 * twice) if once else 0.5, Counter(), Counter()
            for g, v in counts.items():
                total[g[:-1]] += v
                kinds[g[:-1]] += 1
            levels.append((counts, off, total, kinds))
            counts = Counter(g[1:] for g in counts)
        models[name] = levels

    def prob(levels, gram):
        p = 1 / (len(alphabet) + 2)
        for k, (counts, off, total, kinds) in enumerate(reversed(levels), 1):
            g = gram[len(gram) - k :]
            if t := total[g[:-1]]:
                p = (max(counts[g] - off, 0) + off * kinds[g[:-1]] * p) / t
        return p

    def bits(text):
        s = symbols(text or "")
        grams = [tuple(s[i - order + 1 : i + 1]) for i in range(order - 1, len(s))]
        return {name: -sum(math.log2(prob(levels, g)) for g in grams) / max(len(grams), 1) for name, levels in models.items()}

    return bits
