"""Plain single-machine versions of the operators, for tests."""

import base64
import hashlib
import re
from collections import Counter, defaultdict

sha = lambda b: hashlib.sha256(b).hexdigest()


def encoder():
    import public_tokenizers as P
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_50k.tiktoken"), "rb"))}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def bpe(texts):
    enc = encoder()
    out = []
    for t in texts:
        ids = enc.encode_ordinary(t or "")
        out.append((len(ids), sha(" ".join(map(str, ids)).encode()), sha((t or "").encode())))
    return out


def rules(text):
    text = text or ""
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    often = Counter(windows)
    hit = {i + j for i, w in enumerate(windows) if often[w] > 1 for j in range(3)}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if re.search(r"[^\x20\x09-\x0D]", line):
            dup += line in seen
            seen.add(line)
    n = len(words)
    return n, sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(hit), n < 50 or 100 * len(hit) > 50 * n


def pieces(text, vocabulary):
    most = max(map(len, vocabulary))
    total = 0
    for word in (text or "").encode().split():
        left, n = "▁" + word.decode(), 0
        while left:
            k = next((k for k in range(min(most, len(left)), 0, -1) if left[:k] in vocabulary), 0)
            if not k:
                n = 1
                break
            left, n = left[k:], n + 1
        total += n
    return total


def personal(text):
    text = text or ""

    def luhn(d):
        return sum(int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4) for i, c in enumerate(reversed(d))) % 10 == 0

    kinds = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m.split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 12 <= len(d := re.sub("[^0-9]", "", m)) <= 19 and luhn(d)),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(re.sub("[^0-9]", "", m)) <= 15),
    }
    spans = []
    for n, (kind, (pattern, ok)) in enumerate(kinds.items()):
        spans += [(m.start(), n, kind, m.end()) for m in re.finditer(pattern, text) if ok(m[0])]
    spans.sort()
    c = Counter(s[2] for s in spans)
    return [c[k] for k in kinds], ",".join(f"{k}:{a}:{b}" for a, _, k, b in spans)


def shingles(text):
    words = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    if not words:
        return frozenset()
    return frozenset(tuple(words[i : i + 5]) for i in range(len(words) - 4)) if len(words) >= 5 else frozenset([tuple(words)])


def groups(rows):
    """rows: (doc_id, text) with distinct ids; doc_id -> (n, component)."""
    sets = {d: shingles(t) for d, t in rows}
    by_set, lead = {}, {}
    for d in sorted(sets):
        lead[d] = by_set.setdefault(sets[d], d) if sets[d] else d
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for d, e in lead.items():
        a, b = root(d), root(e)
        parent[max(a, b)] = min(a, b)
    index = defaultdict(list)
    reps = [d for d in sorted(sets) if sets[d] and lead[d] == d]
    for d in reps:
        count = Counter(e for s in sets[d] for e in index[s])
        for e, both in count.items():
            if 100 * both >= 75 * (len(sets[d]) + len(sets[e]) - both):
                a, b = root(d), root(e)
                parent[max(a, b)] = min(a, b)
        for s in sets[d]:
            index[s].append(d)
    return {d: (len(sets[d]), root(d)) for d in sets}


def contamination(docs, items):
    words = lambda t: re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").encode().lower())
    windows = defaultdict(set)
    for item, text in items:
        w = words(text)
        for i in range(max(1, len(w) - 12) if w else 0):
            windows[tuple(w[i : i + 13])].add(item)
    lengths = sorted({len(w) for w in windows})
    out = []
    for _, text in docs:
        w = words(text)
        hit, found = set(), set()
        for n in lengths:
            for i in range(len(w) - n + 1):
                if own := windows.get(tuple(w[i : i + n])):
                    hit.update(range(i, i + n))
                    found |= own
        out.append((len(w), len(hit), len(found), sha(",".join(sorted(map(str, found))).encode()), len(hit) > 0 and 20 * len(hit) >= len(w)))
    return out


def together(docs, items, span):
    """(doc, item): documents with a run of ``span`` words that holds all terms of an item."""
    words = lambda t: re.findall(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").encode().lower())
    out = set()
    for doc, text in docs:
        w = words(text)
        for item, bag in ((i, set(words(x))) for i, x in items):
            if bag and len(bag) <= span and bag <= set(w) and any(bag <= set(w[i : i + span]) for i in range(max(1, len(w)))):
                out.add((doc, item))
    return out


def repeats(rows, length=50):
    """rows: (doc_id, text), distinct ids; doc_id -> (n_bytes, n_removed, n_spans, sha)."""
    least = {}
    data = sorted((d, (t or "").encode()) for d, t in rows)
    out = {}
    for d, b in data:
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            s = b[i : i + length]
            if least.setdefault(s, d) < d:
                gone[i : i + length] = b"\x01" * length
        spans = len(re.findall(b"\x01+", bytes(gone)))
        out[d] = (len(b), sum(gone), spans, sha(bytes(x for x, g in zip(b, gone) if not g)))
    return out
