"""Plain single-machine versions of the operators' contracts, and the texts they are tried on."""

import hashlib
import random
import re

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def sha(x):
    return hashlib.sha256(x if isinstance(x, bytes) else x.encode()).hexdigest()


def thue_morse(n=1024, a="a", b="b"):
    """The sequence and its complement: equal under every hash that sums powers modulo a power of two."""
    bits = [bin(i).count("1") & 1 for i in range(n)]
    return "".join((a, b)[x] for x in bits), "".join((b, a)[x] for x in bits)


def sample_texts(seed=1, n=60):
    """(doc_id, text) with shared passages, near and exact copies, nulls, empties, ties and odd characters."""
    r = random.Random(seed)
    words = ["".join(r.choice("abcdeé") for _ in range(r.randint(1, 5))) for _ in range(150)]
    prose = lambda k: " ".join(r.choice(words) for _ in range(k))
    passages = [prose(45) for _ in range(4)]
    lines = [prose(8).capitalize() + "." for _ in range(5)]
    out = [(0, None), (1, ""), (2, " \n\t\n"), (3, "x"), (4, "a\0b " * 60), (5, "ab" * 400)]
    for i in range(6, n):
        parts = [prose(r.randint(1, 60)) for _ in range(r.randint(1, 4))]
        if r.random() < 0.5:
            parts.insert(r.randint(0, len(parts)), r.choice(passages))
        if r.random() < 0.5:
            parts.insert(r.randint(0, len(parts)), r.choice(["", "  ", "\t"]) + r.choice(lines) + r.choice(["", " \r"]))
        text = r.choice(["\n", " ", "\n\n"]).join(parts)
        if r.random() < 0.25 and i > 10:
            base = next((t for _, t in reversed(out) if t and len(t) > 200), text).split(" ")
            for _ in range(r.choice([0, 1, 1, 2])):
                base[r.randrange(len(base))] = r.choice(words)
            text = " ".join(base)
        out.append((i, text))
    s, t = thue_morse()
    twelve = "one two three four five six seven eight nine ten eleven twelve "
    structured = [s, s, t, t, t, twelve + s, twelve + t, f"{s}\n{t}", f"{t}\n{s}", "a" * 700, "a" * 701, "ab" * 350, "ba" * 350, "abc " * 90, "bca " * 90, "abc\n" * 90]
    structured += [" ".join(thue_morse(256, "x", "y")[i]) for i in (0, 1, 0)]
    return out + [(1000 + i, x) for i, x in enumerate(structured)]


def lines(rows, min_chars=20, min_docs=3):
    split = {d: (t or "").split("\n") for d, t in rows}
    key = lambda x: x.strip("\x20\x09\x0a\x0b\x0c\x0d").translate(LOWER)
    holders = {}
    for d, ls in split.items():
        for x in ls:
            holders.setdefault(key(x), set()).add(d)
    out = {}
    for d, ls in split.items():
        kept = [x for x in ls if not (len(key(x)) >= min_chars and len(holders[key(x)]) >= min_docs and max(holders[key(x)]) != d)]
        out[d] = (len(ls), len(ls) - len(kept), sha("\n".join(kept)))
    return out


def substrings(rows, length=100):
    seen, out = set(), {}
    for d, t in sorted(rows):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if (w := b[i : i + length]) in seen:
                gone[i : i + length] = b"\1" * length
            seen.add(w)
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[d] = (len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), sha(kept))
    return out


def windows(rows, size=13):
    seen, out = set(), {}
    for d, t in sorted(rows):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        gone, own = [False] * len(w), set()
        for i in range(len(w) - size + 1):
            own.add(x := tuple(w[i : i + size]))
            if x in seen:
                gone[i : i + size] = [True] * size
        seen |= own
        out[d] = (len(w), sum(gone), sha(" ".join(x for x, g in zip(w, gone) if not g)))
    return out


def jaccard_components(rows, size=4, percent=85):
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER))
        sets[d] = {tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: (len(sets[d]), find(d)) for d in sets}


def contaminated(rows, items, size=13):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    windows_ = {}
    for k, t in items:
        w = words(t)
        for i in range(max(1, len(w) - size + 1)) if w else ():
            windows_.setdefault(tuple(w[i : i + size]), set()).add(k)
    out = {}
    for d, t in rows:
        w, hit, found = words(t), set(), set()
        for n in {len(x) for x in windows_}:
            for i in range(len(w) - n + 1):
                if (x := tuple(w[i : i + n])) in windows_:
                    found |= windows_[x]
                    hit |= set(range(i, i + n))
        out[d] = (len(w), len(hit), len(found), sha(",".join(sorted(map(str, found)))), bool(hit) and 20 * len(hit) >= len(w))
    return out
