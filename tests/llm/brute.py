"""Plain versions of what the queries return, to hold the operators against."""

import hashlib
import re
from collections import Counter

W = re.compile(r"[^\x20\x09-\x0D]+")


def line_base(text):
    text = text or ""
    ws = W.findall(text)
    lines = [x for x in text.split("\n") if W.search(x)]
    c = Counter(tuple(ws[i : i + 5]) for i in range(len(ws) - 4))
    hit = {i + k for i in range(len(ws) - 4) if c[tuple(ws[i : i + 5])] > 1 for k in range(5)}
    n_words, rep = len(ws), len(hit)
    return n_words, sum(map(len, ws)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), rep, n_words < 10 or 100 * rep > 20 * n_words


def luhn(d):
    total = 0
    for i, c in enumerate(reversed(d)):
        v = int(c) * (1 + i % 2)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


PII = {
    "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
    "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(p) <= 255 for p in m.split("."))),
    "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 12 <= len(d := re.sub("[^0-9]", "", m)) <= 19 and luhn(d)),
    "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(re.sub("[^0-9]", "", m)) <= 15),
}


def pii_base(text):
    found, counts = [], []
    for k, (kind, (p, ok)) in enumerate(PII.items()):
        own = [(m.start(), k, m.end(), kind) for m in re.finditer(p, text or "") if ok(m.group())]
        counts.append(len(own))
        found += own
    joined = ",".join(f"{kind}:{s}:{e}" for s, _, e, kind in sorted(found))
    return (*counts, hashlib.sha256(joined.encode()).hexdigest()), {f"{kind}:{s}:{e}" for s, _, e, kind in found}


def license_base(text):
    low = re.sub("[A-Z]", lambda m: m.group().lower(), text or "")
    ws = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    at, labels = [], set()
    for phrase, label in {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}.items():
        p = phrase.split()
        for i in range(len(ws)):
            if ws[i : i + len(p)] == p:
                at.append(i)
                labels.add(label)
    return len(ws), len(at), min(at, default=None), max(at, default=None), ",".join(sorted(labels))


def passages(rows, n=100):
    """doc_id -> n_bytes, n_removed, n_spans, kept_sha256, for (doc_id, text) rows."""
    seen, out = set(), {}
    for doc_id, text in sorted((d, t or "") for d, t in rows if d is not None):
        b = text.encode()
        gone = bytearray(len(b))
        for i in range(len(b) - n + 1):
            w = b[i : i + n]
            if w in seen:
                gone[i : i + n] = b"\1" * n
            else:
                seen.add(w)
        kept = bytes(x for x, g in zip(b, gone) if not g)
        out[doc_id] = len(b), sum(gone), len(re.findall(b"\1+", bytes(gone))), hashlib.sha256(kept).hexdigest()
    return out
