"""Plain versions of the operators: loops over texts, no hashes, no Spark."""

import collections
import re

BLANK = " \t\n\r\x0b\x0c"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


# -- line dedup -----------------------------------------------------------------


def line_records(text):
    """[(tokens with byte-free positions, whole line)] of a text without scripts
    that lack blanks: lists of (start, end, word)."""
    words = [(m.start(), m.end(), lower(m[0])) for m in re.finditer(r"[^\x20\x09-\x0D]+", text or "")]
    out, one, whole = [], [], True
    for i, w in enumerate(words):
        if one:
            broken = "\n" in text[one[-1][1] : w[0]]
            if broken or text[one[-1][1] - 1] in "!.?":
                out.append((one, whole and broken))
                one, whole = [], broken
        one.append(w)
    if one:
        out.append((one, whole))
    return words, out


def line_dedup(rows, needs):
    """id -> (text, records, dropped); rows: distinct ids, texts."""
    templates, runs, parsed = collections.defaultdict(list), collections.defaultdict(list), {}
    for doc, text in rows:
        words, recs = line_records(text)
        parsed[doc] = words, recs
        place, masked = [], []
        at = 0
        for tokens, whole in recs:
            m = len(tokens)
            field = [any(c in "0123456789" for c in w) for _, _, w in tokens]
            mask = tuple("*" if f and 2 * sum(field) <= m else w for f, (_, _, w) in zip(field, tokens))
            place.append((at, at + m))
            masked.append(mask)
            if m >= needs.min_tokens:
                templates[("all", mask)].append((doc, at, at + m, needs.min_docs if m >= needs.long_tokens else needs.short_docs))
            if whole and m >= max(needs.merge_tokens, 4) and 4 * sum(field) <= m - 2:
                tail = mask[2:]
                half = (len(tail) + 1) // 2
                for kind, part in (("first", tail[:half]), ("second", tail[half:]), ("even", tail[::2]), ("odd", tail[1::2])):
                    templates[(kind, m, mask[:2], part)].append((doc, at, at + m, needs.merge_docs))
            at += m
        groups = set()
        for i, (a, b) in enumerate(place):
            if b - a < needs.long_tokens:
                for step in (1, -1):
                    j = i
                    while 0 <= j < len(place) and abs((place[j][1] if step > 0 else place[j][0]) - (a if step > 0 else b)) < needs.long_tokens:
                        j += step
                    if 0 <= j < len(place):
                        groups.add((min(i, j), max(i, j)))
        for i, j in groups:
            flat = tuple(x for mask in masked[i : j + 1] for x in mask)
            templates[("group", flat)].append((doc, place[i][0], place[j][1], needs.min_docs))
        for i in range(len(words) - needs.run_tokens + 1):
            runs[tuple(w for _, _, w in words[i : i + needs.run_tokens])].append((doc, i))
    order = lambda d: (d is None, d)
    gone = collections.defaultdict(set)
    for found in templates.values():
        have = {d for d, *_ in found}
        # a null id never is the smallest one beside others
        if len(have) >= max(x[3] for x in found):
            keeper = min(have, key=order)
            for d, a, b, _ in found:
                if d != keeper:
                    gone[d] |= set(range(a, b))
    before = {d: set(g) for d, g in gone.items()}
    for found in runs.values():
        found = [(d, i) for d, i in found if not set(range(i, i + needs.run_tokens)) <= before.get(d, set())]
        have = {d for d, _ in found}
        if len(have) >= max(needs.min_docs, 2):
            keeper = min(have, key=order)
            for d, i in found:
                if d != keeper:
                    gone[d] |= set(range(i, i + needs.run_tokens))
    out = {}
    for doc, text in rows:
        words, recs = parsed[doc]
        keep = [i not in gone[doc] for i in range(len(words))]
        at, lost = 0, 0
        for tokens, _ in recs:
            lost += not any(keep[at : at + len(tokens)])
            at += len(tokens)
        out[doc] = (None if text is None else [w for k, (_, _, w) in zip(keep, words) if k], len(recs), lost)
    return out


# -- sets ----------------------------------------------------------------------


def shingle_sets(rows, k):
    out = {}
    for doc, text in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", lower(text))
        out[doc] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()
    return out


def components(sets, num, den):
    root = {i: i for i in sets}
    for x in sorted(sets):
        for y in sorted(sets):
            if x < y and sets[x] and sets[y] and den * len(sets[x] & sets[y]) >= num * len(sets[x] | sets[y]) and root[x] != root[y]:
                lo, hi = sorted((root[x], root[y]))
                root = {k: lo if v == hi else v for k, v in root.items()}
    return root


# -- benchmark windows ------------------------------------------------------------


def alnum_words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))


def contaminated(text, items, window=10):
    """(words, hit words, item ids)."""
    w, hit, named = alnum_words(text), set(), set()
    for item, other in items:
        o = alnum_words(other)
        m = min(len(o), window)
        if not m or item is None:
            continue
        wins = {tuple(o[i : i + m]) for i in range(len(o) - m + 1)}
        for i in range(len(w) - m + 1):
            if tuple(w[i : i + m]) in wins:
                hit |= set(range(i, i + m))
                named.add(str(item))
    return len(w), len(hit), sorted(named)


# -- secrets ----------------------------------------------------------------------


def base_secrets(text):
    """[(start, kind number, end)], by the contract's patterns."""
    text = text or ""
    out = []
    for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", text, re.I | re.A):
        if len(m[2]) >= 8:
            out.append((m.start(), 0, m.end()))
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", text) if m.end() - m.start() >= 16]
    out += [(m.start(), 2, m.end()) for m in re.finditer(r"[0-9a-f]+", text) if m.end() - m.start() >= 32]
    return sorted(out)
