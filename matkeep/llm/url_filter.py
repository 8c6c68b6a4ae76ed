"""URL filter: a bit-parallel wildcard automaton over all rules at once.

Every glob rule becomes a stretch of bits in a row of 64-bit words: one bit for each literal or single-character
wildcard, plus, for a run wildcard, the bit before it loops on itself. Reading a character shifts every pattern's
active bits by one and masks them by the character's table (Shift-And), so one pass over a URL simulates all rules.
A block of URLs is advanced together, character position by character position, in NumPy.

Glob language, matched against the whole of ``.host/path?query`` of the canonical address: ``*`` a run without ``/``, ``**`` any run,
``?`` one character other than ``/``. Matching is on UTF-8 bytes.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

#: The site rules asked for, (verdict, host, path).
SITE_RULES = (
    ("block", "net", "/"),
    ("allow", "example.net", "/en/"),
    ("block", "example.com", "/de/"),
    ("allow", "org", "/fr/"),
)

#: Default globs for addresses no site rule fits; a match blocks. Feeds, logins, carts, binaries, session ids.
BLOCK_GLOBS = (
    "**/login", "**/login/**", "**/signin**", "**/cart", "**/cart/**", "**/checkout**", "**/wp-admin/**",
    "**.exe", "**.zip", "**.tar.gz", "**.dmg", "**.apk", "**.iso", "**.jpg", "**.png", "**.gif", "**.mp4", "**.mp3",
    r"**\?**sessionid=**", r"**\?**phpsessid=**", r"**;jsessionid=**", ".casino*.**", "*.casino.*/**", "*.porn*.*/**",
    ".ads.*/**", "*.ads.*/**", ".tracker.*/**", "*.doubleclick.net/**", "**/print/????/**",
)

#: At most so many bytes of padded URL text are advanced together.
BLOCK_BYTES = 8 << 20

SCHEMA = "page_id long, host string, path string, rule string, verdict string, matched_globs array<string>"


@dataclass
class WildcardAutomaton:
    """Shift-And masks of many globs.

    Each pattern owns a start bit, which is active before any character, and one bit for each literal or ``?``.
    """

    globs: list[str]
    words: int = 0
    step: np.ndarray = field(default=None, repr=False)
    loop: np.ndarray = field(default=None, repr=False)
    start: np.ndarray = field(default=None, repr=False)
    last: list[int] = field(default_factory=list)

    def __post_init__(self) -> None:
        slash = ord("/")
        step_bits = [0] * 256
        loop_bits = [0] * 256
        start, at = 0, 0
        for glob in self.globs:
            start |= 1 << at
            for kind, byte in _tokens(glob):
                if kind == "run":
                    for b in range(256):
                        loop_bits[b] |= 1 << at
                elif kind == "part":
                    for b in range(256):
                        loop_bits[b] |= (b != slash) << at
                else:
                    at += 1
                    for b in range(256) if kind == "one" else (byte,):
                        step_bits[b] |= (kind == "literal" or b != slash) << at
            self.last.append(at)
            at += 1
        self.words = max(1, -(-at // 64))
        self.step, self.loop = self._table(step_bits), self._table(loop_bits)
        self.start = self._table([start])[0]

    def _table(self, rows: list[int]) -> np.ndarray:
        mask = (1 << 64) - 1
        return np.array([[(r >> (64 * w)) & mask for w in range(self.words)] for r in rows], dtype=np.uint64)

    def matches(self, texts: list[bytes]) -> np.ndarray:
        """Boolean matrix, text by glob."""
        out = np.zeros((len(texts), len(self.globs)), dtype=bool)
        sizes = np.array([len(t) for t in texts], dtype=np.int64)
        order = np.argsort(sizes, kind="stable")
        at = 0
        while at < len(order):
            end = at + 1
            while end < len(order) and (end + 1 - at) * max(1, sizes[order[end]]) <= BLOCK_BYTES:
                end += 1
            out[order[at:end]] = self._advance([texts[i] for i in order[at:end]], sizes[order[at:end]])
            at = end
        return out

    def _advance(self, texts: list[bytes], sizes: np.ndarray) -> np.ndarray:
        """``texts`` in ascending length: those that have ended are a prefix, whose states stay as they are."""
        state = np.repeat(self.start[None, :], len(texts), axis=0)
        if sizes[-1]:
            chars = np.zeros((len(texts), int(sizes[-1])), dtype=np.uint8)
            inside = np.arange(int(sizes[-1]))[None, :] < sizes[:, None]
            chars[inside] = np.frombuffer(b"".join(texts), dtype=np.uint8)
            one, top = np.uint64(1), np.uint64(63)
            live = np.searchsorted(sizes, np.arange(int(sizes[-1])), side="right")
            for j in range(int(sizes[-1])):
                s = state[live[j] :]
                moved = s << one
                moved[:, 1:] |= s[:, :-1] >> top
                byte = chars[live[j] :, j]
                state[live[j] :] = (moved & self.step[byte]) | (s & self.loop[byte])
        bits = np.array(self.last, dtype=np.uint64)
        return ((state[:, bits >> np.uint64(6)] >> (bits & np.uint64(63))) & np.uint64(1)).astype(bool)


def _tokens(glob: str) -> Iterator[tuple[str, int]]:
    raw, at = glob.encode(), 0
    while at < len(raw):
        if raw[at : at + 2] == b"**":
            yield "run", 0
            at += 2
        elif raw[at : at + 1] == b"*":
            yield "part", 0
            at += 1
        elif raw[at : at + 1] == b"?":
            yield "one", 0
            at += 1
        elif raw[at : at + 1] == b"\\" and at + 1 < len(raw):
            yield "literal", raw[at + 1]
            at += 2
        else:
            yield "literal", raw[at]
            at += 1


def split_url(url: str | None) -> tuple[str, str, str]:
    """Host with A-Z lower-cased, path, and what follows the path."""
    _, found, rest = (url or "").partition("://")
    if not found:
        return "", "", ""
    end = next((i for i, c in enumerate(rest) if c in "/?#"), len(rest))
    host, rest = rest[:end], rest[end:]
    cut = next((i for i, c in enumerate(rest) if c in "?#"), len(rest))
    return host.translate(_LOWER), rest[:cut], rest[cut:]


_LOWER = {c: c + 32 for c in range(65, 91)}
#: Ports that go without saying, and characters whose percent codes mean themselves.
PORTS = (("http", "80"), ("https", "443"))
UNRESERVED = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789-._~"
_CODED = re.compile("%(" + "|".join(f"{ord(c):02X}" for c in UNRESERVED) + ")", re.IGNORECASE)


def canonical(url: str | None) -> str:
    """What globs match: ``host/path?query``.

    Without user name, default port and fragment; percent codes of unreserved characters resolved in path and query,
    and dot segments in the path. Empty for an address without ``://``.
    """
    host, path, rest = split_url(url)
    if not (host or path or rest):
        return ""
    scheme = url.partition("://")[0].translate(_LOWER)
    host = host.rpartition("@")[2]
    for name, port in PORTS:
        if scheme == name:
            host = host.removesuffix(f":{port}")
    decode = lambda x: _CODED.sub(lambda m: chr(int(m[1], 16)), x)
    parts: list[str] = []
    for segment in (segments := decode(path).split("/")):
        if segment == "..":
            del parts[max(1, len(parts) - 1) :]
        elif segment != ".":
            parts.append(segment)
    if segments[-1] in (".", ".."):
        parts.append("")
    return host + "/".join(parts) + decode(rest.partition("#")[0])


def judge_urls(pages: DataFrame, site_rules=SITE_RULES, block_globs=BLOCK_GLOBS) -> DataFrame:
    """page_id, host, path, rule, verdict and the default globs that match.

    A site rule fits its host and all subdomains where the path starts with the rule's path; the longest fitting rule
    wins and names the verdict. Otherwise a matching default glob blocks, else the page is allowed. A null url or one
    without ``://`` has an empty host and path, fits nothing and is allowed. Globs are asked of the canonical address, host
and path are those of the address as it stands. Only page_id and url are read.
    """
    longest = sorted(site_rules, key=lambda r: len(r[1] + r[2]), reverse=True)
    # Site rules are of the address as it stands, anchored at a label of the host; default globs of the canonical one.
    globs = [f"**.{host}{path}**" for _, host, path in longest]
    names = [f"{host}{path}" for _, host, path in longest]
    verdicts = [v for v, _, _ in longest]

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        automaton, defaults = WildcardAutomaton(globs), WildcardAutomaton(list(block_globs))
        hosts_only = WildcardAutomaton([f"**.{host}" for _, host, _ in longest])
        for batch in batches:
            parts = [split_url(u) for u in batch.column(1).to_pylist()]
            # A rule's dot may also stand in the path, so its host part is asked of the host alone.
            at_host = hosts_only.matches([f".{h}".encode() for h, _, _ in parts])
            at_path = automaton.matches([f".{h}{p}".encode() if h or p else b"" for h, p, _ in parts])
            globbed = defaults.matches([f".{u}".encode() if u else b"" for u in map(canonical, batch.column(1).to_pylist())])
            rule, verdict, matched = [], [], []
            for row, (_, path, _) in enumerate(parts):
                fits = [i for i in np.flatnonzero(at_path[row] & at_host[row]) if path.startswith(longest[i][2])]
                found = [block_globs[i] for i in np.flatnonzero(globbed[row])]
                rule.append(names[fits[0]] if fits else None)
                verdict.append(verdicts[fits[0]] if fits else "block" if found else "allow")
                matched.append(found)
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0).cast(pa.int64()),
                    pa.array([h for h, _, _ in parts], pa.string()),
                    pa.array([p for _, p, _ in parts], pa.string()),
                    pa.array(rule, pa.string()),
                    pa.array(verdict, pa.string()),
                    pa.array(matched, pa.list_(pa.string())),
                ],
                names=["page_id", "host", "path", "rule", "verdict", "matched_globs"],
            )

    return pages.select("page_id", "url").mapInArrow(judge, SCHEMA)
