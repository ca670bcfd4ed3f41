"""Code that runs in Python workers. Pickled by value, so executors need no copy of the package."""

from __future__ import annotations

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])


# --- WARC -----------------------------------------------------------------------------------------------------


#: Bytes that no header holds.
CONTROL = bytes(x for x in range(32) if x not in b"\t\n\r") + b"\x7f"
#: Control characters of a url, as they are written to a header.
ESCAPED = {x: f"%{x:02X}" for x in (*range(32), 127)}
#: A record that claims more content than this, or has a longer header, fails its check: what a reader holds is bounded by it.
MOST_RECORD = 1 << 28


def record_bytes(page_id, uri, payload, digest, size, kind, refers_to) -> bytes:
    """One WARC record, not compressed."""
    import base64
    import hashlib
    import uuid

    rid = lambda n: f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{n}')}>"
    body = b"" if payload is None else bytes(payload)
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
    block = http if kind == "revisit" else http + body
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {rid(page_id)}", "WARC-Date: 2000-01-01T00:00:00Z", "WARC-Target-URI: " + (uri or "about:blank").translate(ESCAPED), "Content-Type: application/http; msgtype=response"]
    head += [f"WARC-Payload-Digest: sha1:{base64.b32encode(bytes.fromhex(digest)).decode()}", f"X-Payload-Length: {size}"]
    head += [f"WARC-Block-Digest: sha1:{base64.b32encode(hashlib.sha1(block).digest()).decode()}"]
    head += [] if page_id is None else [f"X-Page-Id: {page_id}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {rid(refers_to)}", f"X-Refers-To-Page: {refers_to}"]
    head += [f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def archive_writer(folder: str, roll_bytes: int):
    def write(batches):
        import gzip
        import uuid

        import pandas as pd
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(folder)
        system.create_dir(root, recursive=True)
        out = path = None
        done = []
        for batch in batches:
            for row in batch.itertuples(index=False):
                if out is None:
                    name = f"part-{uuid.uuid4().hex}.warc.gz"
                    path, out, n, size = f"{root}/{name}", system.open_output_stream(f"{root}/{name}", compression=None), 0, 0
                page, refers = row.page_id or None, row.refers_to or None  # as texts: a column of numbers with nulls would be rounded
                member = gzip.compress(record_bytes(page, row.uri, row.payload, row.digest, int(row.bytes), row.record_type, refers), 4, mtime=0)
                out.write(member)
                n, size = n + 1, size + len(member)
                if size >= roll_bytes:
                    out.close()
                    done.append((f"{folder}/{name}", n, size))
                    out = None
        if out is not None:
            out.close()
            done.append((f"{folder}/{name}", n, size))
        yield pd.DataFrame(done, columns=["path", "records", "bytes"])

    return write


class Source:
    """A window on a stream that only moves forward, with as many bytes ahead as are asked for."""

    def __init__(self, stream, block: int):
        self.stream, self.block, self.base, self.data, self.pos, self.ended = stream, block, 0, b"", 0, False

    @property
    def offset(self) -> int:
        return self.base + self.pos

    def ahead(self, n: int) -> bool:
        """Whether n bytes are there, after reading on if need be."""
        while len(self.data) - self.pos < n and not self.ended:
            more = self.stream.read(max(self.block, n - len(self.data) + self.pos))
            self.ended = not more
            self.base, self.data, self.pos = self.base + self.pos, self.data[self.pos :] + more, 0
        return len(self.data) - self.pos >= n

    def peek(self, at: int, n: int) -> bytes:
        self.ahead(at + n)
        return self.data[self.pos + at : self.pos + at + n]


def parse_header(raw: bytes) -> tuple[dict, int, int]:
    """Fields of the header at the start of raw, where its content begins, and the content's length.

    Raises ValueError, or EOFError if all of raw is sound but the header goes on beyond it.
    """
    if raw[:7] != b"WARC/1." or not raw[7:8].isdigit() or raw[8:10] != b"\r\n":
        raise ValueError("no version line")
    end = raw.find(b"\r\n\r\n", 0, MOST_RECORD)
    head = raw[:end] if end >= 0 else raw[:MOST_RECORD]
    if head.translate(None, CONTROL) != head:
        raise ValueError("control characters in the header")
    if end < 0:  # whole lines are checked before more is read, so that junk is left soon
        head = head[: head.rfind(b"\r\n")]
    fields = {}
    for line in head.decode("utf-8", "replace").split("\r\n")[1:]:
        name, colon, value = line.partition(":")
        if not colon:
            raise ValueError("malformed header line")
        name = name.strip().lower()
        if name in fields and name != "warc-concurrent-to":
            raise ValueError("field given twice")  # a cut header goes on as the next record's
        fields[name] = value.strip()
    if end < 0:
        raise EOFError("header without an end") if len(raw) < MOST_RECORD else ValueError("header beyond the limit")
    if not fields.get("content-length", "").isdigit():
        raise ValueError("no content length")
    size = int(fields["content-length"])
    if size > MOST_RECORD:
        raise ValueError("content length beyond the limit")
    return fields, end + 4, size


def checked(fields: dict, block: bytes) -> dict:
    """fields with the digest and the payload. Raises ValueError if a digest differs."""
    import base64
    import hashlib

    payload = block.partition(b"\r\n\r\n")[2] if "msgtype=" in fields.get("content-type", "") else block
    given = fields.get("warc-payload-digest", "")
    digest = hashlib.sha1(payload).hexdigest()
    whole = fields.get("warc-block-digest", "")
    if whole.startswith("sha1:") and whole[5:] != base64.b32encode(hashlib.sha1(block).digest()).decode():
        raise ValueError("block digest differs")
    if given.startswith("sha1:"):
        try:
            told = base64.b32decode(given[5:]).hex()
        except ValueError:
            raise ValueError("malformed digest") from None
        if fields.get("warc-type") != "revisit" and told != digest:
            raise ValueError("digest differs")
        digest = told
    fields["digest"], fields["payload"] = digest, payload
    return fields


def member_at(src: Source) -> tuple[bytes, int]:
    """The inflated gzip member at the start of the window, and its length in the file. Raises ValueError."""
    import zlib

    inflate, at, out, size = zlib.decompressobj(31), 0, [], 0
    while not inflate.eof:
        chunk = src.peek(at, 1 << 14)
        if not chunk:
            raise ValueError("member is cut short")
        try:
            out.append(inflate.decompress(chunk))
        except zlib.error as e:
            raise ValueError(f"member does not inflate: {e}") from None
        if at == 0 and not b"WARC/1.".startswith(out[0][:7]):
            raise ValueError("no version line")
        at, size = at + len(chunk), size + len(out[-1])
        if size > MOST_RECORD + (1 << 24):
            raise ValueError("member beyond the limit")
    return b"".join(out), at - len(inflate.unused_data)


CLOSING = b"\r\n\r\n"


def record_at(src: Source) -> tuple[dict, int]:
    """The record at the start of the window (gzip member or plain), and its length in the file. Raises ValueError."""
    if src.peek(0, 2) == b"\x1f\x8b":
        raw, used = member_at(src)
        try:
            fields, at, size = parse_header(raw)
        except EOFError as e:
            raise ValueError(str(e)) from None
        if len(raw) != at + size + 4 or raw[-4:] != CLOSING:
            raise ValueError("member holds less or more than its record")
        return checked(fields, raw[at : at + size]), used
    want = 1 << 16
    while True:
        raw = src.peek(0, want)
        try:
            fields, at, size = parse_header(raw)
            break
        except EOFError as e:
            if len(raw) < want:
                raise ValueError(str(e)) from None
            want *= 2
    if src.peek(at + size, 4) != CLOSING:  # before the content is taken out of the window
        raise ValueError("no closing lines")
    return checked(fields, src.peek(at, size)), at + size + 4


def salvage(stream, block: int):
    """Yields ("record", offset, fields) and ("gap", offset, bytes, reason) in file order."""
    import re

    src, gap, why = Source(stream, block), None, ""
    mark = re.compile(rb"\x1f\x8b\x08|WARC/1\.")
    while src.ahead(1):
        try:
            fields, used = record_at(src)
        except ValueError as e:
            if gap is None:
                gap, why = src.offset, str(e)
            src.pos += 1
            while (hit := mark.search(src.data, src.pos)) is None:
                src.pos = max(src.pos, len(src.data) - 6)
                if not src.ahead(len(src.data) - src.pos + 1):
                    src.pos = len(src.data)
                    break
            if hit:
                src.pos = hit.start()
            continue
        if gap is not None:
            yield "gap", gap, src.offset - gap, why
            gap = None
        yield "record", src.offset, fields
        src.pos += used
    if gap is not None:
        yield "gap", gap, src.offset - gap, why


def archive_reader(payloads: bool, block: int):
    def rows(path):
        from pyarrow import fs

        number = lambda x: int(x) if (x or "").lstrip("-").isdigit() else None
        system, at = fs.FileSystem.from_uri(path)
        with system.open_input_stream(at, compression=None) as stream:
            for item in salvage(stream, block):
                if item[0] == "gap":
                    yield (path, item[1], "gap", item[3], item[2], *[None] * 8), 0
                else:
                    f = item[2]
                    size = number(f.get("x-payload-length")) if f.get("warc-type") == "revisit" else len(f["payload"])
                    held = f["payload"] if payloads else None
                    yield (path, item[1], "record", None, None, f.get("warc-type"), f.get("warc-record-id"), f.get("warc-target-uri"), number(f.get("x-page-id")), number(f.get("x-refers-to-page")), size, f["digest"], held), len(held or b"")

    def read(batches):
        import pandas as pd

        names = ["path", "offset", "status", "reason", "gap_bytes", "record_type", "record_id", "uri", "page_id", "refers_to", "payload_bytes", "payload_digest", "payload"]

        def frame(some):
            df = pd.DataFrame(some, columns=names, dtype=object)
            return df.astype({c: "Int64" for c in ("offset", "gap_bytes", "page_id", "refers_to", "payload_bytes")})

        some, held = [], 0
        for batch in batches:
            for path in batch["path"]:
                for row, size in rows(path):
                    some.append(row)
                    held += size
                    if len(some) >= 2000 or held >= 8 << 20:
                        yield frame(some)
                        some, held = [], 0
        if some:
            yield frame(some)

    return read


# --- words ----------------------------------------------------------------------------------------------------

WORD = r"\w+"


def mixed(x):
    """A 64-bit mix of unsigned 64-bit values."""
    import numpy as np

    x = (x ^ (x >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return x ^ (x >> np.uint64(29))


def word_hasher(most: int = 100_000):
    """list of words -> uint64 hashes, with a table of words seen that is emptied when it is full."""
    import numpy as np
    import xxhash

    table: dict[str, int] = {}

    def hashes(words):
        try:
            return np.fromiter(map(table.__getitem__, words), np.uint64, len(words))
        except KeyError:
            if len(table) > most:
                table.clear()
            for w in set(words):
                if w not in table:
                    table[w] = xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"))
            return np.fromiter(map(table.__getitem__, words), np.uint64, len(words))

    return hashes


# --- toxicity -------------------------------------------------------------------------------------------------


def gram_hashes(h, bits: int, skip: int):
    """Distinct feature numbers of a text's word hashes: words, pairs, and pairs with up to skip words between."""
    import numpy as np

    parts = [mixed(h)]
    parts += [mixed(h[:-d] * np.uint64(0x100000001B3) + mixed(h[d:]) + np.uint64(min(d, 2))) for d in range(1, skip + 2) if len(h) > d]
    return np.unique((np.concatenate(parts) >> np.uint64(64 - bits)).astype(np.uint32))


def gram_rows(bits: int, skip: int):
    """(label, text) batches -> label and the text's features, as the bytes of 32-bit numbers."""

    def run(batches):
        import re

        import pandas as pd

        words, hashes = re.compile(WORD).findall, word_hasher()
        for batch in batches:
            grams = [gram_hashes(hashes(words((t or "").lower())), bits, skip).tobytes() for t in batch["text"]]
            yield pd.DataFrame({"label": batch["label"], "grams": grams})

    return run


def ftrl(rows: list, bits: int, alpha: float, beta: float, l1: float, l2: float, epochs: int, seed: int, positive: float = 1.0):
    """FTRL-proximal logistic regression over binary features: (weights at non-zero coordinates, bias)."""
    import numpy as np

    rng = np.random.default_rng(seed)
    z, n = np.zeros((1 << bits) + 1), np.zeros((1 << bits) + 1)
    bias = 1 << bits

    def weight(i):
        w = -(z[i] - np.sign(z[i]) * l1) / ((beta + np.sqrt(n[i])) / alpha + l2)
        return np.where(np.abs(z[i]) <= l1, 0.0, w)

    for _ in range(epochs):
        for k in rng.permutation(len(rows)):
            y, grams = rows[k]
            i = np.append(grams, bias)
            w = weight(i)
            g = (1 / (1 + np.exp(-np.clip(w.sum(), -35, 35))) - y) * (positive if y else 1.0)
            root = np.sqrt(n[i])
            z[i] += g - (np.sqrt(n[i] + g * g) - root) / alpha * w
            n[i] += g * g
    at = np.flatnonzero(np.abs(z[:-1]) > l1)
    return at.astype(np.uint32), weight(at), float(weight(np.array([bias]))[0])


def ftrl_rows(*settings):
    """Batches of label and features, all in one task -> one row of the fitted weights; none without rows. Order plays no part."""
    fit = ftrl

    def run(batches):
        import numpy as np
        import pandas as pd

        rows = sorted((int(y), g) for batch in batches for y, g in zip(batch["label"], batch["grams"], strict=True))
        if rows:
            at, weights, bias = fit([(y, np.frombuffer(g, np.uint32)) for y, g in rows], *settings)
            yield pd.DataFrame({"at": [at.tobytes()], "weights": [weights.tobytes()], "bias": [bias]})

    return run


def gram_scorer(at, weights, bias: float, bits: int, skip: int):
    """Texts -> probabilities under the sparse weights."""
    import numpy as np

    state = {}

    def score(texts):
        import re

        import pandas as pd

        if not state:
            state.update(words=re.compile(WORD).findall, hashes=word_hasher(), dense=np.zeros(1 << bits, np.float32))
            state["dense"][at] = weights
        dense = state["dense"]
        out = np.empty(len(texts))
        for k, t in enumerate(texts):
            h = state["hashes"](state["words"]((t or "").lower()))
            shift, total, own = np.uint64(64 - bits), 0.0, []
            for d in range(skip + 2):
                if len(h) <= d:
                    break
                x = mixed(h) if d == 0 else mixed(h[:-d] * np.uint64(0x100000001B3) + mixed(h[d:]) + np.uint64(min(d, 2)))
                i = (x >> shift).astype(np.uint32)
                own.append(i[dense[i] != 0])
            if own:
                total = float(dense[np.unique(np.concatenate(own))].sum(dtype=np.float64))
            out[k] = 1 / (1 + np.exp(-np.clip(total + bias, -35, 35)))
        return pd.Series(out)

    return score


# --- word shingles --------------------------------------------------------------------------------------------


def shingle_hashes(h, size: int):
    """Sorted distinct hashes of all runs of size words; of a shorter text, of all its words."""
    import numpy as np

    if len(h) == 0:
        return h
    size = min(size, len(h))
    n = len(h) - size + 1
    x = np.zeros(n, np.uint64)
    for k in range(size):
        x = mixed(x * np.uint64(0xD6E8FEB86659FD93) + h[k : k + n])
    return np.unique(x)


def signature_rows(size: int, bands: int, rows: int, seed: int):
    """(id, text) batches -> id, n (shingles), set (hash of the shingle set), bands (array of band hashes)."""

    def run(batches):
        import hashlib
        import re

        import numpy as np
        import pandas as pd

        words, hashes = re.compile(WORD).findall, word_hasher()
        rng = np.random.default_rng(seed)
        a = rng.integers(1, 1 << 32, bands * rows, np.uint32) | np.uint32(1)
        b = rng.integers(0, 1 << 32, bands * rows, np.uint32)
        fold, place = rng.integers(1, 1 << 63, rows, np.uint64) | np.uint64(1), rng.integers(1, 1 << 63, bands, np.uint64)
        for batch in batches:
            out = []
            for key, text in zip(batch["id"], batch["text"], strict=True):
                s = shingle_hashes(hashes(words((text or "").lower())), size)
                if not len(s):
                    out.append((key, 0, "", np.zeros(0, np.int64)))
                    continue
                x, low = (s >> np.uint64(32)).astype(np.uint32), None
                for k in range(0, len(x), 512):
                    part = (x[None, k : k + 512] * a[:, None] + b[:, None]).min(axis=1)
                    low = part if low is None else np.minimum(low, part)
                band = mixed((low.reshape(bands, rows).astype(np.uint64) * fold).sum(axis=1, dtype=np.uint64) + place)
                out.append((key, len(s), hashlib.md5(s.tobytes()).hexdigest(), band.view(np.int64)))
            yield pd.DataFrame(out, columns=["id", "n", "set", "bands"])

    return run


def shingle_rows(size: int):
    """Arrow batches whose last column is a text -> the same rows with its shingles in the text's place."""

    def run(batches):
        import re

        import pyarrow as pa

        words, hashes = re.compile(WORD).findall, word_hasher()
        for batch in batches:
            shingles = [shingle_hashes(hashes(words((t or "").lower())), size).tobytes() for t in batch.column(batch.num_columns - 1).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(shingles, pa.binary())], names=[*batch.schema.names[:-1], "shingles"])

    return run


def overlaps(left: list, right: list):
    """Sizes of the intersections of two lists of sorted distinct arrays."""
    import numpy as np

    both = left if left is right else left + right
    owner = np.repeat(np.arange(len(both)), [len(x) for x in both])
    _, where, times = np.unique(np.concatenate(both), return_inverse=True, return_counts=True)
    shared = times[where] > 1
    owner, where = owner[shared], where[shared]
    order = np.argsort(where, kind="stable")
    owner, where = owner[order], np.unique(where[order], return_inverse=True)[1]
    out = np.zeros((len(left), len(right)), np.float32)
    step, n, width = 4096, len(both), int(where[-1]) + 1 if len(where) else 0
    for k in range(0, width, step):
        lo, hi = np.searchsorted(where, [k, k + step])
        m = np.zeros((n, min(step, width - k)), np.float32)
        m[owner[lo:hi], where[lo:hi] - k] = 1
        out += m[: len(left)] @ (m if left is right else m[len(left) :]).T
    return out


def spanning(pairs, n: int):
    """Pairs of numbers below n that connect what all pairs connect."""
    up, out = list(range(n)), []
    for i, j in pairs:
        while up[i] != i:
            i = up[i] = up[up[i]]
        while up[j] != j:
            j = up[j] = up[up[j]]
        if i != j:
            up[max(i, j)] = min(i, j)
            out.append((max(i, j), min(i, j)))
    return out


def tile_verifier(similarity: float):
    """A task holds the texts of two tiles (or of one) of a group or a band: counts of links for each text, and connecting links.

    key: whether it is a whole group, the group or band hash, and the two tiles. In a band only pairs that share no earlier band count.
    """

    def run(key, df):
        import numpy as np
        import pandas as pd

        whole, band, a, b = bool(key[0]), int(key[1]), int(key[2]), int(key[3])
        df = df.sort_values("cid", kind="stable").reset_index(drop=True)
        sets = [np.frombuffer(x, np.uint64) for x in df["shingles"]]
        size, copies, tile = df["n"].to_numpy(), df["copies"].to_numpy(), df["tile"].to_numpy()
        i, j = np.flatnonzero(tile == a), np.flatnonzero(tile == b)
        if not len(i) or not len(j):
            return pd.DataFrame({"u": [], "v": [], "links": []}).astype("Int64")
        left = [sets[k] for k in i]
        inter = overlaps(left, left if a == b else [sets[k] for k in j])
        union = size[i][:, None] + size[j][None, :] - inter
        linked = inter >= similarity * union - 1e-9
        if not whole:
            own = np.stack(df["bands"].to_numpy())
            first = (own[i][:, None, :] == own[j][None, :, :]).argmax(axis=2)
            linked &= own[i][np.arange(len(i))[:, None], first] == band
        if a == b:
            np.fill_diagonal(linked, False)
        names = df["cid"].to_numpy()
        out = [(names[k], None, int(c)) for k, c in zip(i, linked @ copies[j], strict=True) if c]
        if a != b:
            out += [(names[k], None, int(c)) for k, c in zip(j, copies[i] @ linked, strict=True) if c]
        x, y = np.nonzero(linked)
        out += [(names[u], names[v], 0) for u, v in spanning(zip(i[x].tolist(), j[y].tolist(), strict=True), len(df))]
        return pd.DataFrame({c: pd.array([row[k] for row in out], dtype="Int64") for k, c in enumerate(("u", "v", "links"))})

    return run


# --- context trees --------------------------------------------------------------------------------------------


class ContextTrees:
    """Byte context trees of several languages, laid over one trie of the grams that any of them has seen.

    ``order`` preceding bytes are the longest context. In a context with total count t and q different successors
    a seen byte with count c costs -log2(c / (t + q)) and an escape to the next shorter context -log2(q / (t + q));
    below the empty context all 256 bytes cost 8 bits. Statistics are frozen after fit().
    """

    def __init__(self, order: int = 4):
        self.order = order

    @classmethod
    def of(cls, fields: dict):
        trees = cls()
        vars(trees).update(fields)
        return trees

    def fit(self, texts: dict[str, list[str]]):
        """texts: for each language its training texts."""
        import numpy as np

        self.langs = sorted(texts)
        raw = {lang: [np.frombuffer(t.encode("utf-8", "replace"), np.uint8) for t in texts[lang] if t] for lang in self.langs}
        seen = sorted({int(b) for parts in raw.values() for x in parts for b in np.unique(x)})
        self.symbol = np.zeros(256, np.int32)
        self.symbol[seen] = np.arange(1, len(seen) + 1)
        self.width = len(seen) + 1
        n_lang, parents = len(self.langs), {lang: [np.zeros(len(x), np.int64) for x in parts] for lang, parts in raw.items()}
        symbols = {lang: [self.symbol[x] for x in parts] for lang, parts in raw.items()}
        self.child, self.cost, self.escape = [], [], []
        # level L: grams of L bytes; node 0 is "never seen"; the empty gram is node 1 of level 0
        grams = {lang: [np.ones(len(x) + 1, np.int64) for x in parts] for lang, parts in raw.items()}  # gram that ends before position i
        nodes, before_cost, suffix, lower_child = 2, None, None, None
        for level in range(self.order + 1):
            keys, owner = [], []
            for k, lang in enumerate(self.langs):
                for g, s in zip(grams[lang], symbols[lang], strict=True):
                    x = g[: len(s)] * self.width + s
                    keys.append(x[g[: len(s)] > 0])
                    owner.append(np.full(len(keys[-1]), k))
            keys, owner = (np.concatenate(keys), np.concatenate(owner)) if keys else (np.zeros(0, np.int64), np.zeros(0, np.int64))
            grown, where = np.unique(keys, return_inverse=True)
            count = np.zeros((len(grown) + 1, n_lang))
            np.add.at(count, (where + 1, owner), 1)
            parent, byte = grown // self.width, grown % self.width
            child = np.zeros(nodes * self.width, np.int32)
            child[grown] = np.arange(1, len(grown) + 1)
            total, kinds = np.zeros((nodes, n_lang)), np.zeros((nodes, n_lang))
            np.add.at(total, parent, count[1:])
            np.add.at(kinds, parent, count[1:] > 0)
            with np.errstate(divide="ignore", invalid="ignore"):
                escape = np.where(kinds > 0, -np.log2(kinds / (total + kinds)), 0.0)
                own = -np.log2(count[1:] / (total + kinds)[parent])
            # the cost of the same byte after the context without its first byte
            if level == 0:
                shorter = np.full((len(grown), n_lang), 8.0)
                up = np.zeros(len(grown) + 1, np.int64) + 1
                up[0] = 0
            else:
                up = np.concatenate([[0], lower_child[suffix[parent] * self.width + byte]]).astype(np.int64)
                shorter = before_cost[up[1:]]
            cost = np.where(count[1:] > 0, own, escape[parent] + shorter)
            self.child.append(child)
            never = escape[1] + 8.0 if level == 0 else np.zeros(n_lang)  # a byte that no language has seen
            self.cost.append(np.concatenate([never[None], cost]))
            self.escape.append(escape)
            for lang in self.langs:
                for k, s in enumerate(symbols[lang]):
                    g = grams[lang][k]
                    nxt = np.zeros(len(s) + 1, np.int64)
                    nxt[1:] = child[g[: len(s)] * self.width + s]
                    grams[lang][k] = nxt
            lower_child, before_cost, suffix, nodes = child, self.cost[-1], up, len(grown) + 1
        return self

    def lengths(self, data, starts):
        """Code lengths in bits, a row per text and a column per language. data: bytes of all texts; starts: where each begins."""
        import numpy as np

        s = self.symbol[data].astype(np.int64)
        n, first = len(s), np.zeros(len(s), bool)
        first[starts[starts < n]] = True
        depth = np.arange(n) - np.maximum.accumulate(np.where(first, np.arange(n), 0))
        gram = self.child[0][self.width + s].astype(np.int64)
        total = self.cost[0][gram]
        above = gram
        for level in range(1, self.order + 1):
            context = np.zeros(n, np.int64)
            context[1:] = above[:-1]
            context[depth < level] = 0
            gram = self.child[level][context * self.width + s].astype(np.int64)
            found = gram > 0
            # no language has seen the byte here: each escapes from the context if it has seen that
            lost = np.flatnonzero(~found & (context > 0))
            total[lost] += self.escape[level][context[lost]]
            found = np.flatnonzero(found)
            total[found] = self.cost[level][gram[found]]
            above = gram
        out = np.zeros((len(starts), total.shape[1]))
        full = np.flatnonzero(np.diff(np.append(starts, n)) > 0)
        if len(full):
            out[full] = np.add.reduceat(total, starts[full], axis=0)
        return out


def language_scorer(trees: ContextTrees, chunk: int = 1 << 18):
    """Texts -> (language or None where there is no letter, score). Long texts are coded in pieces that overlap by the order."""
    import numpy as np

    def score(texts):
        import re

        letter, langs, label = re.compile(r"[^\W\d_]").search, trees.langs, []
        raw = [(t or "").encode("utf-8", "replace") for t in texts]
        bits = np.zeros((len(raw), len(langs)))
        batch, size = [], 0

        def code():
            nonlocal batch, size
            if batch:
                starts = np.cumsum([0, *[len(x) for _, x, _ in batch]])[:-1]
                got = trees.lengths(np.frombuffer(b"".join(x for _, x, _ in batch), np.uint8), starts)
                for (k, x, lead), g in zip(batch, got, strict=True):
                    bits[k] += g - (trees.lengths(np.frombuffer(x[:lead], np.uint8), np.zeros(1, np.int64))[0] if lead else 0)
                batch, size = [], 0

        for k, x in enumerate(raw):
            for at in range(0, len(x), chunk):
                lead = min(at, trees.order)
                piece = x[at - lead : at + chunk]
                batch.append((k, piece, lead))
                size += len(piece)
                if size >= chunk:
                    code()
        code()
        for k, t in enumerate(texts):
            if t is None or not letter(t) or not langs:
                label.append(("und", 0.0))
                continue
            best = int(np.argmin(bits[k]))
            label.append((langs[best], float(1 / np.exp2(np.clip(bits[k][best] - bits[k], -500, 0)).sum())))
        return label

    return score


# --- sorted projection passes ---------------------------------------------------------------------------------


def units(raw, kind: str):
    """Unit vectors in double precision, of rows of numbers or of their bytes in the table's own precision; a row that has none comes back with nan or inf."""
    import numpy as np

    x = raw if isinstance(raw, np.ndarray) else np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1)
    x = x.astype(np.float64)
    with np.errstate(all="ignore"):
        x = x / np.abs(x).max(axis=1, keepdims=True)  # squares neither overflow nor vanish
        return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def sign_keys(unit, passes: int, bits: int, seed: int):
    """For each row and pass the signs of bits random projections, as one number."""
    import numpy as np

    planes = np.random.default_rng([seed, unit.shape[1]]).standard_normal((unit.shape[1], passes * bits))
    signs = (unit @ planes >= 0).reshape(len(unit), passes, bits)
    return (signs * (1 << np.arange(bits - 1, -1, -1, dtype=np.int64))).sum(axis=2)


def vector_rows(kind: str, rounds: int, key_bits: int, passes: int, seed: int):
    """Arrow batches of (id, label, vec) -> id, label with the length, node (hash of label and vector, empty if it links with nothing), vector as bytes, keys.

    The id is passed on as it is. Lengths are kept apart.
    """

    def run(batches):
        import hashlib

        import numpy as np
        import pyarrow as pa

        for batch in batches:
            n, vec = batch.num_rows, batch.column(2)
            labels = batch.column(1).to_pylist()
            size = np.asarray(vec.value_lengths().fill_null(0))
            at, values = vec.offsets.to_numpy()[:-1], vec.values.to_numpy(zero_copy_only=False).astype(kind)
            known = np.array([x is not None for x in labels], bool)
            name, node, raw = [None] * n, [""] * n, [b""] * n
            near, keys = np.zeros((n, rounds), np.int64), np.zeros((n, passes), np.int64)
            for width in np.unique(size[(size > 0) & known]).tolist():
                own = np.flatnonzero((size == width) & known)
                x = values[at[own][:, None] + np.arange(width)]
                unit = units(x, kind)
                good = np.isfinite(unit).all(axis=1)
                own, x, unit = own[good], x[good], unit[good]
                near[own], keys[own] = sign_keys(unit, rounds, key_bits, seed), sign_keys(unit, passes, 60, seed + 1)
                for k, v in zip(own.tolist(), x, strict=True):
                    name[k], raw[k] = f"{width}|{labels[k]}", v.tobytes()
                    node[k] = hashlib.md5(name[k].encode() + b"|" + raw[k]).hexdigest()
            lists = [pa.ListArray.from_arrays(np.arange(n + 1, dtype=np.int32) * x.shape[1], pa.array(x.ravel())) for x in (near, keys)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(name, pa.string()), pa.array(node, pa.string()), pa.array(raw, pa.binary()), *lists], names=["id", "label", "node", "raw", "near", "keys"])

    return run


def ball_rows(kind: str, most: float):
    """(ball, pivot, raw, pivot_raw, radius) batches -> the balls that fit in the ball around the pivot, and how far they reach."""

    def run(batches):
        import numpy as np
        import pandas as pd

        for batch in batches:
            width = batch["raw"].map(len)
            for _, some in batch.groupby(width, sort=False):
                dot = np.clip((units(some["raw"], kind) * units(some["pivot_raw"], kind)).sum(axis=1), -1, 1)
                same = (some["ball"] == some["pivot"]).to_numpy()
                reach = np.where(same, 0.0, np.arccos(dot)) + some["radius"].to_numpy()
                yield pd.DataFrame({"ball": some["ball"], "pivot": some["pivot"], "reach": reach})[reach <= most]

    return run


def pass_tile(cosine: float, kind: str, window: int, eps: float):
    """Rows of one or two tiles of a pass: links that no earlier pass has compared.

    A neighbour tile compares its own rows with the ``window`` rows before each; a run tile (of rows with one key prefix)
    compares what is farther apart. Two rows were compared in a pass if they are neighbours there or share the prefix.
    """

    def run(key, df):
        import numpy as np
        import pandas as pd

        near, theta = key[0] < 0, np.arccos(cosine)
        df = df.sort_values(["rank", "ball"], kind="stable").reset_index(drop=True)
        out = []
        for _, some in df.groupby(["pass", "label"], sort=False):
            unit, rank, part = units(some["raw"], kind), some["rank"].to_numpy(), some["part"].to_numpy()
            own, other = (np.flatnonzero(part == 1), np.arange(len(some))) if near else (np.flatnonzero(part == part.max()), np.flatnonzero(part == part.min()))
            if not len(own):
                continue
            step = rank[own][:, None] - rank[other][None, :]
            new = (step > 0) & (step <= window) if near else step > window
            ranks, runs = np.stack(some["ranks"].to_numpy()), np.stack(some["runs"].to_numpy())
            for q in range(int(some["pass"].iloc[0])):
                new &= (np.abs(ranks[own][:, None, q] - ranks[other][None, :, q]) > window) & (runs[own][:, None, q] != runs[other][None, :, q])
            dot = np.clip(unit[own] @ unit[other].T, -1, 1)
            radius, size, ball = some["radius"].to_numpy(), some["size"].to_numpy(), some["ball"].to_numpy()
            around, angle = radius[own][:, None] + radius[other][None, :], np.arccos(dot)
            linked = new & np.where(around == 0, dot >= cosine, angle + around <= theta - eps)
            unsure = new & ~linked & (around > 0) & (angle - around <= theta + eps)
            out += [(ball[k], None, int(c), "count") for k, c in zip(own, linked @ size[other], strict=True) if c]
            out += [(ball[k], None, int(c), "count") for k, c in zip(other, size[own] @ linked, strict=True) if c]
            i, j = np.nonzero(linked)
            out += [(ball[a], ball[b], 0, "edge") for a, b in spanning(zip(own[i].tolist(), other[j].tolist(), strict=True), len(some))]
            i, j = np.nonzero(unsure)
            out += [(ball[own[a]], ball[other[b]], 0, "open") for a, b in zip(i, j, strict=True)]
        return pd.DataFrame(out, columns=["u", "v", "links", "kind"])

    return run


def open_tile(cosine: float, kind: str):
    """Vectors of two balls, a tile of each: counts of links for each vector, and one link of the balls."""

    def run(key, df):
        import numpy as np
        import pandas as pd

        left, right = df[df["side"] == 0], df[df["side"] == 1]
        if not len(left) or not len(right):
            return pd.DataFrame({"u": [], "v": [], "node": [], "links": []}).astype({"u": str, "v": str, "node": str, "links": "int64"})
        linked = np.clip(units(left["raw"], kind) @ units(right["raw"], kind).T, -1, 1) >= cosine
        out = [(key[0], key[1], n, int(c)) for n, c in zip(left["node"], linked @ right["size"].to_numpy(), strict=True) if c]
        out += [(key[0], key[1], n, int(c)) for n, c in zip(right["node"], left["size"].to_numpy() @ linked, strict=True) if c]
        out += [(key[0], key[1], None, 0)] if linked.any() else []
        return pd.DataFrame(out, columns=["u", "v", "node", "links"])

    return run
