"""HTML extraction (9): main texts of pages, with a host's repeated runs of words found by sorted suffixes.

A tolerant scanner splits a page into blocks and marks each block's place: inside an article (or main)
element, outside, or inside page furniture (menus, headers, footers, sidebars, notices, adverts, forms,
scripts, styles, reader comments), which is dropped. The remaining blocks of every page are told from
boilerplate by their hosts: the streams of words of all pages of a host are taken together, with and without
an article, suffixes are dealt by the hash of their first ``RUN`` words
and sorted there by the hashes of their first 2, 4, 8, ... times as many. Beginnings that only one page
has are left out of the dealing by a bitmap of those met twice, which may let others pass. A suffix's nearest neighbours
of distinct pages on both sides give the length it repeats for, down to such a multiple; the suffixes
inside a run cover its rest. Words that such runs cover go, and the words in between stay. A bucket of suffixes
holds equal beginnings only, and a bucket of more than ``SHARE`` is sorted in shares of whole pages,
so a host of any size is spread over all tasks. Pages with equal words are one page.

An article's own words are never dropped for being repeated, as its text must stay whole; structure decides
nothing else. Blocks outside an article are text as far as no run covers them.

Defined cases: a null or empty html, or one without such blocks, gives an empty text; a null url is a
host of its own; null ids and repeated rows are pages like others, and pages of one host whose words are
equal aren't distinct, whatever their ids; unclosed elements end with their parents or the page; an empty table
gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import kernels as K
from .shared import freed_shuffles, materialize, release, small_batches, text_parts

#: Words of a repeated run, at least.
RUN = 8
#: Suffixes of a bucket that are sorted together, about.
SHARE = 50_000

#: Elements by their role in a page.
DROPPED = frozenset("nav header footer aside script style form noscript template iframe svg math button select textarea menu dialog head title object canvas audio video".split())
RAW = frozenset("script style textarea title noscript template iframe".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("p div article section main h1 h2 h3 h4 h5 h6 ul ol li table thead tbody tfoot tr td th caption blockquote pre dl dt dd figure figcaption hr address body html details summary fieldset center".split())
FURNITURE = re.compile(r"(?i)(?:^|[\s_-])(?:ads?|advert\w*|banner\w*|cookies?|consent|gdpr|sidebar\w*|side|menu\w*|nav|navbar|navigation|comments?|commentlist|replies|disqus|share|sharing|social|promo\w*|sponsor\w*|newsletter|subscribe|breadcrumbs?|related|recommended|footer|header|masthead|popup|modal|overlay|notice|notification|alert|widget\w*|toolbar|skip-link)(?:$|[\s_-])")
#: Inside an article whole class tokens and ids count: one of these, or a known compound of them.
COMPOUND = re.compile(
    r"(?i)(?:(?:article|post|entry|page|site|user|reader|main|google|inline)[_-]{1,2})?(?:ads?|advert\w*|banners?|cookies?|consent|gdpr|sidebar|side|menu|nav|navbar|navigation|breadcrumbs?|comments?|commentlist|replies|disqus|share|sharing|social|promo\w*|sponsor\w*|newsletter|subscribe|popup|modal|overlay|masthead|notice|notification|alert|widgets?|toolbar|related|recommended|footer|skip-link)"
    r"(?:[_-]{1,2}(?:box|bar|list|links?|icons?|buttons?|area|section|wrapper|container|form|respond|reply|count|block|posts?|articles?|stories|slot|unit|banner|notice|consent|thread|widget|menu|nav|signup|share|media))?|header"
)
#: Elements that no class or id makes furniture.
KEPT = frozenset("html body main article h1 h2 h3 h4 h5 h6".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar toolbar".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^<>]*)>|[^<]+|<", re.S)
_ATTRIBUTE = re.compile(r"([a-zA-Z-]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")


def _named(value: str, inside: bool) -> bool:
    """Whether a class or id names furniture; ``inside`` an article or main only whole tokens do, as parts of a slug are content."""
    return any(COMPOUND.fullmatch(t) for t in value.split()) if inside else bool(FURNITURE.search(value))


def _is_furniture(tag: str, attributes: str, inside: bool) -> bool:
    if tag in DROPPED:
        return True
    if not attributes.strip():
        return False
    for name, *value in _ATTRIBUTE.findall(attributes):
        v, name = "".join(value), name.lower()
        if name in ("class", "id") and tag not in KEPT and _named(v, inside):
            return True
        if name == "role" and v.lower() in ROLES or name == "hidden" or name == "aria-hidden" and v == "true":
            return True
        if name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", v, re.I):
            return True
    return False


#: Fixed values of the HTML standard: elements whose end tag may be left out, and what holds list items.
OPTIONAL_END = frozenset(("p", "li", "dt", "dd"))
LISTS = frozenset(("ul", "ol", "menu", "dl"))


def _ends(skip: str, tag: str, closing: bool, lists: int) -> bool:
    """Whether this tag ends an open element ``skip`` whose end tag was left out; ``lists`` are open inside it."""
    if skip == "p":
        return tag in BLOCKS and tag != "p" or tag == "p" and not closing
    if lists:
        return False
    return closing and tag in LISTS or not closing and (tag == skip or {skip, tag} == {"dt", "dd"})


def _found(page: str) -> list[tuple[int, str]]:
    """The blocks in order, without furniture, each with its place: in an article (2), in main alone (1) or outside (0)."""
    found: list[tuple[int, str]] = []
    parts: list[str] = []
    articles = mains = 0
    skip, depth, lists, raw_end = "", 0, 0, 0

    def close() -> None:
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                found.append((2 if articles else 1 if mains else 0, text))
            parts.clear()

    at, size = 0, len(page)
    while at < size:
        m = _TOKEN.match(page, at)
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            if not skip and page[m.start() : m.start() + 2] not in ("<!", "<?"):
                parts.append(m[0])
            continue
        closing, attributes = bool(m[1] or m[4]), m[3] or m[6] or ""
        if skip in OPTIONAL_END and _ends(skip, tag, closing, lists):
            skip, depth = "", 0  # an element without its end tag ends here
        if skip and tag in LISTS:
            lists += -1 if closing else 1
        if not closing and tag in RAW and not attributes.rstrip().endswith("/"):
            raw_end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            at = raw_end.end() if raw_end else size
            continue
        if skip:
            if tag == skip and not attributes.rstrip().endswith("/"):
                depth += -1 if closing else 1
                if not depth:
                    skip = ""
            elif closing and tag in ("article", "main", "body", "html"):
                skip, depth = "", 0  # an element left open ends with its parent
                close()
                articles, mains = (max(0, articles - 1), mains) if tag == "article" else (articles, max(0, mains - 1)) if tag == "main" else (0, 0)
            continue
        if tag in VOID:
            if tag == "br":
                parts.append(" ")
            elif tag == "hr":
                close()
            continue
        if not closing and _is_furniture(tag, attributes, articles + mains > 0):
            close()
            if not attributes.rstrip().endswith("/"):
                skip, depth, lists = tag, 1, 0
            continue
        if tag in BLOCKS:
            close()
            if tag == "article":
                articles = max(0, articles - 1) if closing else articles + 1
            elif tag == "main":
                mains = max(0, mains - 1) if closing else mains + 1
    close()
    return found


def _own(found: list[tuple[int, str]]) -> list[bool]:
    """Which blocks are inside the page's articles, or else its main element."""
    best = max((d for d, _ in found), default=0)
    return [d == best and best > 0 for d, _ in found]


def blocks(page: str) -> tuple[list[str], list[str]]:
    """(blocks inside the page's articles, or else its main element; all others, without furniture)."""
    found = _found(page)
    own = _own(found)
    return [t for (_, t), o in zip(found, own, strict=True) if o], [t for (_, t), o in zip(found, own, strict=True) if not o]


def _parsed(pages: DataFrame) -> DataFrame:
    """(uid, page_id, url, host, text, own): ``text``: all blocks, one a line; ``own``: "1" for each of the article's, else "0"."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                part = batch.slice(a, 500)
                got = [_found(h) for h in part.column("html").to_pylist()]
                own = ["".join("01"[o] for o in _own(g)) for g in got]
                yield pa.RecordBatch.from_arrays([part.column(c) for c in ("uid", "page_id", "url", "host")] + [pa.array(["\n".join(t for _, t in g) for g in got], pa.string()), pa.array(own, pa.string())], ["uid", "page_id", "url", "host", "text", "own"])

    host = F.lower(F.coalesce(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://([^/?#]*)", 1), F.lit("")))
    rows = pages.select(F.monotonically_increasing_id().alias("uid"), "page_id", "url", host.alias("host"), F.coalesce("html", F.lit("")).alias("html"))
    return rows.mapInArrow(run, "uid long, page_id long, url string, host string, text string, own string")


#: Windows of a batch that are sorted together for the bitmap; its least number of buckets; its bits for a byte of text and in all, at most.
SORTED, BUCKETS, BITS_BYTE, MOST_BITS = 1 << 20, 256, 0.5, 1 << 28


def _windows(batch: pa.RecordBatch, run: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(hash of ``run`` words, the same with the host, first word's place in the slice and in its text, row) by slices of a batch's texts."""
    host = batch.column("host").to_numpy(zero_copy_only=False).view(np.uint64)
    for a, _, buf, off in text_parts(batch.column("text")):
        start, end, bounds = K.words(buf, off)
        if len(start) >= run:
            h, at, text = K.windows(K.span_hash(K.prefix(buf), start, end), bounds, run)
            yield h, K.mix(h + host[a + text] * np.uint64(0x9E3779B97F4A7C15)), at, at - bounds[text], a + text


def _slots(keys: np.ndarray, buckets: int, bits: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket, value in it, bit in the bucket's bitmap of ``bits`` that the value has)."""
    value = keys & np.uint64(0xFFFFFFFF)
    return ((keys >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64), value, ((value * np.uint64(bits)) >> np.uint64(32)).astype(np.int64)


def _met_twice(streams: DataFrame, run: int) -> tuple[np.ndarray, int, int]:
    """(bitmap by buckets, their number, bits of each): set for all windows that two distinct pages of a host have, and
    some others. A batch's windows travel as gaps between sorted values, about three bytes each."""
    spark = streams.sparkSession
    size = streams.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    buckets = max(BUCKETS, int(spark.conf.get("spark.sql.shuffle.partitions")))
    bits = 8 * max(128, int(min(size * BITS_BYTE, MOST_BITS)) // (8 * buckets))

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts: list[tuple[np.ndarray, np.ndarray]] = []

        def packed() -> Iterator[pa.RecordBatch]:
            keys, page = (np.concatenate(x) for x in zip(*parts, strict=True))
            bucket, value, _ = _slots(keys, buckets, bits)
            order = np.lexsort((value, bucket))
            bucket, value, page = bucket[order], value[order], page[order]
            first = np.flatnonzero(np.append(True, (np.diff(bucket) != 0) | (value[1:] != value[:-1])))
            twice = np.minimum.reduceat(page, first) != np.maximum.reduceat(page, first)
            bucket, value = bucket[first], value[first]
            cuts = np.flatnonzero(np.append(True, np.diff(bucket) != 0))
            out = []
            for lo, hi in zip(cuts, np.append(cuts[1:], len(bucket)), strict=True):
                gaps = np.diff(value[lo:hi], prepend=np.uint64(0)).astype("<u4")
                # bytes of equal weight stand together, as most of the highest are zero
                out.append((int(bucket[lo]), np.ascontiguousarray(gaps.view(np.uint8).reshape(-1, 4).T).tobytes(), np.packbits(twice[lo:hi]).tobytes()))
            columns = [pa.array(c, kind) for c, kind in zip(zip(*out, strict=True), (pa.int32(), pa.binary(), pa.binary()), strict=True)]
            yield pa.RecordBatch.from_arrays(columns, ["bucket", "gaps", "twice"])

        for batch in batches:
            page = batch.column("page").to_numpy(zero_copy_only=False)
            for _, keys, _, _, row in _windows(batch, run):
                parts.append((keys, page[row]))
                if sum(len(k) for k, _ in parts) >= SORTED:
                    yield from packed()
                    parts.clear()
        if parts:
            yield from packed()
        release()

    def maps(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, values = None, []

        def packed() -> pa.RecordBatch:
            every = np.sort(np.concatenate(values))
            out = np.zeros(bits, bool)
            out[_slots(every[1:][every[1:] == every[:-1]], 1, bits)[2]] = True
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([np.packbits(out).tobytes()], pa.binary())], ["bucket", "bits"])

        for batch in batches:
            for i, bucket in enumerate(batch.column("bucket").to_pylist()):
                if values and bucket != now:
                    yield packed()
                    values = []
                now = bucket
                gaps = np.ascontiguousarray(np.frombuffer(batch.column("gaps")[i].as_buffer(), np.uint8).reshape(4, -1).T).view("<u4").ravel()
                value = np.cumsum(gaps, dtype=np.uint64)
                twice = np.unpackbits(np.frombuffer(batch.column("twice")[i].as_buffer(), np.uint8), count=len(value)).view(bool)
                values += [value, value[twice]]
        if values:
            yield packed()
        release()

    dealt = streams.mapInArrow(sets, "bucket int, gaps binary, twice binary").repartition(buckets, "bucket").sortWithinPartitions("bucket")
    out = np.zeros((buckets, bits // 8), np.uint8)
    with small_batches(spark), freed_shuffles(spark):
        for r in dealt.mapInArrow(maps, "bucket int, bits binary").collect():
            out[r["bucket"]] = np.frombuffer(bytes(r["bits"]), np.uint8)
    return out, buckets, bits


def _doubled(hashes: np.ndarray, places: np.ndarray, text: np.ndarray, run: int) -> pa.ListArray:
    """For each suffix the hashes of its first 2, 4, 8, ... times ``run`` words, as far as its text goes."""
    levels, width, now = [], run, hashes
    where = np.full(int(places[-1]) + 2 if len(places) else 1, -1)
    where[places] = np.arange(len(places))
    held = np.ones(len(places), bool)
    while held.any():
        at = places + width
        later = np.where(at < len(where), where[np.minimum(at, len(where) - 1)], -1)
        # the second half begins at a suffix of the same text that has a window of this width itself
        held = held & (later >= 0) & (text[later] == text) & held[later]
        now = np.where(held, K.mix(now * np.uint64(0x9E3779B97F4A7C15) + now[later]), np.uint64(0))
        levels.append((held, now))
        width *= 2
    mask = np.stack([h for h, _ in levels], 1) if levels else np.zeros((len(places), 0), bool)
    values = np.stack([v for _, v in levels], 1)[mask] if levels else np.zeros(0, np.uint64)
    return pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(mask.sum(1))).astype(np.int32)), pa.array(values.view(np.int64)))


def _neighbour(order: list[Column], name: str, frame: DataFrame) -> DataFrame:
    """Adds ``name``: the steps of the last suffix of another page before each suffix in this order."""
    w = Window.partitionBy("head", "share").orderBy(*order)
    turned = frame.withColumn("_page", F.lag("page").over(w)).withColumn("_steps", F.lag("steps").over(w))
    return turned.withColumn(name, F.last(F.when(F.col("_page") != F.col("page"), F.col("_steps")), True).over(w.rowsBetween(Window.unboundedPreceding, 0))).drop("_page", "_steps")


def repeated_runs(streams: DataFrame, run: int = RUN, share: int = SHARE) -> DataFrame:
    """(uid, at, length): word places from which ``length`` words, ``run`` at least, stand in a distinct page of the
    host too. ``streams``: uid, host, text; a stream's words are those between white space."""

    # pages with the same words are one page
    page = F.xxhash64(F.concat_ws(" ", F.split(F.trim("text"), r"\s+")))
    numbered = streams.select("uid", F.xxhash64("host").alias("host"), page.alias("page"), "text")
    bitmap, buckets, bits = _met_twice(numbered, run)
    spread = streams.sparkSession.sparkContext.broadcast(bitmap)

    def suffixes(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            uid, page = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("uid", "page"))
            for h, keys, place, at, row in _windows(batch, run):
                bucket, _, bit = _slots(keys, buckets, bits)
                met = (spread.value[bucket, bit >> 3] >> (7 - (bit & 7)).astype(np.uint8)) & 1 > 0
                steps = _doubled(h, place, row, run).filter(pa.array(met))
                yield pa.RecordBatch.from_arrays([pa.array(keys[met].view(np.int64)), pa.array(page[row[met]]), pa.array(uid[row[met]]), pa.array(at[met].astype(np.int32)), steps], ["head", "page", "uid", "at", "steps"])

    # the head is the hash of a suffix's first words and its host
    heads = numbered.mapInArrow(suffixes, "head long, page long, uid long, at int, steps array<long>")
    # a bucket of one page has no neighbours of distinct pages; in others every suffix has one that shares its first words
    shares = F.ceil(F.count("*") / F.lit(float(share))).cast("int").alias("shares")
    shared = heads.groupBy("head").agg(F.min("page").alias("p0"), F.max("page").alias("p1"), shares).where("p0 <> p1").select("head", "shares")
    dealt = heads.join(shared, "head").withColumn("share", F.pmod(F.hash("page"), F.col("shares")))
    keys = ["steps", "page", "uid", "at"]
    near = _neighbour([F.desc(k) for k in keys], "after", _neighbour([F.asc(k) for k in keys], "before", dealt))
    # equal hashes of some length imply equal ones of all lengths before it
    alike = [F.coalesce(F.size(F.filter(F.zip_with("steps", c, lambda x, y: x == y), lambda e: e)), F.lit(0)) for c in ("before", "after")]
    return near.select("uid", F.col("at").cast("long").alias("at"), (F.lit(run) * F.pow(F.lit(2.0), F.greatest(F.lit(0), *alike))).cast("long").alias("length"))


def _unique_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for text, own, places in zip(*(batch.column(c).to_pylist() for c in ("text", "own", "places")), strict=True):
            lines, covered, at = [], np.zeros(len(text.split()), bool), 0
            for p in places or ():
                covered[p["at"] : p["at"] + p["length"]] = True
            for line, whole in zip(text.split("\n"), own, strict=True):
                words = line.split()
                lines.append(line if whole == "1" else " ".join(w for w, c in zip(words, covered[at : at + len(words)], strict=True) if not c))
                at += len(words)
            out.append("\n".join(x for x in lines if x))
        yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in ("page_id", "url")), pa.array(out, pa.string())], ["page_id", "url", "text"])


def page_texts(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    parsed = materialize(_parsed(pages), "pages-parsed", compression="zstd")
    # the runs of all pages are written, as the plan would else leave them out where no page has a block outside its article
    runs = materialize(repeated_runs(parsed.where("text <> ''").select("uid", "host", "text")), "page-runs")
    loose = parsed.where("contains(own, '0')")
    places = runs.groupBy("uid").agg(F.collect_list(F.struct("at", "length")).alias("places"))
    cleaned = loose.join(places, "uid", "left").select("page_id", "url", "text", "own", "places").mapInArrow(_unique_words, "page_id long, url string, text string")
    out = parsed.where("not contains(own, '0')").select("page_id", "url", "text").unionByName(cleaned)
    return out.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
