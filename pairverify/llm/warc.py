"""WARC archives: writing pages with duplicate payloads as revisits, and reading archives by verified record boundaries.

Writing goes through Spark's text sink with the end of a WARC record as line end. Reading splits archives at the record
mark wherever it stands, in byte ranges of files, so a mark inside a payload gives a candidate too. Every candidate names
its successor: its own offset plus header and content length. Candidates that follow one another directly are drawn
together into segments inside each byte range; then pointer jumping from each file's first byte, doubling the stride
every round, finds the segments that a chain from the start reaches. Only records on that chain stay.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ._common import freed_shuffles, materialize, scratch_dir

# Fixed values of the format.
MARK = "WARC/1.1\r\n"
END = "\r\n\r\n"
BASE32 = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def base32_of_hex(hexes: Column) -> Column:
    """Base32 text of a 40-digit hexadecimal number, four letters for every five digits."""
    parts = []
    for g in range(8):
        n = F.conv(F.substring(hexes, 5 * g + 1, 5), 16, 10).cast("int")
        parts += [F.substring(F.lit(BASE32), F.shiftright(n, s).bitwiseAND(31) + 1, F.lit(1)) for s in (15, 10, 5, 0)]
    return F.concat(*parts)


def write(pages: DataFrame, path: str, min_bytes: int = 0, date: str = "2024-01-01T00:00:00Z", broadcast_rows: int = 100_000) -> None:
    """One record per row of pages (page_id, url, html). A null html is empty, a null url leaves out its field.

    Among equal payloads of at least min_bytes the row with the largest page_id is the response and the others are
    revisits of it; rows that repeat that largest id are all responses, as are all rows of a group without any id. Other
    columns of pages play no part. An empty table gives archives without records.
    """
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    rows = rows.withColumn("size", F.octet_length("html").cast("long")).withColumn("hex", F.sha1(F.col("html").cast("binary")))
    groups = rows.where(F.col("size") >= min_bytes).groupBy("hex", "size").agg(F.max("page_id").alias("first"), F.count("*").alias("n"))
    groups = materialize(groups.where("n > 1 and first is not null").select("hex", "size", "first"), "payloads")
    small = groups.count() <= broadcast_rows  # beyond that many, both sides are shuffled
    rows = rows.join(F.broadcast(groups) if small else groups, ["hex", "size"], "left")
    again = F.coalesce(F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first")), F.lit(False))
    urn = lambda c: F.concat(F.lit("<urn:page:"), F.coalesce(c.cast("string"), F.lit("")), F.lit(">"))
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), F.col("size").cast("string"), F.lit(END))
    block = F.when(again, http).otherwise(F.concat(http, F.col("html")))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    head = F.concat(
        F.lit(MARK),
        line("WARC-Type", F.when(again, F.lit("revisit")).otherwise(F.lit("response"))),
        line("WARC-Record-ID", urn(F.col("page_id"))),
        line("WARC-Date", F.lit(date)),
        F.coalesce(line("WARC-Target-URI", F.regexp_replace("url", "[\\r\\n]+", "")), F.lit("")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), base32_of_hex(F.col("hex")))),
        F.when(again, F.concat(line("WARC-Profile", F.lit(PROFILE)), line("WARC-Refers-To", urn(F.col("first"))))).otherwise(F.lit("")),
        line("Content-Type", F.lit("application/http; msgtype=response")),
    )
    text = F.concat(head, line("Content-Length", F.octet_length(block).cast("string")), F.lit("\r\n"), block)
    rows.select(text.alias("value")).write.option("lineSep", END).text(path)


def pieces(spark: SparkSession, path: str) -> DataFrame:
    """What stands between record marks: file, byte range, place in it, and the bytes as `value`."""
    raw = spark.read.option("lineSep", MARK).text(path)
    return raw.select(F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("block"), F.monotonically_increasing_id().alias("place"), "value")


def _offsets(rows: DataFrame) -> DataFrame:
    """Adds `off`, where a piece's mark begins; a file's first piece has no mark before it. rows: with `size`, a piece's bytes."""
    step = F.col("size") + len(MARK)
    blocks = rows.groupBy("file", "block").agg(F.sum(step).alias("bytes"))
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    blocks = blocks.select("file", "block", F.coalesce(F.sum("bytes").over(before), F.lit(0)).alias("base"))
    inside = Window.partitionBy("file", "block").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("in_block", F.coalesce(F.sum(step).over(inside), F.lit(0)))
    return rows.join(blocks, ["file", "block"]).withColumn("off", F.col("base") + F.col("in_block") - len(MARK)).drop("base", "in_block")


def _fields(value: Column) -> dict[str, Column]:
    """Columns read from a record's bytes after its mark."""
    head = F.substring_index(value, END, 1)
    start = F.octet_length(head) + len(END)
    number = lambda text, pattern: F.nullif(F.regexp_extract(text, pattern, 1), F.lit(""))
    length = F.expr("try_cast(length_text as bigint)")
    return {"head": head, "start": start, "length_text": number(head, r"(?i)(?:^|\r\n)Content-Length:[ \t]*(\d+)"), "length": length}


def _payload(value: Column, start: Column, length: Column) -> Column:
    """The bytes after the HTTP header of the record's block."""
    block = F.substring(value.cast("binary"), (start + 1).cast("int"), length.cast("int"))
    head = F.substring_index(block.cast("string"), END, 1)
    at = F.octet_length(head) + len(END)
    return F.substring(block, (at + 1).cast("int"), F.greatest(length - at, F.lit(0)).cast("int"))


def chains(spots: DataFrame, max_rounds: int = 64) -> DataFrame:
    """The rows of spots (file, block, off, next) that a chain of off to next from offset 0 of their file reaches.

    No row of a file that does not begin with a record stays. An empty table gives no rows.
    """
    order = Window.partitionBy("file", "block").orderBy("off")
    new = F.coalesce(F.lag("next").over(order) != F.col("off"), F.lit(True))
    spots = spots.withColumn("segment", F.last(F.when(new, F.col("off")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0)))
    spots = materialize(spots, "spots")
    ends = spots.groupBy("file", "segment").agg(F.max_by("next", "off").alias("to_off"))
    entries = spots.select("file", F.col("off").alias("to_off"), F.col("segment").alias("to_segment"))
    jump = materialize(ends.join(entries, ["file", "to_off"]).where("to_off > segment"), "jump")
    reached = spots.where("off = 0").select("file", "segment", F.col("off").alias("entry")).distinct()
    reached = materialize(reached, "reached")
    count = reached.count()
    for _ in range(max_rounds):
        more = reached.join(jump, ["file", "segment"]).select("file", F.col("to_segment").alias("segment"), F.col("to_off").alias("entry"))
        reached = materialize(reached.unionAll(more).groupBy("file", "segment").agg(F.min("entry").alias("entry")), "reached")
        now = reached.count()
        if now == count:
            break
        count = now
        far = jump.select("file", F.col("to_segment").alias("segment"), F.col("to_off").alias("_o"), F.col("to_segment").alias("_s"), F.col("segment").alias("from_segment"))
        nxt = far.join(jump, ["file", "segment"]).select("file", F.col("from_segment").alias("segment"), "to_off", "to_segment")
        jump = materialize(nxt, "jump")
    return spots.join(reached, ["file", "segment"]).where("off >= entry").drop("segment", "entry")


def read(spark: SparkSession, path: str) -> DataFrame:
    """One row per record on the boundary chains: page_id, record_type, refers_to, payload_bytes, payload_digest, digest_ok.

    payload_bytes and payload_digest of a response are taken from its bytes; those of a revisit from the response it
    refers to. Records whose mark also stands inside their payload are put together again from their pieces. Archives
    without records give no rows.
    """
    value = F.col("value")
    f = _fields(value)
    rows = pieces(spark, path).withColumn("head", f["head"]).withColumn("length_text", f["length_text"]).withColumn("length", f["length"])
    rows = rows.withColumn("start", F.octet_length("head") + F.lit(len(END))).withColumn("size", F.octet_length("value").cast("long"))
    whole = F.col("length").isNotNull() & (F.col("size") >= F.col("start") + F.col("length"))
    payload = F.when(whole, _payload(value, F.col("start"), F.col("length")))
    rows = rows.select("file", "block", "place", "size", F.when(F.col("length").isNotNull(), F.col("head")).alias("head"), "start", "length", whole.alias("whole"), F.octet_length(payload).cast("long").alias("bytes"), F.sha1(payload).alias("hex"))
    spots = materialize(_offsets(rows), "candidates").where("length is not null and off >= 0")
    spots = spots.withColumn("next", F.col("off") + len(MARK) + F.col("start") + F.col("length") + len(END))
    found = materialize(chains(spots), "records")
    torn = found.where("not whole").select("file", "off", "next", "start", "length")
    if torn.limit(1).count():
        found = found.where("whole").unionByName(_mended(spark, path, found))
    head = lambda name, pattern: F.regexp_extract("head", rf"(?i)(?:^|\r\n){name}:[ \t]*{pattern}", 1)
    records = found.select(
        F.nullif(head("WARC-Record-ID", r"<urn:page:(-?\d*)>"), F.lit("")).cast("long").alias("page_id"),
        head("WARC-Type", r"(\w+)").alias("record_type"),
        F.nullif(head("WARC-Refers-To", r"<urn:page:(-?\d+)>"), F.lit("")).cast("long").alias("refers_to"),
        head("WARC-Payload-Digest", r"sha1:(\w+)").alias("told"),
        "bytes",
        base32_of_hex(F.col("hex")).alias("digest"),
    )
    records = materialize(records, "parsed")
    first = records.where("record_type = 'response'").groupBy(F.col("page_id").alias("refers_to"), F.col("digest").alias("told")).agg(F.max("bytes").alias("first_bytes"))
    wanted = records.where("record_type = 'revisit'").select("refers_to", "told").distinct()
    first = first.join(wanted, ["refers_to", "told"], "left_semi")
    out = records.join(first, ["refers_to", "told"], "left")
    again = F.col("record_type") == "revisit"
    return out.select(
        "page_id",
        F.when(again, F.col("first_bytes")).otherwise(F.col("bytes")).alias("payload_bytes"),
        F.when(again, F.when(F.col("first_bytes").isNotNull(), F.col("told"))).otherwise(F.col("digest")).alias("payload_digest"),
        "record_type",
        "refers_to",
        F.when(again, F.col("first_bytes").isNotNull()).otherwise(F.col("told") == F.col("digest")).alias("digest_ok"),
    )


def _mended(spark: SparkSession, path: str, found: DataFrame, cell: int = 1 << 20) -> DataFrame:
    """The torn records of found, with `bytes` and `hex` from all their pieces.

    Pieces meet the records that hold them in cells of a file's bytes, so a task gets the pieces of single records.
    """
    torn = found.where("not whole")
    rows = _offsets(pieces(spark, path).withColumn("size", F.octet_length("value").cast("long"))).where("off >= 0")
    spans = torn.select("file", F.col("off").alias("first"), F.col("next").alias("last"))
    spans = spans.withColumn("cell", F.explode(F.sequence(F.floor(F.col("first") / cell), F.floor((F.col("last") - 1) / cell))))
    marks = rows.select("file", "off", "value", F.floor(F.col("off") / cell).alias("cell"))
    joined = marks.join(spans, ["file", "cell"]).where("off >= first and off < last")
    texts = joined.groupBy("file", "first").agg(F.array_sort(F.collect_list(F.struct("off", "value"))).alias("all"))
    texts = texts.select("file", F.col("first").alias("off"), F.array_join(F.transform("all", lambda x: x["value"]), MARK).alias("value"))
    full = torn.drop("bytes", "hex").join(texts, ["file", "off"])
    payload = _payload(F.col("value"), F.col("start"), F.col("length"))
    return full.withColumn("bytes", F.octet_length(payload).cast("long")).withColumn("hex", F.sha1(payload)).drop("value")


def round_trip(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Write archives of pages to the shared scratch folder and read them back."""
    spark = pages.sparkSession
    path = f"{scratch_dir(spark)}/warc"
    with freed_shuffles(spark):
        write(pages, path, min_bytes)
    return read(spark, path)
