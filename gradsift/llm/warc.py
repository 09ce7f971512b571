"""Web-archive records and a Merkle audit of their replicas.

Records are laid out in archives of about the same number, in order of their id, each at its
offset. The record digests of an archive are the leaves of a tree whose inner nodes digest
the runs of their children, in offset order; archive roots are the leaves of a tree over the
corpus. Two replicas are compared from the top, and only below nodes that differ, so equal
archives cost one digest each.

Defined results: a null body or address is empty; a null id is an id; equal ids are ordered
by address and digest; a record that one replica lacks differs there, as do those after it
in its archive; an empty table has no node and no fault. No record leaves its task: what is
shuffled are digests and offsets.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from gradsift.llm.staging import Stage

PER_ARCHIVE = 1000
FANOUT = 16


def record(id_col: str, url_col: str, body_col: str) -> Column:
    """A WARC 1.1 resource record."""
    body = F.coalesce(F.col(body_col), F.lit(""))
    head = F.concat(
        F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:record:"), F.coalesce(F.col(id_col).cast("string"), F.lit("")),
        F.lit(">\r\nWARC-Target-URI: "), F.coalesce(F.col(url_col), F.lit("")), F.lit("\r\nContent-Type: text/html\r\nContent-Length: "),
        F.octet_length(body).cast("string"), F.lit("\r\n\r\n"),
    )
    return F.concat(head, body, F.lit("\r\n\r\n"))


def read_record(raw: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields and body of one record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if not lines[0].startswith("WARC/"):
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) for x in lines[1:])
    return fields, rest[: int(fields["Content-Length"])]


def manifest(pages: DataFrame, n_archives: int, id_col: str = "page_id", url_col: str = "url", body_col: str = "html") -> DataFrame:
    """(archive, pos, record_offset, n_bytes, digest, id, url): one row a record."""
    rec = record(id_col, url_col, body_col)
    name = F.coalesce(F.col(id_col).cast("string"), F.lit(""))
    rows = pages.select(
        (F.conv(F.substring(F.md5(name.cast("binary")), 1, 8), 16, 10).cast("long") % n_archives).alias("archive"),
        F.col(id_col).alias("id"), F.coalesce(F.col(url_col), F.lit("")).alias("url"),
        F.octet_length(rec).cast("long").alias("n_bytes"), F.sha2(rec.cast("binary"), 256).alias("digest"),
    )
    order = Window.partitionBy("archive").orderBy("id", "url", "digest")
    return rows.select(
        "archive", (F.row_number().over(order) - 1).cast("long").alias("pos"),
        (F.sum("n_bytes").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_bytes")).alias("record_offset"),
        "n_bytes", "digest", "id", "url",
    )


def _above(level: DataFrame, keys: list[str], node: str, fanout: int) -> DataFrame:
    """The parents of a level: each digests at most fanout children in their order."""
    return (
        level.groupBy(*keys, F.floor(F.col(node) / fanout).alias("_up"))
        .agg(F.array_sort(F.collect_list(F.struct(F.col(node).alias("n"), "digest"))).alias("_c"))
        .select(*keys, F.col("_up").alias(node), F.sha2(F.array_join(F.transform("_c", lambda c: c["digest"]), "").cast("binary"), 256).alias("digest"))
    )


class Tree:
    """Levels of one replica, from the leaves up; the last has the corpus root.

    Levels are written, so that a comparison's plan doesn't hold the levels below.
    """

    def __init__(self, leaves: DataFrame, depth: int, n_archives: int, stage: Stage, fanout: int = FANOUT):
        self.fanout = fanout
        self.within = [leaves.select("archive", "pos", "digest")]
        for _ in range(depth):
            self.within.append(stage.put(_above(self.within[-1], ["archive"], "pos", fanout)))
        self.over = [self.within[-1].select("archive", "digest")]
        while n_archives > 1:
            self.over.append(stage.put(_above(self.over[-1], [], "archive", fanout)))
            n_archives = -(-n_archives // fanout)

    def root(self) -> str | None:
        top = self.over[-1].first()
        return top["digest"] if top else None


def _differing(a: DataFrame, b: DataFrame, keys: list[str]) -> DataFrame:
    return a.join(b.withColumnRenamed("digest", "_other"), keys, "full").where(~F.col("digest").eqNullSafe(F.col("_other"))).select(*keys)


def audit(primary: DataFrame, replica: DataFrame, id_col: str = "page_id", url_col: str = "url", body_col: str = "html", per_archive: int = PER_ARCHIVE, fanout: int = FANOUT) -> DataFrame:
    """The records that differ: place in the archive, and both replicas' digests."""
    stage = Stage(primary.sparkSession, "fixity")
    n_archives = max(1, -(-primary.count() // per_archive))
    a, b = (stage.put(manifest(t, n_archives, id_col, url_col, body_col)) for t in (primary, replica))
    longest = max((t.agg(F.max("pos")).first()[0] or 0) + 1 for t in (a, b))
    depth = 0
    while fanout**depth < longest:
        depth += 1
    x, y = (Tree(t, depth, n_archives, stage, fanout) for t in (a, b))
    bad: DataFrame | None = None
    for p, q in zip(reversed(x.over), reversed(y.over), strict=True):
        if bad is not None:
            up = bad.select(F.col("archive").alias("_up"))
            p, q = (t.join(up, F.floor(t["archive"] / fanout) == up["_up"], "left_semi") for t in (p, q))
        bad = _differing(p, q, ["archive"])
    bad = bad.withColumn("pos", F.lit(0).cast("long"))
    for p, q in zip(reversed(x.within[:-1]), reversed(y.within[:-1]), strict=True):
        up = bad.select(F.col("archive").alias("_a"), F.col("pos").alias("_up"))
        p, q = (t.join(up, (t["archive"] == up["_a"]) & (F.floor(t["pos"] / fanout) == up["_up"]), "left_semi") for t in (p, q))
        bad = stage.put(_differing(p, q, ["archive", "pos"]))
    other = b.select("archive", "pos", F.col("digest").alias("found_sha256"), F.col("id").alias("_id"), F.col("url").alias("_url"))
    return (
        bad.join(a, ["archive", "pos"], "left").join(other, ["archive", "pos"], "left")
        .select(
            F.coalesce("id", "_id").alias(id_col), F.coalesce("url", "_url").alias(url_col), "archive", "pos", "record_offset", "n_bytes",
            F.col("digest").alias("expected_sha256"), "found_sha256",
        )
    )
