"""Gather, verify, select, tag: one object that is fitted to a reference and links queries to it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import gather as G
from ..operators.gather import once
from ..operators.encode import HashedNgramEncoder, TfidfEncoder
from ..operators.lexical import brute_score, joint_query, lexical_search
from ..operators.serialize import serialize_records, serialize_values
from ..operators.tag import tag_pairs
from ..operators.verify import attach_fields, composite_score, select_best, select_nearest
from ..schema import RecordSchema
from ..sources.shared import keep, settle

GATHERERS = ("knn", "pruned", "forest", "ivf", "density", "lsh", "lexical", "joint", "brute_cosine", "brute_score")
#: Rows up to which the reference is searched flat; above, cells are searched.
FLAT_ROWS = 2_000_000


def choose_gatherer(rows: int, exact: bool = True) -> str:
    """Flat search for a small reference; beyond it, pruned cells if exactness is asked for, else cells."""
    return "knn" if rows <= FLAT_ROWS else "pruned" if exact else "ivf"


@dataclass
class Linker:
    """``encoder``: HashedNgramEncoder, TfidfEncoder, PretrainedEncoder or ProjectedEncoder; ``gatherer``: a name of GATHERERS,
    "auto" or None (verify every pair); ``sentence``: "full" (``template``, or the schema's own) or "values"; ``verify``: False takes the nearest candidate; ``options`` go to the gatherer."""

    schema: RecordSchema
    encoder: object = field(default_factory=HashedNgramEncoder)
    gatherer: str | None = "knn"
    k: int = 5
    verify: bool = True
    accept: float | None = None
    missing: str = "zero"
    sentence: str = "full"
    template: str | None = None
    options: dict = field(default_factory=dict)

    def _sentences(self, df: DataFrame) -> DataFrame:
        return serialize_records(df, self.schema, template=self.template) if self.sentence == "full" else serialize_values(df, self.schema)

    def fit(self, ref: DataFrame, path: str | None = None) -> Linker:
        """Encode and index the reference once, into the shared folder; ``path`` keeps its vectors as Parquet."""
        self.ref = ref = once(self.schema.check(ref))
        name = self.gatherer
        if name == "auto":
            name = choose_gatherer(ref.count())
        self.used = name
        self.index = None
        if name in (None, "brute_score", "joint"):
            return self
        s = self._sentences(ref)
        if name == "lexical":
            self.ref_text = s
            return self
        if isinstance(self.encoder, TfidfEncoder):
            self.encoder.fit(s, "rid")
            if name == "knn":  # in the term space itself, without hashing
                self.vectors = settle(self.encoder.sparse(s, "rid"))
                return self
        vectors = self.encoder.encode(s, "rid")
        if path:
            vectors.write.mode("overwrite").parquet(path)
            vectors = ref.sparkSession.read.parquet(path)
        self.vectors = vectors if path else keep(vectors)  # encoded once, whatever reads it
        kinds = {
            "pruned": (G.PivotIndex, ("pivots", "seed", "sample")),
            "forest": (G.Forest, ("trees", "leaf", "seed", "sample", "least")),
            "ivf": (G.CellIndex, ("cells", "seed", "sample")),
            "lsh": (G.HashIndex, ("tables", "bits", "leaf", "seed", "sample")),
            "density": (G.DensityIndex, ("eps", "min_pts", "pivots", "seed")),
        }
        if name in kinds:
            index, names = kinds[name]
            self.index = index.fit(self.vectors, **{k: v for k, v in self.options.items() if k in names})
        return self

    def gather(self, queries: DataFrame) -> DataFrame:
        """(qid, rid, rank, sim)."""
        name, o = self.used, self.options
        if name in (None, "brute_score"):
            return brute_score(queries, self.ref, self.schema, self.k)
        if name == "joint":
            return joint_query(queries, self.ref, k=self.k, **{k: v for k, v in o.items() if k in ("keys", "mode", "steps")})
        s = self._sentences(queries)
        if name == "lexical":
            return lexical_search(s, self.ref_text, self.k, **{k: v for k, v in o.items() if k in ("scorer", "df_share")})
        if isinstance(self.encoder, TfidfEncoder) and name == "knn":
            return G.knn_sparse(self.encoder.sparse(s, "qid"), self.vectors, self.k, "term", "w")
        q = self.encoder.encode(G.spread(s.select("qid", "sentence"), "qid"), "qid")
        if name == "knn":
            return G.knn_exact(q, self.vectors, self.k)
        if name == "brute_cosine":
            return G.brute_cosine(q, self.vectors, self.k)
        if name == "pruned":
            return self.index.query(q, self.k)
        inside = ("trees", "leaf") if o.get("inner") == "forest" or name == "density" else ()
        return self.index.query(q, self.k, **{k: v for k, v in o.items() if k in ("probes", "inner", *inside)})

    def score(self, cands: DataFrame, queries: DataFrame) -> DataFrame:
        return composite_score(attach_fields(cands, queries, self.ref, self.schema), self.schema, missing=self.missing)

    def link(self, queries: DataFrame, multi: bool = False) -> DataFrame:
        """(qid, rid, score, sim, tag, fields) for every query; rid is null for an unlinked one."""
        queries = once(self.schema.check(queries))
        cands = self.gather(queries)
        best = select_best(self.score(cands, queries)) if self.verify else select_nearest(cands)
        if self.accept is not None:
            best = best.where(F.col("score") >= self.accept)
        tags = tag_pairs(best, queries, self.ref, self.schema, multi=multi)
        return tags.join(best.select("qid", "sim"), "qid", "left").select("qid", "rid", "score", "sim", "tag", "fields")


LINK_SQL = """
WITH pair AS (
  SELECT c.qid, c.rid, c.sim,
    composite_score(q.email, q.username, q.domain, q.servername, q.status, r.email, r.username, r.domain, r.servername, r.status) AS score
  FROM {cand} c JOIN {queries} q USING (qid) JOIN {ref} r ON r.rid = c.rid)
SELECT qid, max_by(rid, struct(score, sim, -rid)) AS rid, max(score) AS score FROM pair GROUP BY qid
"""


def link_sql(cands: DataFrame, queries: DataFrame, ref: DataFrame) -> DataFrame:
    """Verification and choice as one SQL statement over registered functions."""
    from ..functions.similarity import register

    spark = cands.sparkSession
    register(spark)
    return spark.sql(LINK_SQL, cand=cands, queries=queries, ref=ref)
