"""The whole index in one object: fitted pivots and hashes, blocks, directory, and its two ways of searching."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.linalg import norm
from ..sources.storage import settle
from . import best, fastmap, lsh, search
from . import blocks as B


@dataclass
class GroupIndex:
    d: int
    pivots: list
    directions: tuple
    width: float
    bits: int
    rows_per_block: int
    buckets: int
    blocks: DataFrame
    directory: DataFrame
    mode: str
    variant: str
    longest: float
    packs: DataFrame | None = None
    held: DataFrame | None = None

    @staticmethod
    def build(groups: DataFrame, d: int, axes: int = 4, n_hash: int = 4, bits: int = 8, width: float | None = 0.25, rows_per_block: int = 256, buckets: int = 1024, seed: int = 3, mode: str = "mips", variant: str = "standard", distributed: bool = True) -> "GroupIndex":
        """groups: (g, vec). Pivots are chosen on all groups; only their few vectors reach the driver.

        width None fits the cells to the groups, so that every hash uses all of them.
        """
        wide = d + (mode == "mips")
        mapped, _ = fastmap.to_distance(groups, groups.select(F.col("g").alias("v"), "vec").limit(0), d, mode)
        mapped = settle(mapped, "mapped")
        pivots = fastmap.choose_pivots(mapped, axes, wide)
        hashes = lsh.directions(n_hash, len(pivots), seed)
        points = fastmap.project(mapped, pivots, wide, variant)
        if width is None:
            points = settle(points.select("g", "xs"), "points")
            hashes, width = lsh.fitted(points, hashes[0], bits), 1.0
        keyed = settle(lsh.keyed(points, *hashes, width, bits).select("z", "g"), "keys").join(groups.select("g", "vec"), "g").select("z", "g", "vec")
        laid = settle(B.build_blocks(keyed, rows_per_block, distributed), "blocks")
        directory = settle(B.build_directory(laid, buckets), "directory")
        longest = groups.agg(F.max(norm(F.col("vec"), d))).first()[0] or 0.0
        return GroupIndex(d, pivots, hashes, width, bits, rows_per_block, buckets, laid, directory, mode, variant, longest)

    def keys(self, items: DataFrame) -> DataFrame:
        """(v, vec, z): items under the stored pivots and hashes; vec stays the one that scores.

        Keys are long expressions, so they are written out once rather than repeated in every branch of a search.
        """
        mapped = items.select("v", fastmap.scaled(F.lit(self.longest), self.d)) if self.mode == "mips" else items.select("v", "vec")
        points = fastmap.project(mapped, self.pivots, self.d + (self.mode == "mips"), self.variant)
        found = lsh.keyed(points, *self.directions, self.width, self.bits).select("v", "z")
        return settle(found.join(items.select("v", "vec"), "v"), "asked")

    def packed(self) -> DataFrame:
        """The blocks with their summaries, one row for each; written out when first asked for."""
        if self.packs is None:
            self.packs = settle(best.pack(self.blocks), "packs")
        return self.packs

    def update(self, changed: DataFrame) -> None:
        """Changed and new groups (g, vec) for the search by blocks: only the blocks that they leave or enter are written anew."""
        held = self.blocks.select("g", "block") if self.held is None else self.held
        self.packs, self.held = best.update(self.packed(), held, changed, self.rows_per_block)

    def top_k(self, items: DataFrame, k: int, budget: int, on_miss: str = "nearest") -> DataFrame:
        """Directory, then scan, then exact scores. on_miss 'scan' goes by the blocks' summaries: an item's own key is rarely
        among the groups' keys, so that says more about where its groups are than the neighbours of a place do."""
        if on_miss == "scan":
            return best.top_k(self.packed(), items, k, budget, self.rows_per_block)
        asked = self.keys(items)
        found = search.probe(search.cluster_items(asked), self.directory, self.buckets, on_miss)
        return search.best_around(found, self.blocks, asked, budget, k)

    def tree_top_k(self, items: DataFrame, k: int, budget: int) -> DataFrame:
        """The tree-keyed baseline: the same scan, placed by ordered search."""
        asked = self.keys(items)
        found = search.tree_probe(search.cluster_items(asked), self.blocks)
        return search.best_around(found, self.blocks, asked, budget, k)
