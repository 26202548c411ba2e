"""What a worker remembers of words: each distinct word's properties are worked out once."""

from __future__ import annotations

from collections.abc import Callable
from itertools import islice, repeat

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class WordTable:
    """Word to place, and a row of numbers for each place; beyond `most` words only those met first, the frequent ones, stay."""

    def __init__(self, width: int, describe: Callable[[str], tuple], most: int = 100_000):
        self.places: dict[str, int] = {}
        self.describe, self.most, self.rows = describe, most, np.zeros((1024, width), np.float32)

    def look_up(self, words: list[str]) -> np.ndarray:
        """The places of words; their rows are self.rows[places]."""
        if len(self.places) > self.most:
            self.places = dict(islice(self.places.items(), self.most // 3))
        found = np.fromiter(map(self.places.get, words, repeat(-1)), np.int64, len(words))
        for k in np.flatnonzero(found < 0).tolist():
            w = words[k]
            at = self.places.get(w)
            if at is None:
                at = self.places[w] = len(self.places)
                if at >= len(self.rows):
                    self.rows = np.concatenate([self.rows, np.zeros_like(self.rows)])
                self.rows[at] = self.describe(w)
            found[k] = at
        return found


def sampled(ids: DataFrame, most: int) -> DataFrame:
    """Up to `most` distinct doc_ids, those with the least hashes: the same ones however rows are dealt."""
    distinct = ids.select("doc_id").where("doc_id is not null").distinct()
    return distinct.orderBy(F.xxhash64("doc_id", F.lit("sample")), "doc_id").limit(most)


def part_of(doc_id: Column, parts: int) -> Column:
    """crc32 of the id as text modulo parts; -1 for null ids."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % parts, F.lit(-1))
