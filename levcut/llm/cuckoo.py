"""Cuckoo filter over digests, with the keys kept beside it in buckets."""

from __future__ import annotations


class CuckooIndex:
    """Maps live digests to records.

    A filter of four-slot buckets holds one 16-bit tag for each live digest.
    A lookup that finds no tag is a certain miss. A hit is only a candidate:
    it is verified against the whole digests that the slots of the bucket
    store. When an insertion can't place a tag within ``max_kicks`` moves,
    the filter doubles and is rebuilt from the stored keys, so nothing is lost.
    Deleting a digest frees its slot.
    """

    SLOTS = 4

    def __init__(self, capacity: int = 1024, max_kicks: int = 128):
        self.max_kicks = max_kicks
        self.resizes = 0
        self._allocate(max(2, 1 << max(1, (capacity // self.SLOTS - 1).bit_length())))

    def _allocate(self, buckets: int) -> None:
        self.mask = buckets - 1
        self.tags: list[list[int]] = [[] for _ in range(buckets)]
        self.keys: list[list[bytes]] = [[] for _ in range(buckets)]
        self.values: list[list[object]] = [[] for _ in range(buckets)]
        self.size = 0

    def _place(self, digest: bytes) -> tuple[int, int]:
        """Tag and first bucket. Digests are uniform, so their bytes are the hash."""
        return int.from_bytes(digest[:2], "little") or 1, int.from_bytes(digest[2:10], "little") & self.mask

    def _other(self, bucket: int, tag: int) -> int:
        return bucket ^ (((tag * 0x5BD1E995) >> 3) & self.mask)

    def _find(self, digest: bytes) -> tuple[int, int] | None:
        tag, first = self._place(digest)
        for bucket in (first, self._other(first, tag)):
            if tag in self.tags[bucket]:
                for slot, key in enumerate(self.keys[bucket]):
                    if key == digest:
                        return bucket, slot
        return None

    def get(self, digest: bytes):
        at = self._find(digest)
        return None if at is None else self.values[at[0]][at[1]]

    def __contains__(self, digest: bytes) -> bool:
        return self._find(digest) is not None

    def __len__(self) -> int:
        return self.size

    def insert(self, digest: bytes, value: object) -> None:
        """Adds a digest, or replaces the record of one that is live."""
        at = self._find(digest)
        if at is not None:
            self.values[at[0]][at[1]] = value
            return
        while (left := self._put(digest, value)) is not None:
            digest, value = left
            self._grow()

    def _put(self, digest: bytes, value: object) -> tuple[bytes, object] | None:
        """None, or the record that found no slot."""
        tag, bucket = self._place(digest)
        other = self._other(bucket, tag)
        if len(self.tags[bucket]) >= self.SLOTS and len(self.tags[other]) < self.SLOTS:
            bucket = other
        for kick in range(self.max_kicks):
            tags, keys, values = self.tags[bucket], self.keys[bucket], self.values[bucket]
            if len(tags) < self.SLOTS:
                tags.append(tag)
                keys.append(digest)
                values.append(value)
                self.size += 1
                return None
            slot = kick % self.SLOTS
            tags[slot], tag = tag, tags[slot]
            keys[slot], digest = digest, keys[slot]
            values[slot], value = value, values[slot]
            bucket = self._other(bucket, tag)
        return digest, value

    def _grow(self) -> None:
        old = list(self.items())
        buckets = 2 * (self.mask + 1)
        self.resizes += 1
        while True:
            self._allocate(buckets)
            if all(self._put(key, value) is None for key, value in old):
                return
            buckets *= 2

    def delete(self, digest: bytes) -> bool:
        at = self._find(digest)
        if at is None:
            return False
        bucket, slot = at
        for column in (self.tags, self.keys, self.values):
            column[bucket][slot] = column[bucket][-1]
            column[bucket].pop()
        self.size -= 1
        return True

    def items(self):
        for keys, values in zip(self.keys, self.values, strict=True):
            yield from zip(keys, values, strict=True)
