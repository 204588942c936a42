"""Why a partial assignment fails, as bits of pattern positions (bit i: position i of the order)."""

from __future__ import annotations


def reason_wipeout(nbr_mask: int, mapped: int) -> int:
    """An unmapped vertex has no candidate: its mapped neighbours."""
    return nbr_mask & mapped


def reason_reuse(holder: int, current: int) -> int:
    """Two positions hold one data vertex: both."""
    return 1 << holder | 1 << current


def fold_reason(union: int, current: int, nbr_mask: int, mapped: int) -> int:
    """The parent's reason from its children's: if they name the position just tried, its candidates
    were bounded by its mapped neighbours, which join the reason in its stead."""
    return (union | nbr_mask) & mapped if union >> current & 1 else union


def prefix_length(reason: int, key_pos: int) -> int:
    """Length of the shortest prefix that holds every position of the reason but the key's."""
    return (reason & ~(1 << key_pos)).bit_length()
