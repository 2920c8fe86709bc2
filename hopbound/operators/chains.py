"""Chains of events in time, counted without listing them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def two_hop_chains(events: DataFrame, wide: int) -> DataFrame:
    """(a, paths): per user a the chains a, b, c of events (at, user_id) with each event later than the one before, by `wide` at most, and three different users.

    Stretches of twice `wide` are counted on their own, each with the events up to twice `wide` after it, so that every chain lies in the
    stretch of its first event. Work and memory go with the events, whatever the number of chains.
    """
    span = 2 * wide
    p = events.where("at IS NOT NULL AND user_id IS NOT NULL").select("at", "user_id")
    bin_ = F.floor(F.col("at") / F.lit(span))
    each = p.select("at", "user_id", bin_.alias("own"), F.explode(F.array(bin_, bin_ - 1)).alias("bin"))

    def count(part: pd.DataFrame) -> pd.DataFrame:
        first = (part["own"] == part["bin"]).to_numpy()
        if not first.any():
            return pd.DataFrame({"a": pd.Series(dtype="int64"), "paths": pd.Series(dtype="int64")})
        names, user = np.unique(part["user_id"].to_numpy(), return_inverse=True)
        paths = chains_from(part["at"].to_numpy(), user, first, wide)
        total = np.zeros(len(names), np.int64)
        np.add.at(total, user[first], paths)
        met = total > 0
        return pd.DataFrame({"a": names[met], "paths": total[met]})

    return each.groupBy("bin").applyInPandas(count, "a long, paths long").groupBy("a").agg(F.sum("paths").alias("paths"))


def chains_from(at: np.ndarray, user: np.ndarray, first: np.ndarray, wide: int) -> np.ndarray:
    """Chains that begin with each event flagged in `first`; users are numbers from 0.

    Of the events b that may follow a, and the c that may follow each, those with a repeated user are taken off: c with b's user, b with
    a's user, c with a's user. All are differences of prefix sums in order of time, over all events and over those of one user.
    """
    at = at - at.min()
    order = np.argsort(at, kind="stable")
    time = at[order]
    reach = np.int64(time[-1] + wide + 1)  # later than every time that is asked for
    by_user = np.lexsort((at, user))
    keys = user[by_user].astype(np.int64) * (2 * reach) + at[by_user]

    def upto(t: np.ndarray) -> np.ndarray:
        return np.searchsorted(time, t, "right")

    def own_upto(u: np.ndarray, t: np.ndarray) -> np.ndarray:
        """Place in order of user and time behind the events of u up to t; no event has a negative time, so t below 0 is before u's first."""
        return np.searchsorted(keys, u.astype(np.int64) * (2 * reach) + np.maximum(t, -1), "right")

    def sums(x: np.ndarray) -> np.ndarray:
        return np.concatenate(([0], np.cumsum(x, dtype=np.int64)))

    # c after each b, of other users than b
    after = (upto(at + wide) - upto(at)) - (own_upto(user, at + wide) - own_upto(user, at))
    every, own = sums(after[order]), sums(after[by_user])
    a, u = at[first], user[first]
    lo, mid, hi = own_upto(u, a), own_upto(u, a + wide), own_upto(u, a + 2 * wide)
    total = (every[upto(a + wide)] - every[upto(a)]) - (own[mid] - own[lo])
    # less the c of a's user: b of other users lie after a and before c, but within `wide` of both
    ct, cu = at[by_user], user[by_user]
    before = sums(upto(ct - 1) - own_upto(cu, ct - 1))
    early = sums(upto(ct - wide - 1) - own_upto(cu, ct - wide - 1))
    near = (before[mid] - before[lo]) - (mid - lo) * (upto(a) - own_upto(u, a))
    far = (hi - mid) * (upto(a + wide) - own_upto(u, a + wide)) - (early[hi] - early[mid])
    return total - near - far
