"""The asynchronous engine: one barrier job in which workers exchange states through a store without waiting.

A put writes a new file and renames it onto the recipient's slot, so a later put overwrites an unread one;
a take reads and removes the slot if there is one, else the worker goes on alone. Results depend on timing.
The barrier only makes all workers run at once; a retried stage starts all of them again from ``w0``.
"""

from __future__ import annotations

import os
import time
import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from gossamer.config import DescentConfig
from gossamer.functions import kernel
from gossamer.sources.shared import shared_dir


class FolderStore:
    """Slots as files of one shared folder (local or mounted)."""

    def __init__(self, folder: str):
        self.folder = folder
        os.makedirs(folder, exist_ok=True)

    def put(self, recipient: int, buffer: int, w: np.ndarray, blocks: np.ndarray) -> None:
        place = f"{self.folder}/{uuid.uuid4().hex}.tmp"
        with open(place, "wb") as f:
            np.savez(f, w=w, blocks=blocks)
        os.replace(place, f"{self.folder}/{recipient}-{buffer}.npz")

    def take(self, worker: int, buffer: int) -> tuple[np.ndarray, np.ndarray] | None:
        own = f"{self.folder}/{uuid.uuid4().hex}.got"
        try:
            os.rename(f"{self.folder}/{worker}-{buffer}.npz", own)
        except FileNotFoundError:
            return None
        with np.load(own) as z:
            got = z["w"], z["blocks"]
        os.remove(own)
        return got


def lined_up(drawn: DataFrame, cfg: DescentConfig) -> DataFrame:
    """Each worker's samples in a partition of their own, in order: what may be placed before a run is timed."""
    return drawn.select("worker", "round", "slot", "x").repartitionById(cfg.workers, "worker").sortWithinPartitions("worker", "round", "slot")


def mailbox_run(drawn: DataFrame, cfg: DescentConfig, w0: list, placed: bool = False) -> DataFrame:
    """Final states of a run over ``worker, round, slot, x``; needs a task slot for every worker. ``placed``: already ``lined_up``."""
    from gossamer.operators.descent import STATE

    spark = drawn.sparkSession
    if spark.sparkContext.defaultParallelism < cfg.workers:
        raise ValueError("the mailbox engine needs as many task slots as workers")
    where = shared_dir(spark)
    if not where.startswith(("file:", "/")):
        raise ValueError("FolderStore needs a folder that executors can open; use the superstep engine elsewhere")
    folder = f"{where.removeprefix('file://').removeprefix('file:')}/mail-{uuid.uuid4().hex}"
    lined = drawn if placed else lined_up(drawn, cfg)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rng, store = np.random.default_rng(), FolderStore(folder)
        w, worker, sent, received, good, held, now = np.asarray(w0, dtype=np.float64), None, 0, 0, 0, [], None

        def one() -> None:
            nonlocal w, sent, received, good
            g = kernel.gradient(np.concatenate(held), w, cfg.reduce, cfg.normalise, cfg.loss)
            mail = [m for buffer in range(cfg.buffers) if cfg.comm != "silent" and (m := store.take(worker, buffer))]
            modified, n = kernel.step(w, g, mail, cfg.eps, cfg.window, cfg.window_scope, cfg.empty_rule)
            received, good = received + len(mail), good + n
            w = kernel.apply(w, g, modified, cfg.eps, cfg.blend_gain)
            if cfg.comm != "silent" and (now + 1) % cfg.comm_every == 0:
                for to in rng.choice(cfg.workers - 1, cfg.fanout, replace=False):
                    share = np.zeros(cfg.k, bool)
                    share[rng.choice(cfg.k, max(1, round(cfg.block_frac * cfg.k)), replace=False)] = True
                    store.put(int(to) + (to >= worker), int(rng.integers(cfg.buffers)), w, share)
                    sent += 1

        over = None if cfg.stop.max_seconds is None else time.monotonic() + cfg.stop.max_seconds
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column(3).flatten().to_numpy().reshape(batch.num_rows, -1)
            who, when = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            cuts = [0, *(np.flatnonzero((np.diff(who) != 0) | (np.diff(when) != 0)) + 1).tolist(), len(who)]
            for a, b in zip(cuts, cuts[1:], strict=False):
                if held and when[a] != now:
                    if over is not None and time.monotonic() >= over:
                        continue  # the state as it is; the rest of the samples is left
                    one()
                    held.clear()
                worker, now = int(who[a]), int(when[a])
                held.append(x[a:b])
        if held:
            one()
            yield pa.RecordBatch.from_arrays([pa.array([worker], pa.int32()), pa.array([w.tolist()], pa.list_(pa.list_(pa.float64()))), *[pa.array([v], pa.int64()) for v in (sent, received, good)]], ["worker", "w", "sent", "received", "good"])

    return lined.mapInArrow(run, STATE, barrier=True)
