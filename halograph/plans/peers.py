"""Messages between the tasks of a barrier stage, from executor to executor. The driver only learns where each task listens.

Pushes go through a thread of their own, so they travel while the next step is computed; gradients go through a binomial tree. A message is
a head and the raw bytes of its arrays. If a task dies, its peers run into the time limit or a closed connection and fail as well, and
Spark runs the whole stage again, with new connections."""

from __future__ import annotations

import queue
import socket
import struct
import threading
import time
from collections.abc import Callable

import numpy as np

PUSH, UP, DOWN = 1, 2, 3
HEAD = struct.Struct("<iiiiqqi2s")  # kind, iteration, layer, sender, ids, values, width, type
LIMIT_SECONDS = 900


class Peers:
    """One task's connections. gather: a string of each task to all tasks, in order of tasks; token: shared by the stage's tasks."""

    def __init__(self, me: int, hosts: list[str], gather: Callable[[str], list[str]], token: bytes) -> None:
        self.me, self.n, self.token = me, len(hosts), token
        self.listener = socket.create_server(("", 0), backlog=2 * self.n + 8)
        ports = gather(str(self.listener.getsockname()[1]))
        self.where = [(h, int(p)) for h, p in zip(hosts, ports, strict=True)]
        self.came: dict[tuple[int, int, int, int], tuple[np.ndarray, np.ndarray]] = {}
        self.news = threading.Condition()
        self.broken: Exception | None = None
        self.closed = False
        self.out: dict[tuple[int, bool], socket.socket] = {}
        self.waiting: queue.Queue = queue.Queue()
        self.send_seconds = 0.0
        self.lock = threading.Lock()
        for run in (self._accept, self._push):
            threading.Thread(target=run, daemon=True).start()

    # --- receiving -------------------------------------------------------------------------------------------------------------

    def _accept(self) -> None:
        while not self.closed:
            try:
                s, _ = self.listener.accept()
            except OSError:
                return
            threading.Thread(target=self._read, args=(s,), daemon=True).start()

    def _read(self, s: socket.socket) -> None:
        try:
            if self._exactly(s, len(self.token)) != self.token:
                s.close()
                return
            while (head := self._exactly(s, HEAD.size)) is not None:
                kind, it, layer, sender, n_ids, n, width, code = HEAD.unpack(head)
                ids = np.frombuffer(self._exactly(s, 8 * n_ids), np.int64)
                dtype = np.dtype(code.decode())
                rows = np.frombuffer(self._exactly(s, n * dtype.itemsize), dtype)
                with self.news:
                    self.came[kind, it, layer, sender] = (ids, rows.reshape(-1, width) if width else rows)
                    self.news.notify_all()
        except Exception as e:  # noqa: BLE001 - told to whoever waits
            if not self.closed:
                with self.news:
                    self.broken = e
                    self.news.notify_all()

    @staticmethod
    def _exactly(s: socket.socket, n: int) -> bytes | None:
        """n bytes; None where the sender closed before the first."""
        out = bytearray(n)
        view, got = memoryview(out), 0
        while got < n:
            k = s.recv_into(view[got:])
            if not k:
                if got:
                    raise ConnectionError("a peer closed within a message")
                return None
            got += k
        return bytes(out)

    def get(self, kind: int, it: int, layer: int, sender: int) -> tuple[np.ndarray, np.ndarray]:
        key, until = (kind, it, layer, sender), time.monotonic() + LIMIT_SECONDS
        with self.news:
            while key not in self.came:
                if self.broken is not None:
                    raise RuntimeError("a peer failed") from self.broken
                if not self.news.wait(max(0.0, until - time.monotonic())) and time.monotonic() > until:
                    raise TimeoutError(f"no message {key}")
            return self.came.pop(key)

    # --- sending ---------------------------------------------------------------------------------------------------------------

    def _send(self, to: int, kind: int, it: int, layer: int, ids: np.ndarray, rows: np.ndarray) -> None:
        lane = (to, kind == PUSH)
        if lane not in self.out:
            s = socket.create_connection(self.where[to], timeout=LIMIT_SECONDS)
            s.setsockopt(socket.IPPROTO_TCP, socket.TCP_NODELAY, 1)
            s.sendall(self.token)
            self.out[lane] = s
        width = rows.shape[1] if rows.ndim == 2 else 0
        head = HEAD.pack(kind, it, layer, self.me, len(ids), rows.size, width, rows.dtype.str[1:].encode())
        self.out[lane].sendall(b"".join([head, np.ascontiguousarray(ids, np.int64).tobytes(), np.ascontiguousarray(rows).tobytes()]))

    def _push(self) -> None:
        while (item := self.waiting.get()) is not None:
            began = time.perf_counter()
            try:
                self._send(*item)
            except Exception as e:  # noqa: BLE001 - told to whoever waits
                if not self.closed:
                    with self.news:
                        self.broken = e
                        self.news.notify_all()
                return
            with self.lock:
                self.send_seconds += time.perf_counter() - began

    def push(self, to: int, it: int, layer: int, ids: np.ndarray, rows: np.ndarray) -> None:
        """Send in the background."""
        self.waiting.put((to, PUSH, it, layer, ids, rows))

    def take_send_seconds(self) -> float:
        with self.lock:
            out, self.send_seconds = self.send_seconds, 0.0
        return out

    def allreduce(self, it: int, values: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The sums over all tasks of an array and of whole numbers: up and down a binomial tree, so no task takes part in more exchanges
        than the logarithm of the number of tasks."""
        low = (self.me & -self.me) or 1 << (self.n - 1).bit_length()
        below = [1 << k for k in range(low.bit_length() - 1) if self.me + (1 << k) < self.n]
        for s in below:
            c, v = self.get(UP, it, 0, self.me + s)
            values, counts = values + v, counts + c
        if self.me:
            self._send(self.me - low, UP, it, 0, counts, values)
            counts, values = self.get(DOWN, it, 0, self.me - low)
        for s in reversed(below):
            self._send(self.me + s, DOWN, it, 0, counts, values)
        return values, counts

    def close(self) -> None:
        self.closed = True
        self.waiting.put(None)
        for s in (self.listener, *self.out.values()):
            try:
                s.close()
            except OSError:
                pass
