"""The loops of `Loops.java`, run on large models by the Java that Spark needs on each machine anyway.

A loop gets its arrays in a file of the temp folder that both processes map, so they are not held twice; a greedy gets its rows
by a pipe. Where there is no Java compiler, or with CUTSTREAM_JAVA=0, `classes` is None and the same loops run in Python
(kernel.py), with the same results.
"""

from __future__ import annotations

import functools
import hashlib
import os
import shutil
import stat
import subprocess
import tempfile
from importlib import resources

import numpy as np

#: Vertices and half-edges from which on a loop is worth a process.
LARGE = 1 << 18
#: Bytes of an array that Java maps at once.
MOST = (1 << 31) - 64
KINDS = {np.dtype(np.uint8): 0, np.dtype(np.float32): 1, np.dtype(np.float64): 2}
OPTIONS = ("-XX:+UseSerialGC", "-XX:-UsePerfData", "-XX:ActiveProcessorCount=2", "-Xms16m", "-Xmx1g")


def _tool(name: str) -> str | None:
    home = os.environ.get("JAVA_HOME")
    return (shutil.which(os.path.join(home, "bin", name)) if home else None) or shutil.which(name)


def _own_folder() -> str:
    """A folder of the temp folder that no other user can have put files into."""
    at = os.path.join(tempfile.gettempdir(), f"cutstream-loops-{os.getuid()}")
    os.makedirs(at, mode=0o700, exist_ok=True)
    found = os.lstat(at)
    if stat.S_ISDIR(found.st_mode) and found.st_uid == os.getuid() and not found.st_mode & 0o022:
        return at
    return tempfile.mkdtemp(prefix="cutstream-loops-")


@functools.cache
def classes() -> str | None:
    """The folder of the compiled loops; None where they can't be had."""
    compiler = _tool("javac")
    if os.environ.get("CUTSTREAM_JAVA") == "0" or not compiler or not _tool("java"):
        return None
    try:
        source = resources.files("cutstream.plans").joinpath("Loops.java").read_bytes()
        folder = _own_folder()
        at = os.path.join(folder, hashlib.sha256(source).hexdigest()[:24])
        if not os.path.isdir(at):
            made = tempfile.mkdtemp(dir=folder)
            with open(os.path.join(made, "Loops.java"), "wb") as f:
                f.write(source)
            subprocess.run([compiler, "-J-XX:-UsePerfData", "-J-Xmx256m", "-d", made, os.path.join(made, "Loops.java")], check=True, capture_output=True, timeout=120)
            try:
                os.rename(made, at)
            except OSError:  # another worker was first
                shutil.rmtree(made, ignore_errors=True)
        return at
    except (OSError, subprocess.SubprocessError):
        return None


def worth(size: int) -> bool:
    """Whether a loop over so many vertices and half-edges runs in Java."""
    return size >= LARGE and classes() is not None


def known(state) -> bool:
    """Whether the loops score blocks as state does."""
    return state.whole and (state.discount or state.root)


def _command(loop: str, *args) -> list[str]:
    return [_tool("java"), *OPTIONS, "-cp", classes(), "Loops", loop, *map(str, args)]


class _Job:
    """Arguments and arrays of a loop; `run` gives the arrays as the loop left them, None if it failed."""

    def __init__(self, *numbers):
        self.args, self.parts, self.size = list(numbers), [], 0

    def numbers(self, *x) -> _Job:
        self.args += x
        return self

    def array(self, x, kind=None, length: int | None = None) -> _Job:
        """An array of a kind; or room for `length` items, of which the first are x."""
        x = np.asarray(x, kind)
        size = max(8, x.itemsize * (len(x) if length is None else length))
        self.args.append(f"{self.size}:{size}")
        self.parts.append((self.size, size, x))
        self.size += size + -size % 8
        return self

    def weights(self, x) -> _Job:
        x = x if np.asarray(x).dtype in KINDS else np.asarray(x, np.float64)
        return self.numbers(KINDS[x.dtype]).array(x)

    def rows(self, ptr, adj, w) -> _Job:
        return self.array(ptr, np.int32).array(adj, np.int32).weights(w)

    def state(self, state) -> _Job:
        p = state.p
        return self.array(state.load, np.float64).numbers(p.k, int(state.discount), int(state.all), repr(float(state.most)), repr(float(state.scale)))

    def run(self, loop: str) -> list[np.ndarray] | None:
        if any(size > MOST for _, size, _ in self.parts):
            return None
        held, at = tempfile.mkstemp(prefix="cutstream-loop-")
        try:
            os.ftruncate(held, max(8, self.size))
            both = np.memmap(at, np.uint8, "r+")
            out = []
            for begin, size, x in self.parts:
                own = both[begin : begin + size].view(x.dtype)
                own[: len(x)] = x
                out.append(own)
            self.parts.clear()
            done = subprocess.run(_command(loop, at, *self.args), stdin=subprocess.DEVNULL, capture_output=True)
            return None if done.returncode else out
        except OSError:
            return None
        finally:
            os.close(held)
            os.unlink(at)


def clusters(g, rounds: int, most: float, keyed: list[int], mix: tuple[int, ...], random: bool, within: np.ndarray | None) -> np.ndarray | None:
    job = _Job(g.n, rounds, repr(float(most)), int(random), *mix).array(keyed, np.int64).rows(g.ptr, g.adj, g.w).weights(g.weight).numbers(int(within is not None))
    if within is not None:
        job.array(within, np.int32)
    none = np.zeros(0)
    out = job.array(none, np.int32, g.n).array(none, np.float64, g.n).array(none, np.uint8, g.n).run("clusters")
    return out and np.array(out[-3][: g.n])


def _made(out: list[np.ndarray] | None, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    """ptr, neighbours and weights of a made graph, as they lie in the file."""
    if out is None:
        return None
    ptr, adj, w = out[-3:]
    return np.array(ptr[: n + 1]), adj[: ptr[n]], w[: ptr[n]]


def contracted(g, to: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    first, none, most = np.cumsum(np.bincount(to, minlength=n)), np.zeros(0), len(g.adj)
    first = np.concatenate([[0], first[:-1]])
    job = _Job(g.n, n).rows(g.ptr, g.adj, g.w).array(to, np.int32).array(first, np.int32).array(none, np.int32, g.n)
    return _made(job.array([0], np.int32, n + 1).array(none, np.int32, most).array(none, np.float64, most).run("contracted"), n)


def joined(n: int, a: np.ndarray, b: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray] | None:
    none, most = np.zeros(0), 2 * len(a)
    job = _Job(n, len(a)).array(a, np.int32).array(b, np.int32).weights(w).array(none, np.int32, n).array(none, np.int32, most)
    return _made(job.array([0], np.int32, n + 1).array(none, np.int32, most).array(none, np.float64, most).run("joined"), n)


def placed(g, conn, state, start: np.ndarray) -> np.ndarray | None:
    out = _Job(g.n).state(state).rows(g.ptr, g.adj, g.w).rows(conn.ptr, conn.block, conn.w).weights(g.weight).array(start, np.int32).run("placed")
    return _taken(state, out, -1, g.n)


def searched(g, block: np.ndarray, conn, state, rounds: int) -> np.ndarray | None:
    job = _Job(g.n, rounds).state(state).rows(g.ptr, g.adj, g.w).rows(conn.ptr, conn.block, conn.w).weights(g.weight).array(block, np.int32)
    return _taken(state, job.array(np.zeros(0), np.uint8, g.n).run("searched"), -2, g.n)


def _taken(state, out: list[np.ndarray] | None, at: int, n: int) -> np.ndarray | None:
    """The blocks of n vertices; state takes the loads."""
    if out is None:
        return None
    state.set_loads(out[0][: state.p.k].tolist())
    return np.array(out[at][:n])


class Greedy:
    """A one-vertex-at-a-time greedy over n vertices: rows (position, neighbour or -1, weight, block) in, placed vertices out."""

    def __init__(self, state, n: int):
        p = state.p
        self.run = subprocess.Popen(_command("greedy", "-", n, p.k, int(state.discount), int(state.all), repr(float(state.most)), repr(float(state.scale))), stdin=subprocess.PIPE, stdout=subprocess.PIPE)

    def __enter__(self) -> Greedy:
        return self

    def __exit__(self, *_) -> None:
        self.run.kill()
        self.run.communicate()

    def rows(self, *columns: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(vertex, block, fits) of those that are complete with these rows; without any, of the one that is still open."""
        pos, nbr, w, block = columns or ((),) * 4
        self.run.stdin.write(np.int32(len(pos) if columns else -1).tobytes())
        for x, kind in ((w, np.float64), (pos, np.int32), (nbr, np.int32), (block, np.int32)):
            self.run.stdin.write(np.asarray(x, kind).tobytes())
        self.run.stdin.flush()
        head = self.run.stdout.read(4)
        out = np.frombuffer(self.run.stdout.read(8 * int.from_bytes(head, "little")), np.int32).reshape(-1, 2)
        if len(head) < 4:
            raise RuntimeError("the process of the greedy ended")
        return out[:, 0].astype(np.int64), np.where(out[:, 1] < 0, ~out[:, 1], out[:, 1]), out[:, 1] >= 0
