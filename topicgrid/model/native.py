"""A whole fit in a process of its own beside the worker, in Java, which every worker of Spark has.

The driver compiles ``Fit`` for a number of topics with Spark's own compiler and ships the class with the task. The process talks over its
pipes, holds 9 bytes a token and the counts, and makes the operations of ``kernel`` on the same doubles in the same order, with numpy's
numbers and permutations, so its draws are those of the loops in Python to the bit (tested). Those loops run where the driver can't compile it.
"""

from __future__ import annotations

import os
import shutil
import struct
import subprocess
import tempfile
from collections.abc import Iterable
from functools import cache
from pathlib import Path

import numpy as np

MOST_TOPICS = 128  # topics are bytes, sums of a token local variables
PIECE = 1 << 17  # numbers sent at once


def source(topics: int) -> str:
    every = range(topics)
    sums = lambda scale: "".join(f"double c{k} = {f'c{k - 1} + ' if k else ''}(theta[d + {k}] + alpha) * (phi[w + {k}] + beta) / {scale}[{k}];\n" for k in every)
    weights = "".join(f"double v{k} = (theta[d + {k}] + alpha) * (phi[w + {k}] + beta) / s[{k}];\n" for k in every)
    own = "switch (old) {\n" + "".join(f"case {k}: v{k} = ((theta[d + {k}] + alpha) - 1.0) * ((phi[w + {k}] + beta) - 1.0) / (s[{k}] - 1.0); break;\n" for k in every) + "}\n"
    running = "".join(f"double c{k} = {f'c{k - 1} + ' if k else ''}v{k};\n" for k in every)
    found = f"double x = u * c{topics - 1};\nint k = " + " + ".join(f"(c{k} <= x ? 1 : 0)" for k in every) + f";\nif (k == {topics}) k = {topics - 1};\n"
    return (
        JAVA.replace("@K@", str(topics)).replace("@SUMS@", sums("s")).replace("@WEIGHTS@", weights + own + running).replace("@FOUND@", found)
        .replace("@LIKE@", " + ".join(f"(theta[d + {k}] + alpha) * (phi[w + {k}] + beta) * s[{k}]" for k in every))
    )


JAVA = r"""
import java.io.FileDescriptor;
import java.io.FileInputStream;
import java.io.FileOutputStream;
import java.io.IOException;
import java.nio.ByteBuffer;
import java.nio.ByteOrder;
import java.nio.channels.FileChannel;
import java.util.Arrays;

public class Fit {
    static final int K = @K@;
    static FileChannel in, out;
    static ByteBuffer room = ByteBuffer.allocateDirect(1 << 20).order(ByteOrder.LITTLE_ENDIAN);
    static double alpha;
    static int[] theta;
    static int documents;
    static Part[] parts = new Part[2];
    static int round;
    static int[] row = new int[0], col = new int[0];  // the last round that a row or column was met in
    static double[] us = new double[0];

    static double[] room(int n) {
        if (us.length < n) {
            us = null;
            us = new double[n];
        }
        return us;
    }

    static class Part {
        int words, n, groups;
        double beta;
        int[] rows, cols, phi, base, moved, at;
        byte[] z;
        int[][] order, sizes;
        int[] cut;
        long[] totals = new long[K], own = new long[K], change = new long[K];
    }

    static void fill(int bytes) throws IOException {
        room.clear().limit(bytes);
        while (room.hasRemaining())
            if (in.read(room) < 0) throw new IOException("the worker has ended");
        room.flip();
    }

    static void send() throws IOException {
        room.flip();
        while (room.hasRemaining()) out.write(room);
    }

    static void ints(int[] x, int from, int n) throws IOException {
        for (int some; n > 0; from += some, n -= some) {
            some = Math.min(n, 1 << 18);
            fill(4 * some);
            room.asIntBuffer().get(x, from, some);
        }
    }

    static void bytes(byte[] x, int from, int n) throws IOException {
        for (int some; n > 0; from += some, n -= some) {
            some = Math.min(n, 1 << 20);
            fill(some);
            room.get(x, from, some);
        }
    }

    static void doubles(double[] x, int from, int n) throws IOException {
        for (int some; n > 0; from += some, n -= some) {
            some = Math.min(n, 1 << 17);
            fill(8 * some);
            room.asDoubleBuffer().get(x, from, some);
        }
    }

    static void give(int[] x) throws IOException {
        for (int from = 0; from < x.length; from += 1 << 18) {
            int some = Math.min(x.length - from, 1 << 18);
            room.clear();
            room.asIntBuffer().put(x, from, some);
            room.position(4 * some);
            send();
        }
    }

    static void loop(Part p, int[] order, int shift, int from, int to, int first, double[] us, double[] s) {
        int[] theta = Fit.theta, phi = p.phi, rows = p.rows, cols = p.cols;
        byte[] z = p.z;
        long[] totals = p.own;
        double alpha = Fit.alpha, beta = p.beta, scale = p.words * p.beta;
        for (int t = from; t < to; t++) {
            int d = rows[t] * K, w = cols[t] * K, old = z[t];
            double u = us[order == null ? t - first : order[t - shift]];
            theta[d + old]--;
            phi[w + old]--;
            totals[old]--;
            s[old] = totals[old] + scale;
            @SUMS@
            @FOUND@
            z[t] = (byte) k;
            theta[d + k]++;
            phi[w + k]++;
            totals[k]++;
            s[k] = totals[k] + scale;
        }
    }

    static void step(Part p, int[] order, int shift, int from, int to, double[] us, double[] s) {
        int[] theta = Fit.theta, phi = p.phi, rows = p.rows, cols = p.cols;
        byte[] z = p.z;
        long[] totals = p.own;
        double alpha = Fit.alpha, beta = p.beta;
        for (int t = from; t < to; t++) {
            int d = rows[t] * K, w = cols[t] * K, old = z[t];
            double u = us[order[t - shift]];
            @WEIGHTS@
            @FOUND@
            z[t] = (byte) k;
            theta[d + old]--;
            phi[w + old]--;
            totals[old]--;
            theta[d + k]++;
            phi[w + k]++;
            totals[k]++;
        }
    }

    static double like(Part p) {
        int[] theta = Fit.theta, phi = p.phi, rows = p.rows, cols = p.cols;
        double alpha = Fit.alpha, beta = p.beta, sum = 0;
        double[] s = new double[K];
        double[] size = new double[documents];
        for (int i = 0; i < documents; i++) {
            long c = 0;
            for (int k = 0; k < K; k++) c += theta[i * K + k];
            size[i] = Math.log(c + K * alpha);
        }
        for (int k = 0; k < K; k++) s[k] = 1.0 / (p.totals[k] + p.words * beta);
        for (int at = 0; at < p.n; at += 65536) {
            double some = 0;
            for (int t = at, to = Math.min(p.n - at, 65536) + at; t < to; t++) {
                int d = rows[t] * K, w = cols[t] * K;
                some += Math.log(@LIKE@) - size[rows[t]];
            }
            sum += some;
        }
        return sum;
    }

    /* Tokens by block: diagonal, then group of rows, in their order within each. */
    static void deal(Part p, int[] rowGroup, int[] colGroup, boolean replica) {
        int g = p.groups, n = p.n;
        p.at = new int[g * g + 1];
        for (int t = 0; t < n; t++) p.at[block(p, t, rowGroup, colGroup, replica) + 1]++;
        for (int k = 0; k < g * g; k++) p.at[k + 1] += p.at[k];
        p.order = new int[g * g][];
        p.sizes = new int[g * g][];
        p.cut = new int[g * g];
        if (g == 1) return;
        int[] next = (int[]) p.at.clone(), rows = new int[n], cols = new int[n];
        byte[] z = new byte[n];
        for (int t = 0; t < n; t++) {
            int to = next[block(p, t, rowGroup, colGroup, replica)]++;
            rows[to] = p.rows[t];
            cols[to] = p.cols[t];
            z[to] = p.z[t];
        }
        p.rows = rows;
        p.cols = cols;
        p.z = z;
    }

    static int block(Part p, int t, int[] rowGroup, int[] colGroup, boolean replica) {
        int r = rowGroup[p.rows[t]], g = p.groups;
        return replica ? r : (colGroup[p.cols[t]] - r + g) % g * g + r;
    }

    /* The block's tokens from the order given to that of waves, then those without one; order: where each was. */
    static void plan(Part p, int b, int[] order, int look, int thin) {
        int start = p.at[b], n = order.length, done = 0, count = 0, nrest = 0;
        if (row.length < documents || round > 2000000000) row = new int[documents];
        if (col.length < p.words || round > 2000000000) col = new int[p.words];
        if (round > 2000000000) round = 0;
        int[] rows = p.rows, cols = p.cols, row = Fit.row, col = Fit.col, rest = new int[16], sizes = new int[16];
        int[] left = new int[look], taken = new int[look], spare = new int[look], leftRow = new int[look], leftCol = new int[look];
        for (int at = 0; at < n; at += look) {
            int m = Math.min(n - at, look);
            System.arraycopy(order, at, left, 0, m);
            for (int i = 0; i < m; i++) {
                leftRow[i] = rows[start + left[i]];
                leftCol[i] = cols[start + left[i]];
            }
            while (m > 0) {
                int got = 0, stay = 0;
                round++;
                for (int i = 0; i < m; i++) {
                    int t = left[i], r = leftRow[i], c = leftCol[i];
                    spare[i] = 0;
                    if (row[r] != round) {
                        row[r] = round;
                        if (col[c] != round) {
                            col[c] = round;
                            taken[got++] = t;
                            spare[i] = 1;
                        }
                    }
                }
                if ((long) got * thin < m || (got < 4 && m > 4)) break;
                for (int i = 0; i < m; i++) {
                    if (spare[i] == 1) continue;
                    spare[stay] = left[i];
                    leftRow[stay] = leftRow[i];
                    leftCol[stay++] = leftCol[i];
                }
                int[] swap = left;
                left = spare;
                spare = swap;
                m = stay;
                Arrays.sort(taken, 0, got);
                System.arraycopy(taken, 0, order, done, got);
                done += got;
                if (count == sizes.length) sizes = Arrays.copyOf(sizes, 2 * count);
                sizes[count++] = got;
            }
            if (nrest + m > rest.length) rest = Arrays.copyOf(rest, (int) Math.min(n, 2L * (nrest + m)));
            System.arraycopy(left, 0, rest, nrest, m);
            nrest += m;
        }
        Arrays.sort(rest, 0, nrest);
        p.sizes[b] = Arrays.copyOf(sizes, count);
        p.cut[b] = done;
        p.order[b] = null;
        if (done == 0) return;  // all without a wave, so in the order they are in
        System.arraycopy(rest, 0, order, done, nrest);
        rest = null;
        p.order[b] = order;
        int[] moved = new int[n];
        for (int i = 0; i < n; i++) moved[i] = rows[start + order[i]];
        System.arraycopy(moved, 0, rows, start, n);
        for (int i = 0; i < n; i++) moved[i] = cols[start + order[i]];
        System.arraycopy(moved, 0, cols, start, n);
        for (int i = 0; i < n; i++) moved[i] = p.z[start + order[i]];
        for (int i = 0; i < n; i++) p.z[start + i] = (byte) moved[i];
    }

    static void sweep(Part p, int b, int wide, boolean waves, boolean replica) throws IOException {
        int start = p.at[b], n = p.at[b + 1] - start;
        double[] s = new double[K];
        double scale = p.words * p.beta;
        System.arraycopy(p.totals, 0, p.own, 0, K);
        if (replica && p.base == null) {
            p.base = (int[]) p.phi.clone();
            p.moved = new int[p.phi.length];
        }
        for (int k = 0; k < K; k++) s[k] = p.own[k] + scale;
        int[] order = waves ? p.order[b] : null;
        if (order == null) {
            double[] us = room(Math.min(n, 1 << 17));
            for (int at = 0; at < n; at += 1 << 17) {
                int some = Math.min(n - at, 1 << 17);
                doubles(us, 0, some);
                loop(p, null, 0, start + at, start + at + some, start + at, us, s);
            }
        } else {
            double[] us = room(n);
            doubles(us, 0, n);
            int t = start;
            for (int v = 0; v < p.sizes[b].length; v++)
                for (int left = p.sizes[b][v]; left > 0; left -= wide) {
                    int some = Math.min(left, wide);
                    for (int k = 0; k < K; k++) s[k] = p.own[k] + scale;
                    step(p, order, start, t, t + some, us, s);
                    t += some;
                }
            for (int k = 0; k < K; k++) s[k] = p.own[k] + scale;
            loop(p, order, start, t, start + n, 0, us, s);
        }
        for (int k = 0; k < K; k++) p.change[k] += p.own[k] - p.totals[k];
        if (replica) {
            for (int i = 0; i < p.phi.length; i++) p.moved[i] += p.phi[i] - p.base[i];
            System.arraycopy(p.base, 0, p.phi, 0, p.phi.length);
        }
    }

    static void close(Part p) {
        for (int k = 0; k < K; k++) {
            p.totals[k] += p.change[k];
            p.change[k] = 0;
        }
        if (p.base == null) return;
        for (int i = 0; i < p.phi.length; i++) p.phi[i] = p.base[i] + p.moved[i];
        p.base = p.moved = null;
    }

    public static void main(String[] args) throws IOException {
        in = new FileInputStream(FileDescriptor.in).getChannel();
        out = new FileOutputStream(FileDescriptor.out).getChannel();
        while (true) {
            fill(64);
            int op = (int) room.getLong(), which = (int) room.getLong();
            int a = (int) room.getLong(), b = (int) room.getLong(), c = (int) room.getLong(), e = (int) room.getLong();
            double x = room.getDouble(), y = room.getDouble();
            Part p = which < 2 ? parts[which] : null;
            if (op == 0) return;
            if (op == 1) {
                documents = a;
                theta = new int[a * K];
                alpha = x;
            } else if (op == 2) {
                p = parts[which] = new Part();
                p.words = a;
                p.n = b;
                p.groups = c;
                p.beta = x;
                p.rows = new int[b];
                p.cols = new int[b];
                p.z = new byte[b];
                p.phi = new int[a * K];
            } else if (op == 3) {  // tokens: from, how many
                ints(p.rows, a, b);
                ints(p.cols, a, b);
                bytes(p.z, a, b);
            } else if (op == 4) {  // groups of rows and columns; replica
                for (int t = 0; t < p.n; t++) {
                    theta[p.rows[t] * K + p.z[t]]++;
                    p.phi[p.cols[t] * K + p.z[t]]++;
                    p.totals[p.z[t]]++;
                }
                int[] rowGroup = new int[documents], colGroup = new int[p.words];
                ints(rowGroup, 0, documents);
                ints(colGroup, 0, p.words);
                deal(p, rowGroup, colGroup, a == 1);
                give(p.at);
            } else if (op == 5) {  // waves: block, look, thin; its permutation
                int[] order = new int[p.at[a + 1] - p.at[a]];
                ints(order, 0, order.length);
                plan(p, a, order, b, c);
            } else if (op == 6) {  // block, wide, waves, replica; numbers
                sweep(p, a, b, c == 1, e == 1);
            } else if (op == 7) {
                close(p);
            } else if (op == 8) {
                room.clear();
                room.putDouble(like(p));
                send();
            } else if (op == 9) {
                give(theta);
            } else if (op == 10) {
                give(p.phi);
            } else if (op == 11) {
                for (int from = 0; from < p.n; from += 1 << 20) {
                    room.clear();
                    room.put(p.z, from, Math.min(p.n - from, 1 << 20));
                    send();
                }
            } else if (op == 12) {
                room.clear();
                for (int k = 0; k < K; k++) room.putLong(p.totals[k]);
                send();
            }
        }
    }
}
"""

_made: dict[int, dict[str, bytes] | None] = {}


def compiled(spark, topics: int) -> dict[str, bytes] | None:
    """The classes for a number of topics, made on the driver; None where they can't be."""
    if topics not in _made:
        _made[topics] = None
        if 0 < topics <= MOST_TOPICS:
            try:
                maker = spark._jvm.org.codehaus.janino.SimpleCompiler()
                maker.cook(source(topics))
                _made[topics] = {str(k): bytes(v) for k, v in dict(maker.getBytecodes()).items()}
            except Exception as e:  # noqa: BLE001  an older compiler: the loops in Python are there
                _made[topics] = None
                if os.environ.get("TOPICGRID_STRICT"):
                    raise e
    return _made[topics]


@cache
def java() -> str:
    """Java as the environment names it, else that of the executor which this process descends from."""
    home, pid, found = os.environ.get("JAVA_HOME"), os.getpid(), []
    found += [f"{home}/bin/java"] if home else []
    found += [x for x in [shutil.which("java")] if x]
    try:
        while pid > 1:
            exe = os.readlink(f"/proc/{pid}/exe")
            found += [exe] if os.path.basename(exe) == "java" else []
            pid = int(Path(f"/proc/{pid}/stat").read_text().rpartition(")")[2].split()[1])
    except OSError:
        pass
    for x in found:
        if os.access(x, os.X_OK):
            return x
    raise RuntimeError("no java for the sampling process: set JAVA_HOME on the workers")


def memory_mb(documents: int, sizes: list[tuple[int, int]], topics: int, groups: int, block: int) -> int:
    """Heap for one fit: tokens once (those of a part twice while they are dealt), counts, then the waves' order and the numbers of a block, if there are waves. ``sizes``: tokens and words of each part."""
    tokens, most = sum(n for n, _ in sizes), max((n for n, _ in sizes), default=0)
    counts = 4 * topics * (documents + sum(w for _, w in sizes)) + 8 * topics * max(w for _, w in sizes) + 20 * documents + 4 * max(w for _, w in sizes)
    working = max(9 * most if groups > 1 else 0, 4 * tokens + 8 * block if block else 0)
    return int((9 * tokens + counts + working) / 2**20 * 1.03) + 40


class Fit:
    """The process. Tokens are sent piece by piece in the order (row, column), then dealt to blocks."""

    def __init__(self, code: dict[str, bytes], topics: int, documents: int, alpha: float, heap_mb: int):
        self.topics, self.documents, self.tokens, self.words, self.sent, self.blocks = topics, documents, {}, {}, {}, {}
        self.folder = tempfile.mkdtemp(prefix="topicgrid-")
        for name, data in code.items():
            Path(self.folder, f"{name}.class").write_bytes(data)
        how = ["-XX:+UseSerialGC", f"-Xmx{heap_mb}m", "-Xmn4m", "-XX:+UseTransparentHugePages", "-XX:-UsePerfData", "-XX:+DisplayVMOutputToStderr", "-Xshare:auto", "-XX:CICompilerCount=2", "-XX:ReservedCodeCacheSize=32m"]
        env = {k: v for k, v in os.environ.items() if k not in ("JAVA_TOOL_OPTIONS", "_JAVA_OPTIONS", "JDK_JAVA_OPTIONS")}
        self.process = subprocess.Popen([java(), *how, "-cp", self.folder, "Fit"], stdin=subprocess.PIPE, stdout=subprocess.PIPE, env=env)
        self.call(1, 0, documents, x=alpha)

    def __enter__(self) -> Fit:
        return self

    def __exit__(self, *_) -> None:
        self.process.kill()
        self.process.wait()
        self.process.stdin.close() if not self.process.stdin.closed else None
        self.process.stdout.close()
        shutil.rmtree(self.folder, ignore_errors=True)

    def call(self, op: int, part: int, a: int = 0, b: int = 0, c: int = 0, e: int = 0, x: float = 0.0, y: float = 0.0) -> None:
        self.process.stdin.write(struct.pack("<6q2d", op, part, a, b, c, e, x, y))

    def write(self, x: np.ndarray) -> None:
        self.process.stdin.write(memoryview(np.ascontiguousarray(x)).cast("B") if len(x) else b"")

    def read(self, kind, n: int) -> np.ndarray:
        self.process.stdin.flush()
        want = n * np.dtype(kind).itemsize
        raw = self.process.stdout.read(want)
        if len(raw) < want:
            raise RuntimeError(f"the sampling process ended with {self.process.wait()}")
        return np.frombuffer(raw, kind)

    def add_part(self, part: int, words: int, tokens: int, groups: int, prior: float) -> None:
        self.tokens[part], self.words[part], self.sent[part] = tokens, words, 0
        self.call(2, part, words, tokens, groups, x=prior)

    def add_tokens(self, part: int, rows: np.ndarray, cols: np.ndarray, z: np.ndarray) -> None:
        self.call(3, part, self.sent[part], len(rows))
        self.write(rows.astype("<i4"))
        self.write(cols.astype("<i4"))
        self.write(z.astype(np.uint8))
        self.sent[part] += len(rows)

    def add_packed(self, part: int, at: int, rows: bytes, cols: bytes, z: bytes) -> None:
        """The same from bytes, with the place of the first."""
        self.call(3, part, at, len(z))
        self.process.stdin.write(rows + cols + z)
        self.sent[part] += len(z)

    def deal(self, part: int, row_groups: np.ndarray, col_groups: np.ndarray, groups: int, replica: bool = False) -> None:
        """Counts, and tokens by block."""
        assert self.sent[part] == self.tokens[part], "tokens are missing"
        self.call(4, part, int(replica))
        self.write(row_groups.astype("<i4"))
        self.write(col_groups.astype("<i4"))
        self.blocks[part] = self.read("<i4", groups * groups + 1)

    def size(self, part: int, block: int) -> int:
        return int(self.blocks[part][block + 1] - self.blocks[part][block])

    def plan(self, part: int, block: int, look: int, thin: int) -> None:
        n = self.size(part, block)
        self.call(5, part, block, look, thin)
        self.write(np.random.default_rng(n).permutation(np.arange(n, dtype="<i4")))

    def sweep(self, part: int, block: int, wide: int, waves: bool, replica: bool, rng: np.random.Generator) -> None:
        self.call(6, part, block, wide, int(waves), int(replica))
        for at in range(0, n := self.size(part, block), PIECE):
            self.write(rng.random(min(PIECE, n - at)))

    def close(self, part: int) -> None:
        """The end of an epoch: totals are added up."""
        self.call(7, part)

    def perplexity(self) -> float:
        self.call(8, 0)
        return float(np.exp(-self.read("<f8", 1)[0] / self.tokens[0]))

    def totals(self, part: int) -> np.ndarray:
        self.call(12, part)
        return self.read("<i8", self.topics)

    def theta(self) -> np.ndarray:
        self.call(9, 0)
        return self.read("<i4", self.documents * self.topics).reshape(-1, self.topics)

    def phi(self, part: int) -> np.ndarray:
        self.call(10, part)
        return self.read("<i4", self.words[part] * self.topics).reshape(-1, self.topics)

    def z(self, part: int) -> np.ndarray:
        """Topics in the order in which tokens were sent; of one block that has no waves."""
        self.call(11, part)
        return self.read(np.uint8, self.tokens[part])


def usable(documents: int, words: Iterable[int], tokens: Iterable[int], topics: int) -> bool:
    """Whether all fits into arrays."""
    return max((documents, *words)) * topics < 2**31 - 8 and max(tokens) < 2**31 - 8
