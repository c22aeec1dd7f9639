"""Long walks and tables of many keys in a Java process beside the Python one, compiled by the compiler that Spark brings along.

It does what the Python and numpy forms of :mod:`fpfilter.operators.cuckoo` do, with the same random numbers, so results
never depend on it; where none can be started, these forms do the work. Each Python process starts one when it first
has long walks, talks to it through pipes and ends it by closing them.
"""

from __future__ import annotations

import atexit
import contextlib
import glob
import os
import shutil
import subprocess
import tempfile
from collections.abc import Callable, Sequence

import numpy as np

from fpfilter.functions.hashing import linear_np, mix_int, signed
from fpfilter.operators.spec import FilterSpec

#: Fewer items are not worth a process.
WORTH = 1 << 15
#: Bytes that the process reads or writes at once, lanes that it is sent, and what it may take for its arrays.
_BUFFER, _DRAWS, _HEAP = 1 << 18, 1 << 16, "1g"
#: Bytes that a pipe holds, as many as any process may ask for.
_PIPE = 1 << 20
#: Walks under way at a time in a table that stays there: what they read fits into a core's cache.
_WALKS = 512

_SOURCE = r"""
import java.io.IOException;
import java.io.FileDescriptor;
import java.io.FileInputStream;
import java.io.FileOutputStream;
import java.nio.ByteBuffer;
import java.nio.ByteOrder;
import java.nio.channels.FileChannel;

public class Walks {
    static FileChannel in = new FileInputStream(FileDescriptor.in).getChannel();
    static FileChannel out = new FileOutputStream(FileDescriptor.out).getChannel();
    static ByteBuffer buffer = ByteBuffer.allocateDirect(BUFFER).order(ByteOrder.LITTLE_ENDIAN);
    static byte[] draws = new byte[0];
    static int drawn = 0;

    static boolean fill(long bytes) throws IOException {
        buffer.clear();
        buffer.limit((int) bytes);
        while (buffer.hasRemaining()) if (in.read(buffer) < 0) return false;
        buffer.flip();
        return true;
    }

    static void need(long bytes) throws IOException { if (!fill(bytes)) throw new IOException("input ended"); }

    static void send() throws IOException {
        buffer.flip();
        while (buffer.hasRemaining()) out.write(buffer);
        buffer.clear();
    }

    static long[] longs(int n) throws IOException {
        long[] x = new long[n];
        for (int low = 0; low < n; low += BUFFER / 8) {
            int count = Math.min(BUFFER / 8, n - low);
            need(8L * count);
            buffer.asLongBuffer().get(x, low, count);
        }
        return x;
    }

    static int[] ints(int n) throws IOException {
        int[] x = new int[n];
        for (int low = 0; low < n; low += BUFFER / 4) {
            int count = Math.min(BUFFER / 4, n - low);
            need(4L * count);
            buffer.asIntBuffer().get(x, low, count);
        }
        return x;
    }

    static void give(long[] x) throws IOException {
        for (int low = 0; low < x.length; low += BUFFER / 8) {
            int count = Math.min(BUFFER / 8, x.length - low);
            buffer.clear();
            buffer.asLongBuffer().put(x, low, count);
            buffer.position(8 * count);
            send();
        }
    }

    static void give(int[] x) throws IOException {
        for (int low = 0; low < x.length; low += BUFFER / 4) {
            int count = Math.min(BUFFER / 4, x.length - low);
            buffer.clear();
            buffer.asIntBuffer().put(x, low, count);
            buffer.position(4 * count);
            send();
        }
    }

    static void more() throws IOException {
        give(new long[] {1});
        need(8);
        draws = new byte[(int) buffer.getLong()];
        need(draws.length);
        buffer.get(draws);
        drawn = 0;
    }

    static int draw() throws IOException {
        if (drawn == draws.length) more();
        return draws[drawn++];
    }

    static int free(int[] held, int from, int l) {
        for (int s = from; s < from + l; s++) if (held[s] < 0) return s;
        return -1;
    }

    static int free(int[] base, int[] held, int item, int d, int l) {
        for (int c = item * d; c < item * d + d; c++) {
            int s = free(held, base[c], l);
            if (s >= 0) return s;
        }
        return -1;
    }

    /* Items one after the other: how many are stored when a walk needs more evictions than each limit. */
    static void oneByOne(int n, int d, int l, int slots, int start, long[] most) throws IOException {
        int[] base = ints(n * d), held = ints(slots), which = new int[d * l], offset = new int[d * l];
        for (int lane = 0; lane < d * l; lane++) {
            which[lane] = lane / l;
            offset[lane] = lane % l;
        }
        long[] got = new long[most.length];
        int at = 0;
        for (int item = start; item < n && at < most.length; item++) {
            int now = item, slot;
            long length = 0;
            while ((slot = free(base, held, now, d, l)) < 0) {
                while (at < most.length && length >= most[at]) got[at++] = item;
                if (at == most.length) break;
                int lane = draw();
                slot = base[now * d + which[lane]] + offset[lane];
                int victim = held[slot];
                held[slot] = now;
                now = victim;
                length++;
            }
            if (slot >= 0) held[slot] = now;
        }
        while (at < most.length) got[at++] = n;
        give(new long[] {0});
        give(got);
    }

    /* A filter's entries, many at a time, in rounds. All addresses are first slots; `by` tells the steps between the two of a fingerprint. */
    static int l, f, o, size;
    static boolean window;

    static int after(int place, int step) {
        int s = place - (size - step);
        return s < 0 ? s + size : s;
    }

    static int empty(int[] slots, int from, int l) {
        for (int x = 0; x < l; x++) if (slots[from + x] == 0) return x;
        return -1;
    }

    static void look(int[] slots, int[] first, int[] second, int[] lane, int now, int l) {
        for (int i = 0; i < now; i++) {
            int x = empty(slots, first[i], l);
            if (x < 0 && (x = empty(slots, second[i], l)) >= 0) x += l;
            lane[i] = x;
        }
    }

    static void aim(int[] first, int[] second, int[] lane, int[] target, int[] claim, int now, int l, int mask) throws IOException {
        for (int i = 0; i < now; i++) {
            int x = lane[i] >= 0 ? lane[i] : (lane[i] = draw());
            target[i] = x < l ? first[i] + x : second[i] + x - l;
            claim[target[i] & mask] = i;
        }
    }

    static int longest(int[] slots, int[] steps, int[] target, int[] claim, int now, int mask) {
        int longest = -1;
        for (int i = 0; i < now; i++) if (steps[i] > longest && claim[target[i] & mask] == i && slots[target[i]] != 0) longest = steps[i];
        return longest;
    }

    /* counts: stored, the longest walk, all evictions; returns how many are still under way. */
    static int move(int[] slots, int[] first, int[] second, int[] print, int[] steps, int[] target, int[] lane, int[] claim, int[] by, int now, int l, int mask, long[] counts, long[] bands) {
        int kept = 0, prints = (1 << f) - 1, offsets = (1 << o) - 1;
        for (int i = 0; i < now; i++) {
            int a = first[i], b = second[i], fp = print[i], s = target[i], length = steps[i];
            if (claim[s & mask] == i) {
                int old = slots[s], choice = lane[i] < l ? 0 : 1, x = lane[i] - choice * l;
                slots[s] = fp | (window ? x << f : 0) | choice << f + o;
                if (old == 0) {
                    counts[0]++;
                    counts[1] = Math.max(counts[1], length);
                    counts[2] += length;
                    bands[32 - Integer.numberOfLeadingZeros(length)]++;
                    continue;
                }
                fp = old & prints;
                int place = s - (window ? old >>> f & offsets : x);
                if (old >>> f + o == 0) {
                    a = place;
                    b = after(place, by[fp]);
                } else {
                    a = after(place, size - by[fp]);
                    b = place;
                }
                length++;
            }
            first[kept] = a;
            second[kept] = b;
            print[kept] = fp;
            steps[kept++] = length;
        }
        return kept;
    }

    static void rounds(int n, int length, int pool, int marks, long[] counts, long most, long[] caps) throws IOException {
        long[] items = longs(n), bands = new long[64], exceeded = new long[caps.length];
        int[] by = ints(1 << f), slots = ints(length), claim = new int[marks];
        int[] first = new int[pool], second = new int[pool], print = new int[pool], steps = new int[pool], target = new int[pool], lane = new int[pool];
        java.util.Arrays.fill(exceeded, -1);
        int now = 0, at = 0, met = 0;
        long ok = 1;
        while (now > 0 || at < n) {
            if (2 * now <= pool)
                for (; now < pool && at < n; now++, at++) {
                    print[now] = (int) (items[at] & (1L << f) - 1);
                    first[now] = (int) (items[at] >> f) * (window ? 1 : l);
                    second[now] = after(first[now], by[print[now]]);
                    steps[now] = 0;
                }
            look(slots, first, second, lane, now, l);
            aim(first, second, lane, target, claim, now, l, marks - 1);
            int longest = longest(slots, steps, target, claim, now, marks - 1);
            while (met < caps.length && longest >= caps[met]) exceeded[met++] = counts[0];
            if (longest >= most) {
                ok = 0;
                break;
            }
            now = move(slots, first, second, print, steps, target, lane, claim, by, now, l, marks - 1, counts, bands);
        }
        give(new long[] {0, ok, counts[0], counts[1], counts[2], draws.length - drawn});
        give(exceeded);
        give(bands);
        give(slots);
    }

    /* A filter's table that stays here: entries come piece by piece, then keys are looked up in its packed words. */
    static int pool, at;
    static long limit, state;
    static char[] table;
    static int[] by;
    static long[] counts, words, keys = new long[0];

    static void begin(int length, int pooled, long most, long seed) throws IOException {
        by = ints(1 << f);
        pool = pooled;
        limit = most;
        state = seed;
        table = new char[length];
        counts = new long[3];
        words = null;
        give(new long[] {0});
    }

    static void receive(int n) throws IOException {
        if (keys.length < n) keys = new long[n];
        for (int low = 0; low < n; low += BUFFER / 8) {
            int count = Math.min(BUFFER / 8, n - low);
            need(8L * count);
            buffer.asLongBuffer().get(keys, low, count);
        }
    }

    static int empty(char[] slots, int from, int l) {
        for (int x = 0; x < l; x++) if (slots[from + x] == 0) return x;
        return -1;
    }

    /* Entries whose first address has a free slot take it, others join the walks; how many walks there are then. */
    static int enter(long[] items, int n, char[] slots, int[] first, int[] second, int[] print, int[] left, int[] steps, int[] by, int now, int l, int f, boolean window) {
        int i = at;
        long stored = 0;
        for (; now < first.length && i < n; i++) {
            int fp = (int) (items[i] & (1L << f) - 1), a = (int) (items[i] >> f) * (window ? 1 : l), x = empty(slots, a, l);
            if (x >= 0) {
                slots[a + x] = (char) (fp | (window ? x << f : 0));
                stored++;
                continue;
            }
            first[now] = a;
            second[now] = after(a, by[fp]);
            print[now] = fp;
            left[now] = 2 * l;
            steps[now++] = 0;
        }
        counts[0] += stored;
        at = i;
        return now;
    }

    /* Reads what the next steps need, all at once. */
    static int touch(char[] slots, int[] first, int[] second, int now) {
        int sum = 0;
        for (int i = 0; i < now; i++) sum += slots[first[i]] ^ slots[second[i]];
        return sum;
    }

    /* A step of each walk, one after the other; how many are still under way, -1 if one is too long. Nobody goes back to the slot that it had to leave. */
    static int step(char[] slots, int[] first, int[] second, int[] print, int[] left, int[] steps, int[] by, int now, int l, int f, int o, boolean window, long limit, long[] counts) {
        int kept = 0, prints = (1 << f) - 1, offsets = (1 << o) - 1, choices = f + o;
        long x = state, stored = 0, total = 0, most = counts[1];
        for (int i = 0; i < now; i++) {
            int a = first[i], b = second[i], length = steps[i], lane = empty(slots, a, l);
            if (lane < 0 && (lane = empty(slots, b, l)) >= 0) lane += l;
            boolean free = lane >= 0;
            if (!free) {
                if (length >= limit) return -1;
                x ^= x << 13;
                x ^= x >>> 7;
                x ^= x << 17;
                lane = (int) ((x >>> 32) * (left[i] < 2 * l ? 2 * l - 1 : 2 * l) >>> 32);
                if (lane >= left[i]) lane++;
            }
            int choice = lane < l ? 0 : 1, offset = lane - choice * l, s = (choice == 0 ? a : b) + offset, old = slots[s];
            slots[s] = (char) (print[i] | (window ? offset << f : 0) | choice << choices);
            if (free) {
                stored++;
                total += length;
                if (length > most) most = length;
                continue;
            }
            int fp = old & prints, was = old >>> choices, at = window ? old >>> f & offsets : offset, step = by[fp];
            int place = s - at, rest = after(place, was == 0 ? step : size - step);
            first[kept] = was == 0 ? place : rest;
            second[kept] = was == 0 ? rest : place;
            print[kept] = fp;
            left[kept] = was * l + at;
            steps[kept++] = length + 1;
        }
        state = x;
        counts[0] += stored;
        counts[1] = most;
        counts[2] += total;
        return kept;
    }

    static void add(int n) throws IOException {
        receive(n);
        int now = 0, sum = 0;
        int[] first = new int[pool], second = new int[pool], print = new int[pool], left = new int[pool], steps = new int[pool];
        at = 0;
        while (now >= 0 && (now > 0 || at < n)) {
            now = enter(keys, n, table, first, second, print, left, steps, by, now, l, f, window);
            sum += touch(table, first, second, now);
            now = step(table, first, second, print, left, steps, by, now, l, f, o, window, limit, counts);
        }
        give(new long[] {0, now < 0 ? 0 : 1, counts[0], counts[1], counts[2], sum});
    }

    static void packed(char[] slots, long[] words, int q) {
        for (int s = 0; s < slots.length; s++) {
            long at = (long) s * q;
            int word = (int) (at >>> 6), shift = (int) at & 63;
            words[word] |= (long) slots[s] << shift;
            if (shift + q > 64) words[word + 1] |= (long) slots[s] >>> 64 - shift;
        }
    }

    /* The linear hash into b values; m is 2^64 / b, so the quotient is too small by one at most. */
    static long hash(long x, long a, long b, long m) {
        long p = x * a;
        if ((b & b - 1) == 0) return b > 1 ? p >>> Long.numberOfLeadingZeros(b) + 1 : 0;
        if ((b & 1) == 0) p ^= p >>> 32;
        long r = p - (Math.multiplyHigh(p, m) + (p >> 63 & m)) * b;
        return r - (b & ~(r - b >> 63));
    }

    static long fetch(long[] words, int slot, int q, long mask) {
        long at = (long) slot * q;
        int word = (int) (at >>> 6), shift = (int) at & 63;
        return (words[word] >>> shift | words[word + 1] << 1 << 63 - shift) & mask;
    }

    static final int BLOCK = 512;

    static long find(long[] keys, int low, int n, byte[] hit, long[] words, int[] by, int l, int f, int o, int unit, long addresses, long address, long finger) {
        int q = f + o + 1;
        long sum = 0, prints = (1L << f) - 1, m = Long.divideUnsigned(-1L, addresses), mf = Long.divideUnsigned(-1L, prints), ones = 0, offsets = 0;
        for (int x = 0; x < l; x++) {
            ones |= 1L << q * x;
            if (o > 0 && unit == 1) offsets |= (long) x << q * x + f;
        }
        long top = ones << q - 1, rest = top - ones, mask = -1L >>> 64 - l * q, other = offsets | ones << f + o;
        long[] pattern = new long[BLOCK];
        int[] one = new int[BLOCK], two = new int[BLOCK];
        for (int from = 0; from < n; from += BLOCK) {
            int count = Math.min(BLOCK, n - from);
            for (int i = 0; i < count; i++) {
                long h = keys[low + from + i];
                int fp = (int) hash(h, finger, prints, mf) + 1;
                pattern[i] = ones * fp;
                one[i] = (int) hash(h, address, addresses, m) * unit;
                two[i] = after(one[i], by[fp]);
            }
            sum += touch(words, one, two, count, q);
            test(words, one, two, pattern, hit, from, count, q, mask, offsets, other, rest, top);
        }
        return sum;
    }

    static long touch(long[] words, int[] one, int[] two, int n, long q) {
        long sum = 0;
        for (int i = 0; i < n; i++) sum += words[(int) (one[i] * q >>> 6)] ^ words[(int) (two[i] * q >>> 6)];
        return sum;
    }

    static void test(long[] words, int[] one, int[] two, long[] pattern, byte[] hit, int from, int n, int q, long mask, long offsets, long other, long rest, long top) {
        for (int i = 0; i < n; i++) {
            long x = fetch(words, one[i], q, mask) ^ (pattern[i] | offsets), y = fetch(words, two[i], q, mask) ^ (pattern[i] | other);
            hit[from + i] = (byte) ((((x & rest) + rest | x) & ((y & rest) + rest | y) & top) == top ? 0 : 1);
        }
    }

    static byte[] hit = new byte[BUFFER / 8];

    static void lookUp(int n, long addresses, long address, long finger) throws IOException {
        receive(n);
        give(new long[] {0});
        for (int low = 0; low < n; low += hit.length) {
            int count = Math.min(hit.length, n - low);
            state += find(keys, low, count, hit, words, by, l, f, o, window ? 1 : l, addresses, address, finger);
            buffer.clear();
            buffer.put(hit, 0, count);
            send();
        }
    }

    static void shape(long[] h) {
        l = (int) h[6];
        f = (int) h[7];
        o = (int) h[8];
        window = h[9] != 0;
        size = (int) h[10];
    }

    public static void main(String[] args) throws IOException {
        while (fill(128)) {
            long[] h = new long[16];
            buffer.asLongBuffer().get(h);
            long[] caps = longs((int) h[1]);
            if (h[0] < 4) {
                draws = new byte[0];
                drawn = 0;
            }
            if (h[0] == 1) oneByOne((int) h[2], (int) h[3], (int) h[4], (int) h[5], (int) h[6], caps);
            else if (h[0] == 4) add((int) h[2]);
            else if (h[0] == 5) {
                words = new long[(int) h[2]];
                packed(table, words, f + o + 1);
                table = null;
                give(new long[] {0});
            } else if (h[0] == 6) lookUp((int) h[2], h[3], h[4], h[5]);
            else if (h[0] == 7) {
                give(new long[] {0});
                give(words);
            } else if (h[0] == 3) {
                shape(h);
                begin((int) h[2], (int) h[3], caps[0], h[4]);
            } else {
                shape(h);
                rounds((int) h[2], (int) h[3], (int) h[4], (int) h[5], new long[] {h[11], h[12], h[13]}, caps[caps.length - 1], java.util.Arrays.copyOf(caps, caps.length - 1));
            }
        }
    }
}
"""


class Helper:
    """The process; an :class:`OSError` tells that it cannot be used."""

    def __init__(self) -> None:
        import pyspark

        homes = [os.environ.get("SPARK_HOME", ""), os.path.dirname(pyspark.__file__)]
        jars = next((found for home in homes if len(found := [p for name in ("janino", "commons-compiler") for p in glob.glob(f"{home}/jars/{name}-*.jar")]) == 2), None)
        java = shutil.which(os.path.join(os.environ.get("JAVA_HOME", ""), "bin", "java")) or shutil.which("java")
        if jars is None or java is None:
            raise OSError("no Java or no compiler")
        with tempfile.TemporaryDirectory(prefix="fpfilter-walks-") as folder:
            with open(f"{folder}/Walks.java", "w") as source:
                source.write(_SOURCE.replace("BUFFER", str(_BUFFER)))
            options = [f"-Xmx{_HEAP}", "-Xms16m", "-XX:+UseSerialGC", "-XX:+UseTransparentHugePages", "-XX:-UsePerfData", "-cp", os.pathsep.join(jars)]
            self.process = subprocess.Popen([java, *options, "org.codehaus.janino.SimpleCompiler", f"{folder}/Walks.java", "Walks"], stdin=subprocess.PIPE, stdout=subprocess.PIPE, stderr=subprocess.DEVNULL, pipesize=_PIPE)
            if self.one_by_one(np.array([[0]]), 1, np.array([-1]), 0, [1], lambda: np.zeros(0, np.int64)) != [1]:  # read by now
                raise OSError("wrong answer")

    def close(self) -> None:
        with contextlib.suppress(OSError):  # it may have failed
            self.process.stdin.close()
        self.process.stdout.close()
        self.process.wait()

    def _send(self, x: np.ndarray) -> None:
        self.process.stdin.write(memoryview(np.ascontiguousarray(x)).cast("B") if x.size else b"")

    def _get(self, n: int, kind: type = np.int64) -> np.ndarray:
        out = np.empty(n, kind)
        if n and self.process.stdout.readinto(memoryview(out).cast("B")) != out.nbytes:
            raise OSError("output ended")
        return out

    def _run(self, head: Sequence[int], caps: Sequence[int], parts: Sequence[np.ndarray], draw: Callable) -> np.ndarray:
        """Send a job and draws until it is done; the last draws that were sent."""
        self._send(np.array([head[0], len(caps), *head[1:], *[0] * (15 - len(head))], np.int64))
        for part in (np.array(caps, np.int64), *parts):
            self._send(part)
        self.process.stdin.flush()
        lanes_ = np.zeros(0, np.uint8)
        while self._get(1)[0]:
            lanes_ = draw().astype(np.uint8)
            self._send(np.array([len(lanes_)], np.int64))
            self._send(lanes_)
            self.process.stdin.flush()
        return lanes_

    def one_by_one(self, base: np.ndarray, l: int, slots: np.ndarray, start: int, caps: Sequence[int], draw: Callable) -> list[int]:  # noqa: E741
        self._run([1, *base.shape, l, len(slots), start], caps, [base.astype(np.int32, "C"), slots.astype(np.int32)], draw)
        return self._get(len(caps)).tolist()

    def _shape(self, spec: FilterSpec) -> tuple[list[int], np.ndarray]:
        unit = 1 if spec.layout == "window" else spec.l
        steps = unit * (1 + linear_np(np.arange(1 << spec.fp_bits), spec.factor("offset", spec.n_addr - 1), spec.n_addr - 1))
        return [spec.l, spec.fp_bits, spec.offset_bits, spec.layout == "window", unit * spec.n_addr], steps.astype(np.int32)

    def begin(self, spec: FilterSpec) -> None:
        """An empty table, which stays until the next one."""
        shape, steps = self._shape(spec)
        self._run([3, spec.n_slots, _WALKS, signed(mix_int(spec.seed)) or 1, 0, *shape], [spec.max_walk], [steps], None)

    def add(self, items: np.ndarray) -> list[int]:
        """Entries for the table; success, those stored so far, the longest walk, all evictions."""
        self._run([4, len(items)], [], [items], None)
        return self._get(5).tolist()[:4]

    def pack(self, words: int) -> None:
        """No more entries: the table becomes so many packed words."""
        self._run([5, words], [], [], None)

    def words(self, words: int) -> np.ndarray:
        self._run([7], [], [], None)
        return self._get(words, np.uint64)

    def contains(self, h: np.ndarray, spec: FilterSpec) -> np.ndarray:
        """Whether the packed table has a slot for each key."""
        factors = [signed(spec.factor(role, b)) for role, b in (("address", spec.n_addr), ("fingerprint", (1 << spec.fp_bits) - 1))]
        self._run([6, len(h), spec.n_addr, *factors], [], [h], None)
        return self._get(len(h), np.bool_)

    def rounds(self, items: np.ndarray, slots: np.ndarray, marks: int, pool: int, spec: FilterSpec, counts: Sequence[int], caps: Sequence[int], draw: Callable) -> tuple[list[int], np.ndarray, np.ndarray, np.ndarray]:
        shape, steps = self._shape(spec)
        lanes_ = self._run([2, len(items), len(slots), pool, marks, *shape, *counts], caps, [items, steps, slots], draw)
        *got, unused = self._get(5).tolist()
        exceeded, bands = self._get(len(caps) - 1), self._get(64)
        return [*got, *exceeded.tolist()], bands, self._get(len(slots), np.uint32), lanes_[len(lanes_) - unused :]


_OWN: dict[int, Helper | None] = {}


def helper() -> Helper | None:
    """This process's helper; None where none can be started."""
    if os.getpid() not in _OWN:
        try:
            _OWN[os.getpid()] = Helper()
            atexit.register(_OWN[os.getpid()].close)
        except OSError:
            _OWN[os.getpid()] = None
    return _OWN[os.getpid()]


def started(n: int) -> None:
    """Start the helper now, if so many keys are worth it, and not while a clock runs."""
    if n >= WORTH:
        helper()


def knows(spec: FilterSpec) -> bool:
    """Whether the helper fills this filter: steps between addresses by fingerprint, and slots of 32 bits."""
    return spec.rule == "signed" and spec.fp_bits <= 20 and spec.slot_bits < 32 and spec.n_slots < 1 << 30


def dropped() -> None:
    """The helper failed: do without."""
    failed, _OWN[os.getpid()] = _OWN[os.getpid()], None
    atexit.unregister(failed.close)
    failed.process.kill()
    failed.close()


def ended() -> None:
    """No more long walks for now: the helper is not kept."""
    own = _OWN.pop(os.getpid(), None)
    if own is not None:
        atexit.unregister(own.close)
        own.close()


def one_by_one(base: np.ndarray, l: int, slots: np.ndarray, start: int, caps: Sequence[int], seed: int) -> list[int] | None:  # noqa: E741
    """How many items are stored when the first walk needs more evictions than each of ``caps`` (in order)."""
    if len(base) - start < WORTH or max(base.size, len(slots)) >= 1 << 31 or base.shape[1] * l > 127 or (own := helper()) is None:
        return None
    rng = np.random.default_rng(seed)
    try:
        return own.one_by_one(base, l, slots, start, caps, lambda: np.concatenate([rng.integers(0, base.shape[1] * l, 4096)[::-1] for _ in range(_DRAWS >> 12)]))
    except OSError:
        dropped()
        return None
