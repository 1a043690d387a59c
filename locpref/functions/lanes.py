"""The draws of ``hashing`` in Spark's own JVM, 512 keys at a time, each step of MD5 a loop over them.

Such loops become vector instructions. The class below is compiled by the compiler that
Spark has for its generated code, goes to the executors as a jar and is called as a
column function, or for all units of a task: then it makes the sums of a pass of
``blocks`` too, and no row goes to Python. Where that can't be (no JVM within reach),
``draws`` makes the same numbers from arrays in Python.
"""

from __future__ import annotations

import os
import tempfile
import zipfile
from collections.abc import Iterable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

SOURCE = r"""
package locpref;

import java.nio.ByteBuffer;
import java.nio.ByteOrder;

public final class Lanes implements org.apache.spark.sql.api.java.UDF6, org.apache.spark.api.java.function.MapPartitionsFunction {
    static final int L = 512;
    static final int D = 4; // room of a vector
    static final int[] TURNS = {7, 12, 17, 22, 5, 9, 14, 20, 4, 11, 16, 23, 6, 10, 15, 21};
    static final int[] SINES = new int[64];
    static final double UNIT = 1.0 / 4503599627370496.0;
    static { for (int i = 0; i < 64; i++) SINES[i] = (int) (long) (Math.abs(Math.sin(i + 1)) * 4294967296.0); }

    static void one(int[] a, int[] b, int[] c, int[] d, int[] m, int k, int s) {
        int r = 32 - s;
        for (int j = 0; j < L; j++) { int x = a[j] + (d[j] ^ (b[j] & (c[j] ^ d[j]))) + m[j] + k; a[j] = ((x << s) | (x >>> r)) + b[j]; }
    }

    static void two(int[] a, int[] b, int[] c, int[] d, int[] m, int k, int s) {
        int r = 32 - s;
        for (int j = 0; j < L; j++) { int x = a[j] + (c[j] ^ (d[j] & (b[j] ^ c[j]))) + m[j] + k; a[j] = ((x << s) | (x >>> r)) + b[j]; }
    }

    static void three(int[] a, int[] b, int[] c, int[] d, int[] m, int k, int s) {
        int r = 32 - s;
        for (int j = 0; j < L; j++) { int x = a[j] + (b[j] ^ c[j] ^ d[j]) + m[j] + k; a[j] = ((x << s) | (x >>> r)) + b[j]; }
    }

    static void four(int[] a, int[] b, int[] c, int[] d, int[] m, int k, int s) {
        int r = 32 - s;
        for (int j = 0; j < L; j++) { int x = a[j] + (c[j] ^ (b[j] | ~d[j])) + m[j] + k; a[j] = ((x << s) | (x >>> r)) + b[j]; }
    }

    static void add(int[] to, int[] from) { for (int j = 0; j < L; j++) to[j] += from[j]; }

    /** Texts one after the other; a key is a prefix, one of them and a suffix. */
    static final class Keys {
        byte[] text; int[] from; int n;
        int[][] words = new int[16][L];
        int[][] state = new int[4][L], now = new int[4][L];
        int[] blocks = new int[L];
        int start, count, head, size;
        byte[] end = null;
        long[] out = new long[L];

        Keys(int n, int bytes) { this.n = 0; from = new int[n + 1]; text = new byte[bytes]; }

        void more(byte[] x) { // after the last text, which it lengthens
            int at = from[n];
            while (at + x.length > text.length) text = java.util.Arrays.copyOf(text, 2 * text.length + x.length);
            System.arraycopy(x, 0, text, at, x.length);
            from[n] = at + x.length;
        }

        void next() { n++; if (n < from.length) from[n] = from[n - 1]; }

        int begin(int i) { return i == 0 ? 0 : from[i - 1]; }

        /** Words of some keys without a prefix of ``p`` bytes, whose place stays empty. What is there already but for the suffix's last byte only changes that. */
        void lay(int start, int count, int p, byte[] suffix) {
            int ns = suffix.length;
            boolean same = end != null && this.start == start && this.count == count && head == p && end.length == ns;
            for (int i = 0; same && i < ns - 1; i++) same = end[i] == suffix[i];
            byte[] old = end;
            this.start = start; this.count = count; head = p; end = suffix;
            if (same) {
                int x = old[ns - 1] ^ suffix[ns - 1];
                for (int j = 0; x != 0 && j < count; j++) {
                    int at = p + from[start + j] - begin(start + j) + ns - 1;
                    words[at >> 2][j] ^= (x & 255) << ((at & 3) << 3);
                }
                return;
            }
            size = 1;
            for (int j = 0; j < count; j++) {
                blocks[j] = (p + from[start + j] - begin(start + j) + ns + 8) / 64 + 1;
                size = Math.max(size, blocks[j]);
            }
            if (words.length < 16 * size) words = new int[16 * size][L];
            for (int w = 0; w < 16 * size; w++) java.util.Arrays.fill(words[w], 0);
            for (int j = 0; j < count; j++) {
                int w = p >> 2, turn = (p & 3) << 3, x = 0, last = from[start + j], i = begin(start + j);
                int at = p + last - i + ns;
                for (; i < last; i++) {
                    x |= (text[i] & 255) << turn;
                    turn += 8;
                    if (turn == 32) { words[w++][j] = x; x = 0; turn = 0; }
                }
                for (i = 0; i < ns; i++) {
                    x |= (suffix[i] & 255) << turn;
                    turn += 8;
                    if (turn == 32) { words[w++][j] = x; x = 0; turn = 0; }
                }
                words[w][j] = x | 128 << turn;
                words[16 * blocks[j] - 2][j] = 8 * at;
            }
        }

        /** 52 bits for each key that was laid, with this prefix. */
        long[] hash(byte[] prefix) {
            int[] fixed = new int[16 * size];
            for (int i = 0; i < head; i++) fixed[i >> 2] |= (prefix[i] & 255) << ((i & 3) << 3);
            java.util.Arrays.fill(state[0], 0x67452301);
            java.util.Arrays.fill(state[1], 0xefcdab89);
            java.util.Arrays.fill(state[2], 0x98badcfe);
            java.util.Arrays.fill(state[3], 0x10325476);
            for (int k = 0; k < size; k++) {
                for (int q = 0; q < 4; q++) System.arraycopy(state[q], 0, now[q], 0, L);
                int[] a = now[0], b = now[1], c = now[2], d = now[3];
                for (int i = 0; i < 64; i++) {
                    int q = i >> 4, w = 16 * k + ((q == 0 ? i : q == 1 ? 5 * i + 1 : q == 2 ? 3 * i + 5 : 7 * i) & 15);
                    int s = TURNS[4 * q + (i & 3)], x = SINES[i] + fixed[w];
                    if (q == 0) one(a, b, c, d, words[w], x, s);
                    else if (q == 1) two(a, b, c, d, words[w], x, s);
                    else if (q == 2) three(a, b, c, d, words[w], x, s);
                    else four(a, b, c, d, words[w], x, s);
                    int[] old = a; a = d; d = c; c = b; b = old;
                }
                for (int q = 0; q < 4; q++) add(state[q], now[q]);
                if (size == 1) told(state[0], state[1]);
                else for (int j = 0; j < count; j++) if (blocks[j] == k + 1) out[j] = bits(state[0][j], state[1][j]);
            }
            return out;
        }

        void told(int[] a, int[] b) { for (int j = 0; j < count; j++) out[j] = bits(a[j], b[j]); }

        static long bits(int a, int b) { return ((long) Integer.reverseBytes(a) & 0xffffffffL) << 20 | (long) (Integer.reverseBytes(b) >>> 12); }
    }

    /** What a plan says; the last one is kept. */
    static final class Plan {
        String said, seed;
        int folds, runs, d, noisy;
        int[] kind;
        double[] unknown;
        double[][] p, scale;
        byte[][][] names;
    }

    static volatile Plan last = null;

    static Plan plan(String said) {
        Plan known = last;
        if (known != null && (known.said == said || known.said.equals(said))) return known;
        Plan x = new Plan();
        String[] parts = said.split("\u001e", -1), f = parts[0].split("\u001f", -1);
        x.said = said;
        x.seed = f[0];
        x.folds = Integer.parseInt(f[1]); x.runs = Integer.parseInt(f[2]); x.d = Integer.parseInt(f[3]); x.noisy = Integer.parseInt(f[4]);
        int settings = Integer.parseInt(f[5]);
        x.kind = new int[settings]; x.unknown = new double[settings]; x.p = new double[settings][x.noisy]; x.scale = new double[settings][x.noisy];
        for (int s = 0; s < settings; s++) {
            String[] g = parts[1 + s].split("\u001f", -1);
            x.kind[s] = Integer.parseInt(g[0]);
            x.unknown[s] = Double.parseDouble(g[1]);
            for (int m = 0; m < x.noisy; m++) { x.p[s][m] = Double.parseDouble(g[2 + 2 * m]); x.scale[s][m] = Double.parseDouble(g[3 + 2 * m]); }
        }
        x.names = new byte[parts.length - 1 - settings][][];
        for (int k = 0; k < x.names.length; k++) {
            String[] g = parts[1 + settings + k].split("\u001f", -1);
            x.names[k] = new byte[g.length][];
            for (int i = 0; i < g.length; i++) x.names[k][i] = utf(g[i]);
        }
        last = x;
        return x;
    }

    static byte[] utf(String x) { return x.getBytes(java.nio.charset.StandardCharsets.UTF_8); }

    static void laplace(long[] bits, double scale, double[] to, int count) {
        for (int j = 0; j < count; j++) {
            double v = Math.min(Math.max(bits[j] * UNIT, 0.5 * UNIT), 1.0 - 0.5 * UNIT) - 0.5;
            to[j] = Math.copySign(-scale * Math.log(1.0 - 2.0 * Math.abs(v)), v);
        }
    }

    /** What a pass over units knows: the plan, numbers of this pass, and item vectors of each round before it, those of the start first. */
    org.apache.spark.broadcast.Broadcast said = null;
    org.apache.spark.broadcast.Broadcast[] past = new org.apache.spark.broadcast.Broadcast[0];
    String numbers = null;

    public Lanes() {}

    Lanes(org.apache.spark.broadcast.Broadcast said, org.apache.spark.broadcast.Broadcast[] past, String numbers) { this.said = said; this.past = past; this.numbers = numbers; }

    public Lanes begun(org.apache.spark.api.java.JavaSparkContext sc, String said) { return new Lanes(sc.broadcast(said), past, null); }

    /** The same with the vectors of one more round, doubles in a file of the driver. */
    public Lanes more(org.apache.spark.api.java.JavaSparkContext sc, String path) throws java.io.IOException {
        ByteBuffer in = ByteBuffer.wrap(java.nio.file.Files.readAllBytes(java.nio.file.Paths.get(path, new String[0]))).order(ByteOrder.LITTLE_ENDIAN);
        double[] z = new double[in.remaining() / 8];
        for (int i = 0; i < z.length; i++) z[i] = in.getDouble();
        org.apache.spark.broadcast.Broadcast[] all = new org.apache.spark.broadcast.Broadcast[past.length + 1];
        System.arraycopy(past, 0, all, 0, past.length);
        all[past.length] = sc.broadcast(z);
        return new Lanes(said, all, null);
    }

    public org.apache.spark.sql.Dataset summed(org.apache.spark.sql.Dataset units, String numbers, org.apache.spark.sql.Encoder encoder) {
        return units.mapPartitions(new Lanes(said, past, numbers), encoder);
    }

    public void end() {
        said.destroy();
        for (int i = 0; i < past.length; i++) past[i].destroy();
    }

    public java.util.Iterator call(java.util.Iterator rows) {
        Pass pass = new Pass(plan((String) said.value()), past, numbers);
        while (rows.hasNext()) pass.unit((org.apache.spark.sql.Row) rows.next());
        return pass.told();
    }

    /** Sums over the units of a task, by group (the runs of a setting and repetition from ``from`` to ``to``) and method. */
    static final class Pass {
        final Plan x;
        final int t, methods, groups;
        final boolean last, decide;
        final double lam, gamma, radius;
        final int[] setting, rep, from, to, start;
        final int[][] at;
        final double[] clip;
        final double[][] m;
        final double[][][] level;
        final double[][] z;
        final double[][][] out;
        final double[][][] counts;

        Pass(Plan x, org.apache.spark.broadcast.Broadcast[] past, String numbers) {
            this.x = x;
            java.util.StringTokenizer f = new java.util.StringTokenizer(numbers, " ");
            t = Integer.parseInt(f.nextToken()); last = f.nextToken().equals("1"); decide = f.nextToken().equals("1");
            lam = Double.parseDouble(f.nextToken()); gamma = Double.parseDouble(f.nextToken()); radius = Double.parseDouble(f.nextToken());
            methods = x.noisy;
            clip = new double[methods];
            for (int i = 0; i < methods; i++) clip[i] = Double.parseDouble(f.nextToken());
            groups = Integer.parseInt(f.nextToken());
            setting = new int[groups]; rep = new int[groups]; from = new int[groups]; to = new int[groups];
            at = new int[groups][methods]; m = new double[groups][]; level = new double[groups][methods][];
            out = new double[groups][methods][]; counts = new double[groups][][];
            int next = 0;
            for (int g = 0; g < groups; g++) {
                setting[g] = Integer.parseInt(f.nextToken()); rep[g] = Integer.parseInt(f.nextToken()); from[g] = Integer.parseInt(f.nextToken()); to[g] = Integer.parseInt(f.nextToken());
                m[g] = new double[to[g] - from[g]];
                for (int k = 0; k < m[g].length; k++) m[g][k] = Double.parseDouble(f.nextToken());
                for (int i = 0; i < methods; i++) {
                    at[g][i] = -1;
                    if (f.nextToken().equals("0")) continue; // not fitted
                    at[g][i] = next;
                    next += m[g].length * D * x.names[x.kind[setting[g]]].length;
                    level[g][i] = new double[m[g].length];
                    for (int k = 0; decide && k < m[g].length; k++) level[g][i][k] = Double.parseDouble(f.nextToken());
                }
            }
            z = new double[past.length][];
            for (int i = 0; i < z.length; i++) z[i] = (double[]) past[i].value();
            start = new int[x.names.length];
            for (int i = 1; i < start.length; i++) start[i] = start[i - 1] + D * x.names[i - 1].length;
        }

        void unit(org.apache.spark.sql.Row row) {
            int kind = row.getInt(0), d = x.d;
            scala.collection.Seq us = (scala.collection.Seq) row.get(1), is = (scala.collection.Seq) row.get(2), rs = (scala.collection.Seq) row.get(3), ts = (scala.collection.Seq) row.get(4);
            int n = us.length(), wide = x.names[kind].length;
            int[] item = new int[n], at = new int[n], begin = new int[n + 1];
            double[] rating = new double[n];
            boolean[] truth = new boolean[n];
            Keys cells = new Keys(n, 32 * n + 64), who = new Keys(n, 8 * n + 64);
            read(x.names[kind], us, is, cells, who, item, at);
            scala.collection.Iterator ri = rs.iterator(), ti = ts.iterator();
            for (int i = 0; i < n; i++) {
                rating[i] = ((Double) ri.next()).doubleValue();
                truth[i] = ((Integer) ti.next()).intValue() == 1;
                begin[at[i] + 1] = i + 1;
            }
            int nu = who.n;
            double[] first = new double[D * nu];
            byte[] head = utf(x.seed + ":init_x:");
            for (int s = 0; s < nu; s += L) for (int k = 0; k < d; k++) {
                int c = Math.min(L, nu - s);
                who.lay(s, c, head.length, utf(":" + k));
                long[] bits = who.hash(head);
                for (int j = 0; j < c; j++) first[D * (s + j) + k] = 0.75 / Math.sqrt((double) d) * (0.5 + bits[j] * UNIT);
            }
            int drawn = -1;
            int[] fold = new int[nu];
            double[] mask = new double[n];
            boolean[] hidden = new boolean[n];
            byte[] held = new byte[n];
            for (int g = 0; g < groups; g++) {
                if (x.kind[setting[g]] != kind) continue;
                if (drawn != rep[g]) folds(rep[g], cells, who, fold, mask);
                drawn = rep[g];
                for (int i = 0; i < n; i++) {
                    hidden[i] = mask[i] < x.unknown[setting[g]];
                    held[i] = (byte) (hidden[i] && fold[at[i]] >= from[g] && fold[at[i]] < to[g] ? fold[at[i]] - from[g] : 255);
                }
                int runs = to[g] - from[g], size = decide ? 6 : D * (wide + 1);
                if (t == 1 && !decide) count(g, runs, wide, item, begin, nu, held);
                for (int i = 0; i < methods; i++) {
                    if (this.at[g][i] < 0) continue;
                    if (out[g][i] == null) out[g][i] = new double[runs * size];
                    double p = x.p[setting[g]][i];
                    byte[] open = p > 0 && !decide ? new byte[runs * n] : null;
                    if (!decide) noise(g, i, cells, item, held, wide, open, out[g][i]);
                    for (int k = 0; k < runs; k++) {
                        int zs = this.at[g][i] + k * D * wide;
                        for (int u = 0; u < nu; u++) fit(first, u, begin[u], begin[u + 1], item, rating, truth, hidden, fold[u] == from[g] + k, kind, zs, m[g][k], clip[i], open, k * n, p, out[g][i], k * size, wide, decide ? level[g][i][k] : 0.0);
                    }
                }
            }
        }

        void folds(int rep, Keys cells, Keys who, int[] fold, double[] mask) {
            byte[] end = utf(":" + rep), head = utf(x.seed + ":fold:");
            for (int s = 0; s < who.n; s += L) {
                int c = Math.min(L, who.n - s);
                who.lay(s, c, head.length, end);
                long[] bits = who.hash(head);
                for (int j = 0; j < c; j++) fold[s + j] = (int) (bits[j] % x.folds);
            }
            head = utf(x.seed + ":mask:");
            for (int s = 0; s < mask.length; s += L) {
                int c = Math.min(L, mask.length - s);
                cells.lay(s, c, head.length, end);
                long[] bits = cells.hash(head);
                for (int j = 0; j < c; j++) mask[s + j] = bits[j] * UNIT;
            }
        }

        /** Ratings of each item and users with one, by run. */
        void count(int g, int runs, int wide, int[] item, int[] begin, int users, byte[] held) {
            if (counts[g] == null) counts[g] = new double[runs][wide + 1];
            for (int k = 0; k < runs; k++) {
                double[] to = counts[g][k];
                for (int u = 0; u < users; u++) {
                    int known = 0;
                    for (int c = begin[u]; c < begin[u + 1]; c++) if (held[c] != (byte) k) { to[item[c]]++; known++; }
                    if (known > 0) to[wide]++;
                }
            }
        }

        /** Noisy bits of cells (1: open) and the sums of their noise. Logarithms of factors are added as one of their product. */
        void noise(int g, int method, Keys cells, int[] item, byte[] held, int wide, byte[] open, double[] sums) {
            double p = x.p[setting[g]][method], scale = x.scale[setting[g]][method];
            if (p == 0 && scale == 0) return;
            int n = item.length, d = x.d, runs = to[g] - from[g], size = D * (wide + 1);
            byte[][] flips = heads("bit_flip", g), coins = heads("bit_coin", g), laps = heads("lap", g);
            double[] weight = {p > 0 ? (0 - p / 2) / (1 - p) : 1.0, p > 0 ? (1 - p / 2) / (1 - p) : 1.0};
            boolean dense = 4 * wide <= n;
            double[][] product = new double[scale > 0 && dense ? runs * d : 0][4 * wide];
            for (int i = 0; i < product.length; i++) java.util.Arrays.fill(product[i], 1.0);
            for (int s = 0; s < n; s += L) {
                int c = Math.min(L, n - s);
                if (p > 0) {
                    byte[] end = utf(":" + t);
                    for (int k = 0; k < runs; k++) {
                        if (k == 0 || flips[k].length != flips[k - 1].length) cells.lay(s, c, flips[k].length, end);
                        long[] got = cells.hash(flips[k]);
                        for (int j = 0; j < c; j++) open[k * n + s + j] = (byte) (got[j] * UNIT < p ? 0 : 1);
                    }
                    for (int k = 0; k < runs; k++) {
                        if (k == 0 || coins[k].length != coins[k - 1].length) cells.lay(s, c, coins[k].length, end);
                        long[] got = cells.hash(coins[k]);
                        for (int j = 0; j < c; j++) if (got[j] * UNIT < 0.5) open[k * n + s + j] = (byte) 1;
                    }
                }
                if (scale == 0) continue;
                for (int i = 0; i < d; i++) {
                    byte[] end = utf(":" + t + ":" + i);
                    for (int k = 0; k < runs; k++) {
                        if (k == 0 || laps[k].length != laps[k - 1].length) cells.lay(s, c, laps[k].length, end);
                        long[] got = cells.hash(laps[k]);
                        double[] factors = dense ? product[k * d + i] : null;
                        for (int j = 0; j < c; j++) {
                            if (held[s + j] == (byte) k) continue;
                            double v = Math.min(Math.max(got[j] * UNIT, 0.5 * UNIT), 1.0 - 0.5 * UNIT) - 0.5, part = 1.0 - 2.0 * Math.abs(v);
                            int o = open == null ? 1 : (int) open[k * n + s + j], to = k * size + D * item[s + j] + i;
                            if (!dense) { sums[to] += (v < 0 ? scale : -scale) * Math.log(part) * weight[o]; continue; }
                            int e = 4 * item[s + j] + (v < 0 ? 2 : 0) + o;
                            factors[e] *= part;
                            if (factors[e] < 1e-290) { sums[to] += (v < 0 ? scale : -scale) * Math.log(factors[e]) * weight[o]; factors[e] = 1.0; }
                        }
                    }
                }
            }
            for (int k = 0; k < runs && product.length > 0; k++) for (int i = 0; i < d; i++) for (int e = 0; e < 4 * wide; e++) {
                double part = product[k * d + i][e];
                if (part < 1.0) sums[k * size + D * (e >> 2) + i] += ((e & 2) != 0 ? scale : -scale) * Math.log(part) * weight[e & 1];
            }
        }

        byte[][] heads(String purpose, int g) {
            byte[][] out = new byte[to[g] - from[g]][];
            for (int k = 0; k < out.length; k++) out[k] = utf(x.seed + ":" + purpose + ":" + (setting[g] * x.runs + rep[g] * x.folds + from[g] + k) + ":");
            return out;
        }

        /** One user in one run: steps through all rounds before, then the parts of item gradients, or decisions. */
        void fit(double[] first, int u, int a, int b, int[] item, double[] rating, boolean[] truth, boolean[] hidden, boolean own, int kind, int zs, double m, double clip, byte[] open, int bits, double p, double[] sums, int to, int wide, double level) {
            double x0 = first[D * u], x1 = first[D * u + 1], x2 = first[D * u + 2], x3 = first[D * u + 3];
            int known = 0;
            for (int c = a; c < b; c++) if (!own || !hidden[c]) known++;
            for (int r = 0; r < z.length; r++) {
                double[] v = z[r];
                int base = r == 0 ? start[kind] : zs;
                boolean now = r == z.length - 1;
                if (now && decide) {
                    for (int c = a; c < b; c++) {
                        int o = base + D * item[c];
                        boolean yes = known > 0 && x0 * v[o] + x1 * v[o + 1] + x2 * v[o + 2] + x3 * v[o + 3] > level;
                        sums[to + (truth[c] ? yes ? 0 : 3 : yes ? 1 : 2)]++;
                        if (own && hidden[c]) { if (truth[c] == yes) sums[to + 4]++; sums[to + 5]++; }
                    }
                    return;
                }
                if (now && known > 0) {
                    double size = Math.abs(x0) + Math.abs(x1) + Math.abs(x2) + Math.abs(x3), yes = p > 0 ? (1 - p / 2) / (1 - p) : 1.0, no = (0 - p / 2) / (1 - p);
                    for (int c = a; c < b; c++) {
                        if (own && hidden[c]) continue;
                        int o = base + D * item[c], i = to + D * item[c];
                        double e = 2.0 * (x0 * v[o] + x1 * v[o + 1] + x2 * v[o + 2] + x3 * v[o + 3] - rating[c]);
                        if (clip >= 0) e *= Math.min(1.0, clip / Math.max(size * Math.abs(e), 1e-300));
                        if (p > 0) e *= open[bits + c] == 1 ? yes : no;
                        sums[i] += e * x0; sums[i + 1] += e * x1; sums[i + 2] += e * x2; sums[i + 3] += e * x3;
                    }
                }
                if (now && (!last || known == 0)) return;
                double g0 = 0, g1 = 0, g2 = 0, g3 = 0;
                for (int c = a; c < b; c++) {
                    if (own && hidden[c]) continue;
                    int o = base + D * item[c];
                    double z0 = v[o], z1 = v[o + 1], z2 = v[o + 2], z3 = v[o + 3], e = 2.0 * (x0 * z0 + x1 * z1 + x2 * z2 + x3 * z3 - rating[c]);
                    g0 += e * z0; g1 += e * z1; g2 += e * z2; g3 += e * z3;
                }
                x0 -= gamma * (g0 / m + 2 * lam * x0); x1 -= gamma * (g1 / m + 2 * lam * x1); x2 -= gamma * (g2 / m + 2 * lam * x2); x3 -= gamma * (g3 / m + 2 * lam * x3);
                double f = Math.min(1.0, radius / Math.max(Math.sqrt(x0 * x0 + x1 * x1 + x2 * x2 + x3 * x3), 1e-300));
                x0 *= f; x1 *= f; x2 *= f; x3 *= f;
            }
            int i = to + D * wide;
            sums[i] += x0; sums[i + 1] += x1; sums[i + 2] += x2; sums[i + 3] += x3;
        }

        java.util.Iterator told() {
            java.util.ArrayList rows = new java.util.ArrayList();
            for (int g = 0; g < groups; g++) {
                if (counts[g] != null) {
                    ByteBuffer to = ByteBuffer.allocate(8 * counts[g].length * counts[g][0].length).order(ByteOrder.LITTLE_ENDIAN);
                    for (int k = 0; k < counts[g].length; k++) for (int i = 0; i < counts[g][k].length; i++) to.putDouble(counts[g][k][i]);
                    rows.add(row(g, -1, to));
                    counts[g] = null;
                }
                int runs = this.to[g] - from[g], wide = x.names[x.kind[setting[g]]].length, size = decide ? 6 : D * (wide + 1);
                for (int i = 0; i < methods; i++) {
                    double[] v = out[g][i];
                    if (v == null) continue;
                    ByteBuffer to = ByteBuffer.allocate(decide ? 8 * v.length : 8 * runs * x.d * (wide + (last ? 1 : 0))).order(ByteOrder.LITTLE_ENDIAN);
                    for (int k = 0; k < runs; k++) {
                        if (decide) { for (int j = 0; j < 6; j++) to.putDouble(v[6 * k + j]); continue; }
                        for (int c = 0; c < x.d; c++) for (int j = 0; j < wide; j++) to.putDouble(v[k * size + D * j + c]);
                        for (int c = 0; last && c < x.d; c++) to.putDouble(v[k * size + D * wide + c]);
                    }
                    rows.add(row(g, i, to));
                    out[g][i] = null;
                }
            }
            return rows.iterator();
        }

        org.apache.spark.sql.Row row(int g, int method, ByteBuffer sums) {
            return org.apache.spark.sql.RowFactory.create(new Object[] {Integer.valueOf(setting[g]), Integer.valueOf(rep[g]), Integer.valueOf(method), sums.array()});
        }
    }

    /** Texts of users and cells, the item of each cell and the place of its user; a user's cells follow each other. */
    static void read(byte[][] names, scala.collection.Seq us, scala.collection.Seq is, Keys cells, Keys who, int[] item, int[] at) {
        byte[] colon = {58};
        byte[] id = null;
        long before = 0;
        scala.collection.Iterator ui = us.iterator(), ii = is.iterator();
        for (int i = 0; i < item.length; i++) {
            long u = ((Long) ui.next()).longValue();
            item[i] = ((Integer) ii.next()).intValue();
            if (id == null || u != before) {
                id = utf(Long.toString(u));
                who.more(id); who.next();
                before = u;
            }
            at[i] = who.n - 1;
            cells.more(id); cells.more(colon); cells.more(names[item[i]]); cells.next();
        }
    }

    /**
     * Of a unit: for each cell the run of the repetition that holds it (255: none), the first vectors of its users; from round 1 on
     * for each noisy method and run the noisy bits of its cells (if there are any) and the sums of noise by item.
     */
    public Object call(Object users, Object items, Object setting_, Object rep_, Object round_, Object said) {
        Plan x = plan((String) said);
        int setting = ((Integer) setting_).intValue(), rep = ((Integer) rep_).intValue(), t = ((Integer) round_).intValue();
        scala.collection.Seq us = (scala.collection.Seq) users, is = (scala.collection.Seq) items;
        int n = us.length(), d = x.d, of = Math.min(x.folds, x.runs - rep * x.folds);
        byte[][] names = x.names[x.kind[setting]];
        int[] item = new int[n];
        int[] at = new int[n];
        Keys cells = new Keys(n, 32 * n + 64), who = new Keys(n, 8 * n + 64);
        read(names, us, is, cells, who, item, at);
        int nu = who.n;
        byte[] end = utf(":" + rep);
        int[] fold = new int[nu];
        double[][] first = new double[d][nu];
        byte[] head = utf(x.seed + ":fold:"), begin = utf(x.seed + ":init_x:");
        for (int s = 0; s < nu; s += L) {
            int c = Math.min(L, nu - s);
            who.lay(s, c, head.length, end);
            long[] bits = who.hash(head);
            for (int j = 0; j < c; j++) fold[s + j] = (int) (bits[j] % x.folds);
            for (int k = 0; k < d; k++) {
                who.lay(s, c, begin.length, utf(":" + k));
                bits = who.hash(begin);
                for (int j = 0; j < c; j++) first[k][s + j] = 0.75 / Math.sqrt((double) d) * (0.5 + bits[j] * UNIT);
            }
        }
        byte[] held = new byte[n];
        byte[] mask = utf(x.seed + ":mask:");
        for (int s = 0; s < n; s += L) {
            int c = Math.min(L, n - s);
            cells.lay(s, c, mask.length, end);
            long[] bits = cells.hash(mask);
            for (int j = 0; j < c; j++) held[s + j] = (byte) (bits[j] * UNIT < x.unknown[setting] && fold[at[s + j]] < of ? fold[at[s + j]] : 255);
        }
        int wide = names.length, packed = (n + 7) / 8;
        long room = n + 8L * d * nu;
        for (int m = 0; t > 0 && m < x.noisy; m++) room += of * ((x.p[setting][m] > 0 ? packed : 0) + (x.scale[setting][m] > 0 ? 8L * d * wide : 0));
        ByteBuffer out = ByteBuffer.allocate(Math.toIntExact(room)).order(ByteOrder.LITTLE_ENDIAN);
        out.put(held);
        for (int k = 0; k < d; k++) for (int j = 0; j < nu; j++) out.putDouble(first[k][j]);
        for (int m = 0; t > 0 && m < x.noisy; m++) noise(x, out, cells, item, held, of, setting, rep, t, m, wide, packed);
        return out.array();
    }

    static byte[][] heads(Plan x, String purpose, int setting, int rep, int of) {
        byte[][] out = new byte[of][];
        for (int k = 0; k < of; k++) out[k] = utf(x.seed + ":" + purpose + ":" + (setting * x.runs + rep * x.folds + k) + ":");
        return out;
    }

    static void noise(Plan x, ByteBuffer out, Keys cells, int[] item, byte[] held, int of, int setting, int rep, int t, int m, int wide, int packed) {
        double p = x.p[setting][m], scale = x.scale[setting][m];
        int n = item.length, d = x.d;
        if (p == 0 && scale == 0) return;
        double[][] sums = new double[of * d][scale > 0 ? wide : 0];
        byte[][] bits = new byte[of][p > 0 ? packed : 0];
        double[][] share = new double[of][L];
        double[] drawn = new double[L];
        byte[][] flips = heads(x, "bit_flip", setting, rep, of), coins = heads(x, "bit_coin", setting, rep, of), laps = heads(x, "lap", setting, rep, of);
        double yes = (1 - p / 2) / (1 - p), no = (0 - p / 2) / (1 - p);
        for (int s = 0; s < n; s += L) {
            int c = Math.min(L, n - s);
            for (int k = 0; k < of; k++) java.util.Arrays.fill(share[k], 1.0);
            if (p > 0) {
                byte[] end = utf(":" + t);
                for (int k = 0; k < of; k++) {
                    if (k == 0 || flips[k].length != flips[k - 1].length) cells.lay(s, c, flips[k].length, end);
                    long[] got = cells.hash(flips[k]);
                    for (int j = 0; j < c; j++) share[k][j] = got[j] * UNIT < p ? no : yes;
                }
                for (int k = 0; k < of; k++) {
                    if (k == 0 || coins[k].length != coins[k - 1].length) cells.lay(s, c, coins[k].length, end);
                    long[] got = cells.hash(coins[k]);
                    for (int j = 0; j < c; j++) {
                        if (share[k][j] == no && got[j] * UNIT < 0.5) share[k][j] = yes;
                        if (share[k][j] == yes) bits[k][(s + j) >> 3] |= (byte) (1 << ((s + j) & 7));
                    }
                }
            }
            if (scale == 0) continue;
            for (int k = 0; k < of; k++) for (int j = 0; j < c; j++) if (held[s + j] == (byte) k) share[k][j] = 0;
            for (int i = 0; i < d; i++) {
                byte[] end = utf(":" + t + ":" + i);
                for (int k = 0; k < of; k++) {
                    if (k == 0 || laps[k].length != laps[k - 1].length) cells.lay(s, c, laps[k].length, end);
                    laplace(cells.hash(laps[k]), scale, drawn, c);
                    double[] to = sums[k * d + i], by = share[k];
                    for (int j = 0; j < c; j++) to[item[s + j]] += drawn[j] * by[j];
                }
            }
        }
        for (int k = 0; k < of; k++) {
            out.put(bits[k]);
            for (int i = 0; i < d; i++) for (int j = 0; j < sums[k * d + i].length; j++) out.putDouble(sums[k * d + i][j]);
        }
    }
}
"""
_MADE: dict[str, object] = {}
#: Room of a vector in the class.
ROOM = 4


def function(spark: SparkSession):
    """The class in this application, or None where it can't be made."""
    try:
        app = spark.sparkContext.applicationId
        if app not in _MADE:
            jvm = spark._jvm
            compiler = jvm.org.codehaus.janino.SimpleCompiler()
            compiler.cook(SOURCE)
            path = os.path.join(tempfile.mkdtemp(prefix="locpref-"), "lanes.jar")
            with zipfile.ZipFile(path, "w") as z:
                for name, code in dict(compiler.getBytecodes()).items():
                    z.writestr(name.replace(".", "/") + ".class", bytes(code))
            spark.sparkContext._jsc.addJar(path)
            _MADE[app] = compiler.getClassLoader().loadClass("locpref.Lanes").getDeclaredConstructor(spark.sparkContext._gateway.new_array(jvm.java.lang.Class, 0)).newInstance(spark.sparkContext._gateway.new_array(jvm.java.lang.Object, 0))
        spark._jsparkSession.udf().register("locpref_lanes", _MADE[app], spark._jvm.org.apache.spark.sql.types.DataTypes.BinaryType)
        return True
    except AttributeError:  # a session without a JVM of its own
        return None


class Known:
    """What the passes of a fit know on the executors: the plan, and a broadcast of item vectors for each round. ``stored`` has a row for each unit (cells, users, item, rating, truth)."""

    def __init__(self, stored: DataFrame, said: str):
        self.stored, self.spark = stored, stored.sparkSession
        self.made = _MADE[self.spark.sparkContext.applicationId].begun(self.spark.sparkContext._jsc, said)
        self.numbers = ""

    def more(self, vectors: Iterable[np.ndarray]) -> None:
        """Vectors of one more round, each array with a column for each item."""
        with tempfile.NamedTemporaryFile(prefix="locpref-") as f:
            for z in vectors:
                f.write(np.ascontiguousarray(np.pad(z, ((0, ROOM - len(z)), (0, 0))).T, "<f8").tobytes())
            f.flush()
            self.made = self.made.more(self.spark.sparkContext._jsc, f.name)

    def end(self) -> None:
        self.made.end()


def known(stored: DataFrame | None, said: str | None, d: int) -> Known | None:
    return None if stored is None or said is None or d > ROOM or not function(stored.sparkSession) else Known(stored, said)


def with_draws(units: DataFrame, said: str, t: int, known: Known | None = None) -> DataFrame:
    """Units with what the class draws for round ``t`` (0: what no round changes), if it is there. With what is ``known``, the sums of a pass by task are drawn instead."""
    if known is not None:
        jvm = known.spark._jvm
        schema = jvm.org.apache.spark.sql.types.StructType.fromDDL("setting int, rep int, method int, drawn binary")
        return DataFrame(known.made.summed(known.stored._jdf, known.numbers, jvm.org.apache.spark.sql.Encoders.row(schema)), known.spark)
    if said is None or not function(units.sparkSession):
        return units
    args: list[Column] = [F.col(c) for c in ("users", "item", "setting", "rep")]
    return units.withColumn("drawn", F.call_function("locpref_lanes", *args, F.lit(t), F.lit(said)))
