"""The context coder as functions of the JVM: the steps of `codec.OrderStep` and of the range coder, one lane after the other.

Only sums, products, quotients and comparisons of doubles in the order in which numpy takes them, so the bytes are those of the
numpy form on any machine. The source is compiled by the compiler that Spark brings along for its own plans; the classes go to
the executors as a jar. Sessions without a JVM at hand keep the numpy form.
"""

from __future__ import annotations

import logging
import os
import tempfile
import zipfile

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from .coder import EXP2, LOG2

#: Contexts of more bases than this stay with numpy, whose numbers may wrap there.
LONGEST = 12
MOST = 16

SOURCE = """
package basepack;

public class Contexts {
    static final double[] L2 = {%(log2)s};
    static final double[] E2 = {%(exp2)s};
    static final ThreadLocal KEPT = new ThreadLocal();

    final String name;
    final int count;
    final int[] order;
    final long slots;
    final int[][] table;
    final int[] at;
    final double[] score, weight, probs = new double[64], p = new double[4];
    final int[] n = new int[4];
    final double alpha, decay;
    long past, mask;

    Contexts(String name) {
        String[] parts = name.split(" ");
        this.name = name;
        slots = Long.parseLong(parts[0]);
        alpha = Double.parseDouble(parts[1]);
        decay = Double.parseDouble(parts[2]);
        count = parts.length - 3;
        order = new int[count];
        table = new int[count][];
        at = new int[count];
        score = new double[count];
        weight = new double[count];
        for (int o = 0; o < count; o++) {
            order[o] = Integer.parseInt(parts[o + 3]);
            table[o] = new int[(int) (4 * Math.min(slots, 1L << (2 * order[o])))];
            mask = Math.max(mask, (1L << (2 * order[o])) - 1);
        }
    }

    /** Cleared tables of these slots and orders. */
    static Contexts of(String name) {
        Contexts found = (Contexts) KEPT.get();
        if (found == null || !found.name.equals(name)) {
            found = new Contexts(name);
            KEPT.set(found);
        } else {
            for (int o = 0; o < found.count; o++) java.util.Arrays.fill(found.table[o], 0);
            java.util.Arrays.fill(found.score, 0.0);
            found.past = 0;
        }
        return found;
    }

    static double log2(double x) {
        long u = Double.doubleToRawLongBits(x);
        int e = (int) (u >>> 52) - 1022;
        double m = Double.longBitsToDouble((u & 0xFFFFFFFFFFFFFL) | (1022L << 52));
        if (m < 0.70710678118654757) { m = m + m; e = e - 1; }
        double s = (m - 1.0) / (m + 1.0), z = s * s, y = L2[0];
        for (int i = 1; i < L2.length; i++) y = y * z + L2[i];
        return e + s * y;
    }

    static double exp2(double x) {
        double n = Math.rint(x), f = x - n, y = E2[0];
        for (int i = 1; i < E2.length; i++) y = y * f + E2[i];
        return y * Double.longBitsToDouble((1023L + (long) n) << 52);
    }

    /** Counts of the next base, of 2^16 in all, to n. */
    void step() {
        double best = score[0];
        for (int o = 0; o < count; o++) {
            long size = 1L << (2 * order[o]), key = past & (size - 1);
            if (size > slots) key = (key * 2654435761L >>> 7) %% slots;
            int k = (int) key * 4;
            int[] t = table[o];
            at[o] = k;
            double a = t[k] + alpha, b = t[k + 1] + alpha, c = t[k + 2] + alpha, d = t[k + 3] + alpha, total = ((a + b) + c) + d;
            probs[4 * o] = a / total;
            probs[4 * o + 1] = b / total;
            probs[4 * o + 2] = c / total;
            probs[4 * o + 3] = d / total;
            if (score[o] > best) best = score[o];
        }
        double a = 0, b = 0, c = 0, d = 0, all = 0;
        for (int o = 0; o < count; o++) {
            double w = exp2(Math.max(score[o] - best, -40.0));
            int k = 4 * o;
            all = all + w;
            a = a + probs[k] * w;
            b = b + probs[k + 1] * w;
            c = c + probs[k + 2] * w;
            d = d + probs[k + 3] * w;
        }
        a = Math.rint(a / all * 65536.0) / 65536.0;
        b = Math.rint(b / all * 65536.0) / 65536.0;
        c = Math.rint(c / all * 65536.0) / 65536.0;
        d = Math.rint(d / all * 65536.0) / 65536.0;
        double total = ((a + b) + c) + d;
        n[0] = 1 + (int) (a / total * 65532.0);
        n[1] = 1 + (int) (b / total * 65532.0);
        n[2] = 1 + (int) (c / total * 65532.0);
        n[3] = 1 + (int) (d / total * 65532.0);
        int top = 0;
        for (int i = 1; i < 4; i++) if (n[i] > n[top]) top = i;
        n[top] += 65536 - (n[0] + n[1] + n[2] + n[3]);
    }

    void learn(int base) {
        for (int o = 0; o < count; o++) {
            score[o] = score[o] * decay + log2(probs[4 * o + base]);
            table[o][at[o] + base]++;
        }
        past = (past * 4 + base) & mask;
    }

    byte[] encode(String bases) {
        byte[] out = new byte[bases.length() / 2 + 64];
        long low = 0, range = 0xFFFFFFFFL;
        int size = 0;
        for (int t = 0; t < bases.length(); t++) {
            char letter = bases.charAt(t);
            int now = letter == 'G' ? 1 : letter == 'C' ? 2 : letter == 'T' ? 3 : 0;
            step();
            long start = 0, r = range >>> 16;
            for (int i = 0; i < now; i++) start += n[i];
            low += start * r;
            range = n[now] * r;
            if (low >>> 32 != 0) {
                for (int i = size - 1; i >= 0; i--) { out[i]++; if (out[i] != 0) break; }
                low &= 0xFFFFFFFFL;
            }
            if (size + 16 > out.length) out = java.util.Arrays.copyOf(out, 2 * out.length);
            while (range < (1L << 24)) { out[size++] = (byte) (low >>> 24); low = (low << 8) & 0xFFFFFFFFL; range <<= 8; }
            learn(now);
        }
        for (int i = 0; i < 4; i++) { out[size++] = (byte) (low >>> 24); low = (low << 8) & 0xFFFFFFFFL; }
        while (size > 0 && out[size - 1] == 0) size--;
        return java.util.Arrays.copyOf(out, size);
    }

    String decode(byte[] data, int length) throws Exception {
        byte[] out = new byte[length];
        long code = 0, range = 0xFFFFFFFFL;
        int next = 0;
        for (; next < 4; next++) code = (code << 8) | (next < data.length ? data[next] & 255 : 0);
        for (int t = 0; t < length; t++) {
            step();
            long start = 0, r = range >>> 16, value = Math.min(code / r, 65535L);
            int now = 0;
            while (now < 3 && start + n[now] <= value) start += n[now++];
            code -= start * r;
            range = n[now] * r;
            while (range < (1L << 24)) { code = (code << 8) | (next < data.length ? data[next] & 255 : 0); next++; range <<= 8; }
            learn(now);
            out[t] = (byte) "AGCT".charAt(now);
        }
        return new String(out, "ISO-8859-1");
    }
}
"""

ENCODE = """
public class ContextEncode implements org.apache.spark.sql.api.java.UDF2 {
    public Object call(Object bases, Object name) throws Exception {
        return bases == null ? null : Contexts.of((String) name).encode((String) bases);
    }
}
"""

DECODE = """
public class ContextDecode implements org.apache.spark.sql.api.java.UDF3 {
    public Object call(Object data, Object length, Object name) throws Exception {
        return data == null ? null : Contexts.of((String) name).decode((byte[]) data, ((Integer) length).intValue());
    }
}
"""


def _jar(spark: SparkSession) -> str:
    listed = lambda xs: ", ".join(float(x).hex() for x in xs)
    source = SOURCE % {"log2": listed(LOG2), "exp2": listed(EXP2)}
    compiler = spark.sparkContext._jvm.org.codehaus.janino.SimpleCompiler()
    compiler.cook(source + ENCODE + DECODE)
    path = os.path.join(tempfile.mkdtemp(prefix="basepack-"), "basepack-context.jar")
    with zipfile.ZipFile(path, "w") as z:
        for name, data in compiler.getBytecodes().items():
            z.writestr(name.replace(".", "/") + ".class", bytes(data))
    return path


def _register(spark: SparkSession, name: str, kind: str, returns: str) -> None:
    """As registerJavaFunction, for classes without generic signatures, which that compiler does not write."""
    jvm, none = spark.sparkContext._jvm, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.java.lang.Object, 0)
    loader = jvm.java.lang.Thread.currentThread().getContextClassLoader()
    found = jvm.java.lang.Class.forName(kind, True, loader).getConstructors()[0].newInstance(none)
    spark._jsparkSession.udf().register(name, found, jvm.org.apache.spark.sql.types.DataType.fromDDL(returns))


def ready(spark: SparkSession) -> bool:
    """Whether this session has the functions; registers them the first time."""
    found = getattr(spark, "_basepack_contexts", None)
    if found is None:
        try:
            spark.sql(f"ADD JAR '{_jar(spark)}'")
            _register(spark, "basepack_context_encode", "basepack.ContextEncode", "binary")
            _register(spark, "basepack_context_decode", "basepack.ContextDecode", "string")
            found = True
        except Exception as e:
            logging.getLogger(__name__).warning("the context coder runs in Python: %s", e)
            found = False
        spark._basepack_contexts = found
    return found


def _name(orders, slots: int, alpha: float, decay: float) -> Column:
    return F.lit(" ".join(map(str, (slots, alpha, decay, *orders))))


def encoded(bases: Column, *model) -> Column:
    """Payload of each value, a lane of its own; model: orders, slots, alpha, decay."""
    return F.call_function("basepack_context_encode", bases, _name(*model))


def decoded(payload: Column, n_bases: Column, *model) -> Column:
    return F.call_function("basepack_context_decode", payload, n_bases.cast("int"), _name(*model))
