"""Sequential descent of wide models as compiled code.

A step of a wide model is a few thousand operations on numbers, which depend on the step before: as calls of array functions they cost mostly the calls. The source below is
compiled by the compiler that Spark uses for its own generated code, goes to the executors as a jar, once per application, and reads the rows of ``descent.packed`` where they are.
It takes the steps of ``descent.Walk``, with draws of its own for each fold.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import threading
import zipfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldpspark.functions import constants as C

SOURCE = """
package ldpspark;

import java.nio.ByteBuffer;
import java.nio.ByteOrder;
import java.util.ArrayList;
import java.util.Iterator;
import java.util.List;
import java.util.SplittableRandom;

public class Walks implements org.apache.spark.api.java.function.MapPartitionsFunction, java.io.Serializable {
    static final long serialVersionUID = 1L;
    int kind;
    boolean halfspace;
    double lam, gamma;
    long seed, most;
    double[] inside, other;
    // by model
    int[] part, fold;
    String[] name;
    double[] chance, size;

    /** Lines: kind, lam, step size, 1 for half-space reports, seed, most users of a model; two cumulative tables; then a line for each model. */
    public void configure(String text) {
        String[] lines = text.split("\\n");
        String[] h = lines[0].split(" ");
        kind = Integer.parseInt(h[0]);
        lam = Double.parseDouble(h[1]);
        gamma = Double.parseDouble(h[2]);
        halfspace = h[3].equals("1");
        seed = Long.parseLong(h[4]);
        most = Long.parseLong(h[5]);
        inside = numbers(lines[1]);
        other = numbers(lines[2]);
        int n = lines.length - 3;
        part = new int[n];
        fold = new int[n];
        name = new String[n];
        chance = new double[n];
        size = new double[n];
        for (int i = 0; i < n; i++) {
            String[] m = lines[i + 3].split(" ", 5);
            part[i] = Integer.parseInt(m[0]);
            fold[i] = Integer.parseInt(m[1]);
            chance[i] = Double.parseDouble(m[2]);
            size[i] = Double.parseDouble(m[3]);
            name[i] = m[4];
        }
    }

    static double[] numbers(String line) {
        String[] s = line.split(" ");
        double[] out = new double[s.length];
        for (int i = 0; i < s.length; i++) out[i] = Double.parseDouble(s[i]);
        return out;
    }

    /** The models of a fold, which step together. */
    static class Fold {
        int number, d;
        int[] models;
        double[][] w;
        long seen;
        SplittableRandom rng;
        double[] low, in, out;
        int[] order;
    }

    public Iterator call(Iterator rows) throws Exception {
        Fold[] folds = null;
        int own = -1;
        while (rows.hasNext()) {
            org.apache.spark.sql.Row r = (org.apache.spark.sql.Row) rows.next();
            int n = r.getInt(1), d = r.getInt(2);
            if (folds == null) {
                own = r.getInt(0);
                folds = started(own, d);
            }
            if (r.getInt(0) != own) throw new IllegalStateException("a task got two streams");
            byte[] raw = new byte[4 * n + 8 * n * (d + 1)];
            if (com.github.luben.zstd.Zstd.decompress(raw, (byte[]) r.get(3)) != raw.length) throw new IllegalStateException("a row of packed users is broken");
            ByteBuffer b = ByteBuffer.wrap(raw);
            b.order(ByteOrder.LITTLE_ENDIAN);
            int[] at = new int[n];
            for (int k = 0; k < n; k++) at[k] = b.getInt(4 * k);
            double[] y = new double[n], x = new double[n * d];
            for (int k = 0; k < n; k++) y[k] = b.getDouble(4 * n + 8 * k);
            for (int j = 0; j < d; j++) {
                int from = 4 * n + 8 * n * (j + 1);
                for (int k = 0; k < n; k++) x[k * d + j] = b.getDouble(from + 8 * k);
            }
            for (int i = 0; i < folds.length; i++) {
                Fold f = folds[i];
                for (int k = 0; k < n; k++) {
                    if (at[k] == f.number || (most >= 0 && f.seen >= most)) continue;
                    if (halfspace) reported(f, x, k * d, y[k]);
                    else exact(f, x, k * d, y[k]);
                }
                for (int e = 0; e < f.w.length; e++)
                    for (int j = 0; j < d; j++)
                        if (Double.isNaN(f.w[e][j]) || Double.isInfinite(f.w[e][j])) throw new ArithmeticException("weights are no longer finite; take a smaller gamma0");
            }
        }
        List done = new ArrayList();
        for (int i = 0; folds != null && i < folds.length; i++) {
            Fold f = folds[i];
            for (int e = 0; f.seen > 0 && e < f.w.length; e++) {
                StringBuilder s = new StringBuilder();
                for (int j = 0; j < f.d; j++) s.append(j == 0 ? "" : ",").append(Double.toString(f.w[e][j]));
                done.add(org.apache.spark.sql.RowFactory.create(new Object[] {name[f.models[e]], Long.valueOf(f.seen), s.toString()}));
            }
        }
        return done.iterator();
    }

    Fold[] started(int own, int d) {
        List out = new ArrayList();
        for (int i = 0; i < part.length; i++) {
            if (part[i] != own) continue;
            int many = 0;
            boolean known = false;
            for (int k = 0; k < part.length; k++) {
                if (fold[k] != fold[i]) continue;
                many++;
                known = known || k < i;
            }
            if (known) continue;
            Fold f = new Fold();
            f.number = fold[i];
            f.d = d;
            f.models = new int[many];
            f.w = new double[many][d];
            f.rng = new SplittableRandom(new SplittableRandom(seed * 1000003L + fold[i]).nextLong());
            f.low = new double[d];
            f.in = new double[d];
            f.out = new double[d];
            f.order = new int[d];
            for (int k = 0; k < d; k++) f.order[k] = k;
            int e = 0;
            for (int k = 0; k < part.length; k++) if (fold[k] == fold[i]) f.models[e++] = k;
            out.add(f);
        }
        Fold[] all = new Fold[out.size()];
        for (int i = 0; i < all.length; i++) all[i] = (Fold) out.get(i);
        return all;
    }

    static double score(double[] w, double[] x, int o) {
        double a = 0, b = 0, c = 0, e = 0;
        int j = 0;
        for (; j + 3 < w.length; j += 4) {
            a += w[j] * x[o + j];
            b += w[j + 1] * x[o + j + 1];
            c += w[j + 2] * x[o + j + 2];
            e += w[j + 3] * x[o + j + 3];
        }
        for (; j < w.length; j++) a += w[j] * x[o + j];
        return (a + b) + (c + e);
    }

    static double slope(int kind, double s, double y) {
        if (kind == 0) return 2 * (s - y);
        if (kind == 1) return -y / (1 + Math.exp(Math.min(y * s, 700)));
        return y * s < 1 ? -y : 0.0;
    }

    void exact(Fold f, double[] x, int o, double y) {
        f.seen++;
        double step = gamma / Math.sqrt((double) f.seen);
        for (int e = 0; e < f.w.length; e++) {
            double[] w = f.w[e];
            double s = slope(kind, score(w, x, o), y);
            for (int j = 0; j < w.length; j++) w[j] -= step * (s * x[o + j] + lam * w[j]);
        }
    }

    /** A step on half-space reports: the draws of a user are those of all budgets of a fold. */
    void reported(Fold f, double[] x, int o, double y) {
        f.seen++;
        double step = gamma / Math.sqrt((double) f.seen);
        int d = f.d;
        SplittableRandom rng = f.rng;
        double[] low = f.low;
        for (int j = 0; j < d; j++) low[j] = 2 * rng.nextDouble() - 1;
        for (int j = d - 1; j > 0; j--) {
            int i = rng.nextInt(j + 1);
            int t = f.order[j];
            f.order[j] = f.order[i];
            f.order[i] = t;
        }
        double u = rng.nextDouble(), toss = rng.nextDouble();
        spread(f.in, f.order, places(inside, u));
        spread(f.out, f.order, places(other, u));
        for (int e = 0; e < f.w.length; e++) {
            int m = f.models[e];
            stepped(f.w[e], x, o, slope(kind, score(f.w[e], x, o), y), lam, low, toss < chance[m] ? f.in : f.out, step * size[m]);
        }
    }

    /** A place is sent as 1 where its uniform number is below (1 + gradient) / 2, and as it is where ``as`` is 1. */
    static void stepped(double[] w, double[] x, int o, double s, double lam, double[] low, double[] as, double far) {
        for (int j = 0; j < w.length; j++) {
            double g = s * x[o + j] + lam * w[j];
            w[j] += Math.copySign(far, (low[j] - g) * as[j]);
        }
    }

    static int places(double[] cdf, double u) {
        int k = 0;
        while (k < cdf.length && cdf[k] <= u) k++;
        return k;
    }

    static void spread(double[] as, int[] order, int own) {
        for (int t = 0; t < order.length; t++) as[order[t]] = t < own ? 1.0 : -1.0;
    }
}
"""

_KINDS = {"linear": 0, "logistic": 1, "svm": 2}
_sent: dict[str, object] = {}
_lock = threading.Lock()


def _walks(spark: SparkSession):
    """A new instance of the compiled class, which the executors get as a jar."""
    sc = spark.sparkContext
    with _lock:
        if sc.applicationId not in _sent:
            compiler = sc._jvm.org.codehaus.janino.SimpleCompiler()
            compiler.setParentClassLoader(sc._jvm.Thread.currentThread().getContextClassLoader())
            compiler.cook(SOURCE)
            folder = tempfile.mkdtemp(prefix="walks-")
            atexit.register(shutil.rmtree, folder, True)
            path = os.path.join(folder, "ldpspark-walks.jar")
            with zipfile.ZipFile(path, "w") as z:
                for name, code in compiler.getBytecodes().items():
                    z.writestr(name.replace(".", "/") + ".class", bytes(code))
            sc._jsc.addJar(path)
            _sent[sc.applicationId] = compiler.getClassLoader().loadClass("ldpspark.Walks")
    return _sent[sc.applicationId].newInstance()


def walked(rows: DataFrame, models: list[tuple[int, int, str, float]], dim: int, kind: str, lam: float, gamma0: float, halfspace: bool, seed: int, max_users: int | None) -> DataFrame:
    """(model, users, weights) of descent over ``rows`` (``descent._streams``) of the models (part, fold, name, eps)."""
    spark = rows.sparkSession
    lines = [f"{_KINDS[kind]} {float(lam)!r} {float(gamma0)!r} {int(halfspace)} {seed} {-1 if max_users is None else max_users}"]
    lines += [" ".join(repr(float(v)) for v in c) for c in (C.halfspace_cdf(dim) if halfspace else ([0.0], [0.0]))]
    for part, fold, name, eps in models:
        chance, size = (C.halfspace_prob(dim, eps), C.halfspace_scale(dim, eps)) if halfspace else (0.0, 0.0)
        lines.append(f"{part} {fold} {float(chance)!r} {float(size)!r} {name}")
    walks = _walks(spark)
    walks.configure("\n".join(lines))
    schema = spark._jvm.org.apache.spark.sql.types.StructType.fromDDL("model string, users long, weights string")
    found = rows.select("part", "rows", "dim", "base")._jdf.mapPartitions(walks, spark._jvm.org.apache.spark.sql.Encoders.row(schema))
    return DataFrame(found, spark).select("model", "users", F.split("weights", ",").cast("array<double>").alias("weights"))
