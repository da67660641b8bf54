"""The fold of `chain.fit_table` in Spark's own tasks: sequences stream past one segment's weights.

A step of a few tags and some dozen positions is too small for arrays, and too many
plain operations for Python; here it takes microseconds.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..functions import jvm
from . import sparse

NAME = "gradfold.ChainFold"
OUT = f"seg long, {sparse.OUT}"

JAVA = """
package gradfold;

import java.util.Arrays;
import java.util.Iterator;
import org.apache.spark.sql.Row;
import org.apache.spark.sql.RowFactory;

/** Folds one segment: (seg, k, n, sizes, feats, tags) in the order of k, from the weights (seg, feature, w) in the order of feature. */
public final class ChainFold implements org.apache.spark.api.java.function.CoGroupFunction {
  private int kinds;
  private double alpha;
  private double mu;

  public void set(int kinds, double alpha, double mu) {
    this.kinds = kinds;
    this.alpha = alpha;
    this.mu = mu;
  }

  public Iterator call(Object seg, Iterator sequences, Iterator weights) {
    Weights own = new Weights(kinds, weights);
    Steps steps = new Steps(own, alpha, mu);
    while (sequences.hasNext()) steps.step((Row) sequences.next());
    return new Result((Long) seg, own, steps.n, steps.loss);
  }
}

/** A segment's weights: the moves, and a row for each of its features, found by an open hash. */
final class Weights {
  final int kinds;
  final double[] move;
  double[] emit = new double[1 << 12];
  long[] features = new long[1 << 10];
  int size = 0;
  private int[] slots = new int[1 << 12];

  Weights(int kinds, Iterator weights) {
    this.kinds = kinds;
    move = new double[kinds * kinds];
    while (weights.hasNext()) {
      Row row = (Row) weights.next();
      long key = row.getLong(1);
      double w = row.getDouble(2);
      if (key < 0) {
        move[(int) (-1 - key)] = w;
        continue;
      }
      int tag = (int) (key % kinds);
      int at = place(key / kinds); // `emit` may be another array after this
      emit[at + tag] = w;
    }
  }

  private int spot(long feature) {
    return (int) ((feature * 0x9E3779B97F4A7C15L) >>> 32) & (slots.length - 1);
  }

  /** Where a feature's weights in `emit` begin; those of a feature that is new are zero. */
  int place(long feature) {
    int at = spot(feature);
    while (slots[at] != 0) {
      if (features[slots[at] - 1] == feature) return (slots[at] - 1) * kinds;
      at = (at + 1) & (slots.length - 1);
    }
    if (size == features.length) features = Arrays.copyOf(features, 2 * size);
    if ((size + 1) * kinds > emit.length) emit = Arrays.copyOf(emit, 2 * (size + 1) * kinds);
    features[size++] = feature;
    slots[at] = size;
    if (2 * size > slots.length) {
      slots = new int[2 * slots.length];
      for (int i = 0; i < size; i++) {
        at = spot(features[i]);
        while (slots[at] != 0) at = (at + 1) & (slots.length - 1);
        slots[at] = i + 1;
      }
    }
    return (size - 1) * kinds;
  }
}

/** Incremental steps, a sequence at a time. */
final class Steps {
  private final Weights own;
  private final int k;
  private final double alpha, mu;
  private double[] pot = new double[0], e, f, b, single;
  private double[] top;
  private int[] places = new int[0];
  private final double[] m, pair, sums;
  long n = 0;
  double loss = 0;

  Steps(Weights own, double alpha, double mu) {
    this.own = own;
    this.k = own.kinds;
    this.alpha = alpha;
    this.mu = mu;
    m = new double[k * k];
    pair = new double[k * k];
    sums = new double[k];
  }

  /** The numbers of a binary value, `count` of one width. */
  private static int[] numbers(byte[] raw, int count) {
    int[] out = new int[count];
    int width = count == 0 ? 1 : raw.length / count;
    for (int i = 0; i < count; i++) {
      int v = 0;
      for (int j = width - 1; j >= 0; j--) v = v << 8 | raw[i * width + j] & 0xFF;
      out[i] = v;
    }
    return out;
  }

  void step(Row row) {
    int length = row.getInt(2), cells = 0;
    int[] sizes = numbers((byte[]) row.get(3), length);
    for (int t = 0; t < length; t++) cells += sizes[t];
    n++;
    step(length, sizes, cells, numbers((byte[]) row.get(4), cells), numbers((byte[]) row.get(5), length));
  }

  private void step(int length, int[] sizes, int cells, int[] feats, int[] tags) {
    if (length == 0) return;
    if (pot.length < length * k) {
      int room = 2 * length * k;
      pot = new double[room];
      e = new double[room];
      f = new double[room];
      b = new double[room];
      single = new double[room];
      top = new double[2 * length];
    }
    if (places.length < cells) places = new int[2 * cells];
    for (int c = 0; c < cells; c++) places[c] = own.place(feats[c]);
    double[] emit = own.emit;
    double[] move = own.move;
    double score = 0;
    int c = 0;
    for (int t = 0; t < length; t++) {
      for (int j = 0; j < k; j++) pot[t * k + j] = 0;
      for (int i = 0; i < sizes[t]; i++, c++) {
        for (int j = 0; j < k; j++) pot[t * k + j] += emit[places[c] + j];
      }
      score += pot[t * k + tags[t]];
      if (t > 0) score += move[tags[t - 1] * k + tags[t]];
    }
    double z = scaled(length);
    if (Double.isNaN(z)) z = logs(length);
    loss += z - score;
    c = 0;
    for (int t = 0; t < length; t++) {
      for (int i = 0; i < sizes[t]; i++, c++) {
        for (int j = 0; j < k; j++) emit[places[c] + j] += alpha * ((j == tags[t] ? 1.0 : 0.0) - single[t * k + j]);
      }
    }
    for (int t = 1; t < length; t++) pair[tags[t - 1] * k + tags[t]] -= 1;
    for (int i = 0; i < k * k; i++) move[i] -= alpha * pair[i];
    if (mu != 0) {
      shrink(emit, own.size * k);
      shrink(move, k * k);
    }
  }

  private void shrink(double[] w, int size) {
    for (int i = 0; i < size; i++) w[i] = Math.signum(w[i]) * Math.max(Math.abs(w[i]) - alpha * mu, 0);
  }

  /** Marginals into `single` and `pair` by numbers scaled at each position, and the log partition; NaN if they leave the range of doubles. */
  private double scaled(int length) {
    double[] move = own.move;
    double lift = move[0];
    for (int i = 1; i < k * k; i++) lift = Math.max(lift, move[i]);
    for (int i = 0; i < k * k; i++) {
      m[i] = Math.exp(move[i] - lift);
      pair[i] = 0;
    }
    double z = (length - 1) * lift;
    for (int t = 0; t < length; t++) {
      double high = pot[t * k];
      for (int j = 1; j < k; j++) high = Math.max(high, pot[t * k + j]);
      z += high;
      double total = 0;
      for (int j = 0; j < k; j++) {
        e[t * k + j] = Math.exp(pot[t * k + j] - high);
        double v = 1;
        if (t > 0) {
          v = 0;
          for (int i = 0; i < k; i++) v += f[(t - 1) * k + i] * m[i * k + j];
        }
        f[t * k + j] = v * e[t * k + j];
        total += f[t * k + j];
      }
      if (!(total > 0)) return Double.NaN;
      for (int j = 0; j < k; j++) f[t * k + j] /= total;
      z += Math.log(total);
    }
    for (int t = length - 1; t >= 0; t--) {
      double total = 0;
      if (t == length - 1) {
        for (int i = 0; i < k; i++) b[t * k + i] = 1.0;
        total = k;
      } else {
        double between = 0;
        for (int j = 0; j < k; j++) {
          sums[j] = e[(t + 1) * k + j] * b[(t + 1) * k + j];
          double ahead = 0;
          for (int i = 0; i < k; i++) ahead += f[t * k + i] * m[i * k + j];
          between += ahead * sums[j];
        }
        if (!(between > 0)) return Double.NaN;
        for (int i = 0; i < k; i++) {
          double v = 0;
          for (int j = 0; j < k; j++) {
            v += m[i * k + j] * sums[j];
            pair[i * k + j] += m[i * k + j] * (f[t * k + i] / between) * sums[j];
          }
          b[t * k + i] = v;
          total += v;
        }
      }
      if (!(total > 0)) return Double.NaN;
      double all = 0;
      for (int i = 0; i < k; i++) {
        b[t * k + i] /= total;
        single[t * k + i] = f[t * k + i] * b[t * k + i];
        all += single[t * k + i];
      }
      if (!(all > 0)) return Double.NaN;
      for (int i = 0; i < k; i++) single[t * k + i] /= all;
    }
    return z;
  }

  /** The same in the log domain. */
  private double logs(int length) {
    double[] move = own.move;
    for (int t = 0; t < length; t++) {
      for (int j = 0; j < k; j++) {
        if (t > 0) for (int i = 0; i < k; i++) sums[i] = f[(t - 1) * k + i] + move[i * k + j];
        f[t * k + j] = pot[t * k + j] + (t > 0 ? lse() : 0);
      }
    }
    for (int t = length - 1; t >= 0; t--) {
      for (int i = 0; i < k; i++) {
        if (t < length - 1) for (int j = 0; j < k; j++) sums[j] = move[i * k + j] + pot[(t + 1) * k + j] + b[(t + 1) * k + j];
        b[t * k + i] = t < length - 1 ? lse() : 0;
      }
    }
    for (int j = 0; j < k; j++) sums[j] = f[(length - 1) * k + j];
    double z = lse();
    for (int i = 0; i < k * k; i++) pair[i] = 0;
    for (int t = 0; t < length; t++) {
      for (int j = 0; j < k; j++) {
        single[t * k + j] = Math.exp(f[t * k + j] + b[t * k + j] - z);
        if (t > 0) for (int i = 0; i < k; i++) pair[i * k + j] += Math.exp(f[(t - 1) * k + i] + move[i * k + j] + pot[t * k + j] + b[t * k + j] - z);
      }
    }
    return z;
  }

  private double lse() {
    double high = sums[0], total = 0;
    for (int i = 1; i < k; i++) high = Math.max(high, sums[i]);
    for (int i = 0; i < k; i++) total += Math.exp(sums[i] - high);
    return high + Math.log(total);
  }
}

/** Rows (seg, feature, w, n, loss): the segment's sequences and loss stand in the first one. */
final class Result implements Iterator {
  private final Long seg;
  private final Weights own;
  private final long n;
  private final double loss;
  private int next = 0;

  Result(Long seg, Weights own, long n, double loss) {
    this.seg = seg;
    this.own = own;
    this.n = n;
    this.loss = loss;
  }

  public boolean hasNext() {
    return next < own.move.length + own.size * own.kinds;
  }

  public Object next() {
    int i = next++;
    int at = i - own.move.length;
    long key = at < 0 ? -1 - i : own.features[at / own.kinds] * own.kinds + at % own.kinds;
    double w = at < 0 ? own.move[i] : own.emit[at];
    return RowFactory.create(new Object[] {seg, Long.valueOf(key), Double.valueOf(w), Long.valueOf(i == 0 ? n : 0L), i == 0 ? Double.valueOf(loss) : null});
  }

  public void remove() {
    throw new UnsupportedOperationException();
  }
}
"""


def folded(sequences: DataFrame, weights: DataFrame, tags: int, alpha: float, mu: float = 0.0) -> DataFrame:
    """(seg, feature, w, n, loss): the weights of each segment after its sequences, in order, from (seg, feature, w), where features that are missing weigh nothing."""
    fold = jvm.compiled(sequences.sparkSession, NAME, JAVA).newInstance()
    fold.set(tags, float(alpha), float(mu))
    return jvm.cogrouped(sequences, weights, "seg", ("k", "feature"), fold, OUT)
