"""The exact page codec in Java: the bytes of ``functions.frame``, planned, written and read by the executors' JVM.

Janino, the compiler that Spark brings along, turns ``SOURCE`` into a class; no other tool is needed.
Everything follows the numpy kernels step by step, ties included; ``tests/test_jvm.py`` compares the bytes.
"""

SOURCE = r"""
package latticepages;

public class Pages implements org.apache.spark.sql.api.java.UDF2 {
    static final int PREDICTORS = 1, SPLIT = 2, RICE = 4, GCD = 8, AFFINE = 16, UPPER = 32, PERSIST = 64, PREDICT = 128, LEARN = 256, VERIFY = 512;
    static final long NONE = 1L << 60;

    /** Words (little-endian) and block,lanes,flags,alpha of the profile to (big-endian): encode ns, decode ns, mismatches, bits by part, length of the metadata, frame. */
    public Object call(Object words, Object profile) throws Exception {
        java.nio.ByteBuffer in = java.nio.ByteBuffer.wrap((byte[]) words).order(java.nio.ByteOrder.LITTLE_ENDIAN);
        long[] w = new long[in.remaining() / 8];
        for (int i = 0; i < w.length; i++) w[i] = in.getLong();
        String[] p = ((String) profile).split(",");
        int flags = Integer.parseInt(p[2]);
        long t0 = System.nanoTime();
        Page page = new Page(w, Integer.parseInt(p[0]), Integer.parseInt(p[1]), flags, Double.parseDouble(p[3]));
        page.plan();
        page.write();
        long t1 = System.nanoTime(), different = -1;
        if ((flags & VERIFY) != 0) {
            long[] back = new Read(page.meta.bytes(), page.body.bytes()).words();
            different = back.length == w.length ? 0 : w.length;
            for (int i = 0; i < w.length && back.length == w.length; i++) if (back[i] != w[i]) different++;
        }
        long t2 = System.nanoTime();
        byte[] meta = page.meta.bytes(), body = page.body.bytes();
        java.nio.ByteBuffer out = java.nio.ByteBuffer.allocate(88 + meta.length + body.length);
        out.putLong(t1 - t0).putLong(t2 - t1).putLong(different);
        for (int i = 0; i < 7; i++) out.putLong(page.parts[i]);
        out.putLong(meta.length).put(meta).put(body);
        return out.array();
    }

    static int len(long v) { return 64 - Long.numberOfLeadingZeros(v); }
    static long zigzag(long r) { return (r << 1) ^ (r >> 63); }
    static long unzigzag(long z) { return (z >>> 1) ^ -(z & 1); }
    static int sevens(long v) { return (len(v) + 6) / 7; }
    static int extra(int a) { return 2 * len(a) - 1 + a; }
    static long low(long v, int w) { return w >= 64 ? v : v & ((1L << w) - 1); }

    static long gcd(long a, long b) {
        while (b != 0) {
            long t = a >= 0 && b > 0 ? a % b : Long.remainderUnsigned(a, b);
            a = b;
            b = t;
        }
        return a;
    }

    /** Bits, most significant first. */
    static class Out {
        byte[] to = new byte[256];
        long bits = 0;

        void put(long v, long width) {
            int need = (int) ((bits + width + 7) >> 3);
            if (need > to.length) to = java.util.Arrays.copyOf(to, Math.max(need, 2 * to.length));
            while (width > 64) {
                bits += Math.min(width - 64, 64);
                width -= Math.min(width - 64, 64);
            }
            int w = (int) width;
            while (w > 0) {
                int room = 8 - (int) (bits & 7), take = Math.min(w, room);
                long part = (v >>> (w - take)) & ((1 << take) - 1);
                to[(int) (bits >> 3)] |= (byte) (part << (room - take));
                bits += take;
                w -= take;
            }
        }

        void gamma(long v) { put(0, len(v) - 1); put(v, len(v)); }
        void varint(long v) {
            while ((v & ~0x7FL) != 0) { put(v & 0x7F | 0x80, 8); v >>>= 7; }
            put(v, 8);
        }
        int length() { return (int) ((bits + 7) >> 3); }
        byte[] bytes() { return java.util.Arrays.copyOf(to, length()); }
        void append(byte[] b) { for (int i = 0; i < b.length; i++) put(b[i] & 0xFF, 8); }
    }

    /** Lengths of the residuals of a block, and its cheapest codes by form. */
    static class Shape {
        int[] count = new int[65], seen = new int[66];
        int n, longest, param;

        void of(long[] z, int m) {
            java.util.Arrays.fill(count, 0);
            longest = 0;
            for (int i = 0; i < m; i++) {
                int l = len(z[i]);
                count[l]++;
                if (l > longest) longest = l;
            }
            n = 1;
            seen[0] = 0;
            for (int l = 1; l <= longest; l++) if (count[l] > 0) seen[n++] = l;
        }

        long patch(int m, long[] width) {
            long best = NONE;
            for (int a = 0; a < n; a++) {
                int w = seen[a];
                long c = (long) m * (w + (a + 1 < n ? 1 : 0)) + width[w] + 1;
                for (int b = a + 1; b < n; b++) c += (long) count[seen[b]] * extra(seen[b] - w);
                if (c < best) { best = c; param = w; }
            }
            return best;
        }

        long split(int m, long[] width) {
            long best = NONE;
            int above = m;
            for (int w = 0; w < longest; w++) {
                above -= count[w];
                long c = (long) m * (w + 1) + 7 + (long) above * (longest - w) + width[w];
                if (c < best) { best = c; param = w; }
            }
            return best;
        }

        /** Parameters that cannot cost less than ``under`` are passed over. */
        long rice(long[] z, int m, long under) {
            long best = NONE;
            int last = Math.min(longest, 20);
            for (int k = Math.max(longest - 31, 0); k <= last; k++) {
                long c = (long) m * (1 + k) + 5;
                if (c >= under || c >= best) break;
                if (longest > 0 && 1L << (longest - 1) >>> k >= under) continue;
                for (int i = 0; i < m; i++) c += z[i] >>> k;
                if (c < best) { best = c; param = k; }
            }
            return best;
        }
    }

    /** The choices of the blocks of a lane. */
    static class Blocks {
        int k;
        int[] size, p, form, param;
        long[] d;
        long[][] z;

        Blocks(int n, int block) {
            k = (n - 1 + block - 1) / block;
            size = new int[k]; p = new int[k]; form = new int[k]; param = new int[k]; d = new long[k]; z = new long[k][];
        }
    }

    static class Candidate {
        int s;
        long d, r;
        boolean[] ok;
        long[] u;
        int bits, fits;

        boolean before(Candidate o) { return s != o.s ? s < o.s : d != o.d ? d < o.d : r < o.r; }
    }

    /** Huffman code lengths by symbol, 0 for none: as ``bits.code_lengths``. */
    static int[] codeLengths(int[] counts) {
        int n = 0;
        for (int s = 0; s < 65; s++) if (counts[s] > 0) n++;
        int[] out = new int[65];
        if (n == 0) return out;
        long[] weight = new long[2 * n];
        int[] least = new int[2 * n], parent = new int[2 * n], depth = new int[2 * n], symbol = new int[n];
        boolean[] gone = new boolean[2 * n];
        int i = 0;
        for (int s = 0; s < 65; s++) if (counts[s] > 0) { symbol[i] = s; weight[i] = counts[s]; least[i] = s; i++; }
        if (n == 1) { out[symbol[0]] = 1; return out; }
        for (int node = n; node < 2 * n - 1; node++) {
            int[] two = new int[2];
            for (int t = 0; t < 2; t++) {
                int b = -1;
                for (int j = 0; j < node; j++)
                    if (!gone[j] && (b < 0 || weight[j] < weight[b] || weight[j] == weight[b] && least[j] < least[b])) b = j;
                gone[b] = true;
                parent[b] = node;
                two[t] = b;
            }
            weight[node] = weight[two[0]] + weight[two[1]];
            least[node] = Math.min(least[two[0]], least[two[1]]);
        }
        for (int j = 2 * n - 3; j >= 0; j--) depth[j] = depth[parent[j]] + 1;
        for (int j = 0; j < n; j++) out[symbol[j]] = depth[j];
        return out;
    }

    /** Canonical codes in order of (length, symbol). */
    static long[] canonical(int[] lengths) {
        long[] out = new long[lengths.length];
        long code = 0;
        int last = 0;
        for (int n = 1; n <= 64; n++)
            for (int s = 0; s < lengths.length; s++)
                if (lengths[s] == n) { code <<= n - last; out[s] = code++; last = n; }
        return out;
    }

    static class Window {
        int lead = 65, tail = 65, fresh = 0;
        long some = 0, bits = 0;

        boolean next(long x) {
            int c = Long.numberOfLeadingZeros(x), d = Long.numberOfTrailingZeros(x);
            boolean set = c < lead || d < tail;
            if (set) { lead = c; tail = d; fresh++; }
            some++;
            bits += 64 - lead - tail;
            return set;
        }
    }

    static long rawBits(long[] w, int n) {
        if (n == 0) return 0;
        Window g = new Window();
        for (int i = 1; i < n; i++) if (w[i] != w[i - 1]) g.next(w[i] ^ w[i - 1]);
        return 64 + n - 1 + g.some + 12L * g.fresh + g.bits;
    }

    static class Page {
        long[] words, width = new long[65];
        int n, block, most, flags;
        double alpha;
        java.util.ArrayList all = new java.util.ArrayList();
        Candidate[] lanes = new Candidate[0];
        long bits;
        int[] sizes = new int[5];
        long[] costs = new long[5];
        long[][] lane;
        int[][] at;
        long[] raw, r, z, zd, choice;
        int raws;
        Shape shape = new Shape();
        Out meta = new Out(), body = new Out();
        long[] parts = new long[7];

        Page(long[] words, int block, int most, int flags, double alpha) {
            this.words = words; n = words.length; this.block = block; this.most = most; this.flags = flags; this.alpha = alpha;
            lane = new long[4][n]; at = new int[4][n]; raw = new long[n];
            r = new long[block]; z = new long[block]; zd = new long[block]; choice = new long[block];
            java.util.Arrays.fill(width, 7);
        }

        boolean on(int flag) { return (flags & flag) != 0; }

        // ------------------------------------------------ candidates
        void candidates() {
            java.util.ArrayList affine = new java.util.ArrayList();
            double p = 1;
            for (int s = 0; s < 19; s++, p = p * 10) {
                Candidate c = new Candidate();
                c.s = s; c.d = 1; c.ok = new boolean[n]; c.u = new long[n]; c.bits = 5 + (on(AFFINE) ? 16 : 0);
                for (int i = 0; i < n; i++) {
                    double x = Double.longBitsToDouble(words[i]), y = Math.rint(x * p);
                    if (!(y >= -0x1p63 && y < 0x1p63)) continue;
                    long q = (long) y;
                    if (Double.doubleToRawLongBits((double) q / p) == words[i]) { c.ok[i] = true; c.u[i] = q; c.fits++; }
                }
                boolean dominated = c.fits == 0;
                for (int j = 0; j < all.size() && !dominated; j++) {
                    boolean[] m = ((Candidate) all.get(j)).ok;
                    int i = 0;
                    while (i < n && (!c.ok[i] || m[i])) i++;
                    dominated = i == n;
                }
                if (dominated) continue;
                all.add(c);
                if (on(AFFINE)) affine(c, affine);
            }
            all.addAll(affine);
        }

        void affine(Candidate c, java.util.ArrayList out) {
            long[] q = new long[c.fits];
            int k = 0;
            for (int i = 0; i < n; i++) if (c.ok[i]) q[k++] = c.u[i];
            if (k < 3) return;
            int span = k - 1 >= 16 ? 16 : k - 1, windows = (k - 1) / span;
            long[] g = new long[windows];
            for (int b = 0; b < windows; b++)
                for (int i = b * span; i < (b + 1) * span; i++) g[b] = gcd(Math.abs(q[i + 1] - q[i]), g[b]);
            java.util.Arrays.sort(g);
            long[] ds = new long[windows], ns = new long[windows];
            int distinct = 0;
            for (int b = 0; b < windows; ) {
                int e = b;
                while (e < windows && g[e] == g[b]) e++;
                if (g[b] >= 2 && g[b] <= 100000000L) { ds[distinct] = g[b]; ns[distinct++] = e - b; }
                b = e;
            }
            int slots = Integer.highestOneBit(Math.max(k, 8)) * 4;
            long[] key = new long[slots];
            for (int pick = 0; pick < Math.min(8, distinct); pick++) {
                int b = -1;
                for (int j = 0; j < distinct; j++) if (ns[j] > 0 && (b < 0 || ns[j] > ns[b])) b = j;
                ns[b] = 0;
                long d = ds[b], r = 0;
                int[] count = new int[slots];
                int full = 0;
                for (int i = 0; i < k; i++) {
                    long m = Math.floorMod(q[i], d);
                    int h = (int) ((m * 0x9E3779B97F4A7C15L) >>> 40) & (slots - 1);
                    while (count[h] > 0 && key[h] != m) h = (h + 1) & (slots - 1);
                    key[h] = m;
                    count[h]++;
                    if (count[h] > full || count[h] == full && m < r) { full = count[h]; r = m; }
                }
                Candidate a = new Candidate();
                a.s = c.s; a.d = d; a.r = r; a.ok = new boolean[n]; a.u = new long[n];
                a.bits = 5 + 8 * (sevens(d) + Math.max(1, sevens(r)));
                for (int i = 0; i < n; i++)
                    if (c.ok[i] && Math.floorMod(c.u[i], d) == r) { a.ok[i] = true; a.u[i] = Math.floorDiv(c.u[i] - r, d); a.fits++; }
                out.add(a);
            }
        }

        // ------------------------------------------------ costs
        /** Bits of a lane of m > 1 coordinates; stops where they reach ``under``. The choices go to ``out``. */
        long upper(long[] u, int m, long under, Blocks out) {
            long total = 0;
            for (int a = 1, b = 0; a < m && total < under; a += block, b++) {
                int size = Math.min(block, m - a);
                long best = NONE;
                for (int p = 0; p < (on(PREDICTORS) ? 5 : 1); p++) {
                    long g = 0;
                    for (int j = 0; j < size; j++) {
                        int i = a + j;
                        r[j] = u[i] - predict(u, i, p);
                        z[j] = zigzag(r[j]);
                    }
                    if (on(GCD)) for (int j = 0; j < size && g != 1; j++) g = r[j] == Long.MIN_VALUE ? 1 : gcd(Math.abs(r[j]), g);
                    for (int which = 0; which < (g > 1 ? 2 : 1); which++) {
                        long[] y = which == 0 ? z : zd;
                        long more = 6;
                        if (which == 1) {
                            for (int j = 0; j < size; j++) zd[j] = zigzag(r[j] / g);
                            more += 2 * len(g) - 1;
                        }
                        shape.of(y, size);
                        for (int form = 0; form < 3; form++) {
                            if (form == 1 && !on(SPLIT) || form == 2 && !on(RICE)) continue;
                            long c = form == 0 ? shape.patch(size, width) : form == 1 ? shape.split(size, width) : shape.rice(y, size, best - more);
                            if (c >= NONE || c + more >= best) continue;
                            best = c + more;
                            if (out != null) {
                                out.size[b] = size; out.p[b] = p; out.form[b] = form; out.param[b] = shape.param; out.d[b] = which == 1 ? g : 1;
                                out.z[b] = java.util.Arrays.copyOf(y, size);
                            }
                        }
                    }
                }
                total += best;
            }
            return total;
        }

        long fast(long[] u, int[] where, int m, long under, Blocks out) {
            long total = 0;
            for (int a = 1, b = 0; a < m && total < under; a += block, b++) {
                int size = Math.min(block, m - a);
                for (int i = a; i < a + size; i++) z[i - a] = zigzag(u[i] - (!on(PREDICT) || !on(PERSIST) && where[i] - where[i - 1] != 1 ? u[0] : u[i - 1]));
                shape.of(z, size);
                total += shape.patch(size, width);
                if (out != null) { out.size[b] = size; out.param[b] = shape.param; out.d[b] = 1; out.z[b] = java.util.Arrays.copyOf(z, size); }
            }
            return total;
        }

        long blocks(int l, int m, long under, Blocks out) { return on(UPPER) ? upper(lane[l], m, under, out) : fast(lane[l], at[l], m, under, out); }

        /** Routes the values to the first lane in order that admits them; sizes by lane. */
        void assign(Candidate[] c, int k) {
            for (int l = 0; l < k; l++) sizes[l] = 0;
            raws = 0;
            for (int i = 0; i < n; i++) {
                int l = 0;
                while (l < k && !c[l].ok[i]) l++;
                if (l == k) { raw[raws++] = words[i]; continue; }
                lane[l][sizes[l]] = c[l].u[i];
                at[l][sizes[l]++] = i;
            }
        }

        /** Cost of ``k`` lanes in order; the ones of known size have known cost. Stops where it reaches ``under``. */
        long cost(Candidate[] c, int k, long under, int[] knownSize, long[] knownCost) {
            assign(c, k);
            int largest = 0;
            for (int l = 0; l < k; l++) largest = Math.max(largest, sizes[l]);
            long got = k == 0 || k == 1 && raws == 0 ? 0 : n + (long) (n - largest) * len(k - 1);
            for (int l = 0; l < k; l++) {
                costs[l] = knownSize != null && knownSize[l] == sizes[l] ? knownCost[l] : -1;
                got += costs[l] >= 0 ? costs[l] : c[l].bits + 16;
            }
            if (got >= under) return got;
            got += rawBits(raw, raws);
            for (int l = 0; l < k && got < under; l++) {
                if (costs[l] >= 0) continue;
                got -= c[l].bits + 16;
                costs[l] = c[l].bits + 16;
                if (sizes[l] > 0) costs[l] += 8 * Math.max(1, sevens(zigzag(lane[l][0])));
                if (sizes[l] > 1) costs[l] += blocks(l, sizes[l], under - got - costs[l], null);
                got += costs[l];
            }
            return got;
        }

        void greedy() {
            Candidate[] trial = new Candidate[5];
            int[] have = new int[5], known = new int[5], won = null;
            long[] paid = new long[5], spent = null;
            long best = NONE;
            int first = -1;
            Candidate[] by = (Candidate[]) all.toArray(new Candidate[0]);
            for (int done = 0; done < by.length; done++) {
                int k = -1;
                for (int j = 0; j < by.length; j++) if (by[j] != null && (k < 0 || by[j].fits > by[k].fits)) k = j;
                trial[0] = by[k];
                by[k] = null;
                long c = cost(trial, 1, best == NONE ? best : best + 1, null, null);
                if (c < best || c == best && k < first) { best = c; first = k; have[0] = sizes[0]; paid[0] = costs[0]; }
            }
            long none = rawBits(words, n);
            lanes = new Candidate[0];
            bits = none;
            if (first < 0 || none <= best) return;
            lanes = new Candidate[] {(Candidate) all.get(first)};
            while (lanes.length < most) {
                long step = best, step0 = best;
                int k = lanes.length;
                Candidate[] next = null;
                long[] knownCost = new long[5];
                int[] knownSize = new int[5];
                for (int j = 0; j < all.size(); j++) {
                    Candidate c = (Candidate) all.get(j);
                    int place = 0;
                    while (place < k && lanes[place].before(c)) place++;
                    if (place < k && lanes[place] == c) continue;
                    for (int l = 0; l <= k; l++) {
                        trial[l] = l < place ? lanes[l] : l == place ? c : lanes[l - 1];
                        knownSize[l] = l == place ? -1 : have[l < place ? l : l - 1];
                        knownCost[l] = l == place ? 0 : paid[l < place ? l : l - 1];
                    }
                    long got = cost(trial, k + 1, step, knownSize, knownCost);
                    if (got >= step || !(got * (1 + alpha) < step)) continue;
                    boolean full = true;
                    for (int l = 0; l <= k; l++) full &= sizes[l] > 0;
                    if (!full) continue;
                    step = got;
                    next = (Candidate[]) java.util.Arrays.copyOf(trial, k + 1);
                    won = (int[]) sizes.clone();
                    spent = (long[]) costs.clone();
                }
                if (next == null) break;
                lanes = next;
                have = won;
                paid = spent;
                best = step;
            }
            bits = best;
        }

        int[] widths(Blocks[] got) {
            int[] counts = new int[65];
            for (int l = 0; l < got.length; l++)
                for (int b = 0; got[l] != null && b < got[l].k; b++) if (got[l].form[b] != 2) counts[got[l].param[b]]++;
            return counts;
        }

        Blocks[] choose() {
            Blocks[] got = new Blocks[lanes.length];
            for (int l = 0; l < lanes.length; l++)
                if (sizes[l] > 1) { got[l] = new Blocks(sizes[l], block); blocks(l, sizes[l], NONE, got[l]); }
            return got;
        }

        void plan() {
            candidates();
            greedy();
            if (lanes.length == 0 || !on(LEARN)) return;
            assign(lanes, lanes.length);
            int[] lengths = codeLengths(widths(choose()));
            int top = 0;
            for (int s = 0; s < 65; s++) top = Math.max(top, lengths[s]);
            for (int s = 0; s < 65; s++) width[s] = lengths[s] > 0 ? lengths[s] : Math.max(top, 1) + 3;
            Candidate[] was = lanes;
            long old = cost(was, was.length, Long.MAX_VALUE, null, null);
            greedy();
            if (bits > old) { lanes = was; bits = old; }
        }

        // ------------------------------------------------ writing
        void write() {
            int k = lanes.length, first = 0;
            assign(lanes, k);
            for (int l = 1; l < k; l++) if (sizes[l] > sizes[first]) first = l;
            boolean whole = k == 1 && raws == 0;
            java.util.Arrays.fill(width, 7);
            Blocks[] got = choose();
            int[] lengths = codeLengths(widths(got));
            int top = 0;
            for (int s = 0; s < 65; s++) top = Math.max(top, lengths[s]);
            if (top > 0 && on(LEARN)) {
                for (int s = 0; s < 65; s++) width[s] = lengths[s] > 0 ? lengths[s] : 1 << 20;
                width[0] = Math.min(width[0], top + 3);
                got = choose();
                lengths = codeLengths(widths(got));
            }
            long[] codes = canonical(lengths);
            Out[] heads = new Out[k];
            for (int l = 0; l < k; l++) {
                heads[l] = new Out();
                if (got[l] == null) continue;
                if (on(UPPER)) writeUpper(got[l], codes, lengths, heads[l]);
                else writeFast(got[l], codes, lengths, heads[l]);
            }
            long before = body.bits;
            if (raws > 0) {
                Window g = new Window();
                body.put(raw[0], 64);
                for (int i = 1; i < raws; i++) {
                    long x = raw[i] ^ raw[i - 1];
                    if (x == 0) { body.put(0, 1); continue; }
                    boolean set = g.next(x);
                    int m = 64 - g.lead - g.tail;
                    body.put(set ? 3 : 2, 2);
                    if (set) { body.put(g.lead, 6); body.put(m - 1, 6); }
                    body.put(x >>> g.tail, m);
                }
            }
            parts[6] = body.bits - before;
            meta.put('L', 8); meta.put('X', 8); meta.put(1, 8);
            meta.put((on(UPPER) ? 1 : 0) | (on(PERSIST) ? 0 : 2) | (on(PREDICT) ? 0 : 4) | (whole ? 16 : 0), 8);
            meta.varint(n);
            meta.varint(block);
            meta.put(k | first << 3, 8);
            int mark = meta.length();
            for (int l = 0; l < k; l++) {
                meta.put(lanes[l].s, 8);
                if (on(UPPER)) { meta.varint(lanes[l].d); meta.varint(lanes[l].r); }
            }
            Out route = new Out();
            if (k > 0 && !whole) {
                int[] of = new int[n];
                java.util.Arrays.fill(of, k);
                for (int l = 0; l < k; l++) for (int i = 0; i < sizes[l]; i++) of[at[l][i]] = l;
                for (int i = 0; i < n; i++) route.put(of[i] == first ? 1 : 0, 1);
                for (int i = 0; i < n; i++) if (of[i] != first) route.put(of[i] > first ? of[i] - 1 : of[i], len(k - 1));
            }
            meta.varint(route.length());
            meta.append(route.bytes());
            parts[1] = 8L * (meta.length() - mark);
            mark = meta.length();
            int symbols = 0;
            for (int s = 0; s < 65; s++) if (lengths[s] > 0) symbols++;
            meta.varint(symbols);
            for (int s = 0; s < 65; s++) if (lengths[s] > 0) { meta.put(s, 8); meta.put(lengths[s], 8); }
            for (int l = 0; l < k; l++) {
                meta.varint(zigzag(lane[l][0]));
                meta.varint(heads[l].length());
                meta.append(heads[l].bytes());
            }
            parts[2] = 8L * (meta.length() - mark);
            meta.varint(body.length());
            Out size = new Out();
            size.varint(meta.length());
            parts[0] = 8L * (meta.length() + body.length() + size.length());
            for (int i = 1; i < 7; i++) parts[0] -= parts[i];
        }

        void writeFast(Blocks g, long[] codes, int[] lengths, Out head) {
            long start = body.bits, ext = 0;
            for (int b = 0; b < g.k; b++) for (int i = 0; i < g.size[b]; i++) body.put(low(g.z[b][i], g.param[b]), g.param[b]);
            long base = body.bits - start;
            boolean[] wide = new boolean[g.k];
            for (int b = 0; b < g.k; b++) {
                for (int i = 0; i < g.size[b]; i++) wide[b] |= len(g.z[b][i]) > g.param[b];
                head.put(codes[g.param[b]], lengths[g.param[b]]);
                head.put(wide[b] ? 1 : 0, 1);
                for (int i = 0; wide[b] && i < g.size[b]; i++) body.put(len(g.z[b][i]) > g.param[b] ? 1 : 0, 1);
            }
            for (int b = 0; b < g.k; b++)
                for (int i = 0; wide[b] && i < g.size[b]; i++) { int e = len(g.z[b][i]) - g.param[b]; if (e > 0) body.gamma(e); }
            for (int b = 0; b < g.k; b++)
                for (int i = 0; wide[b] && i < g.size[b]; i++) { int e = len(g.z[b][i]) - g.param[b]; if (e > 0) { body.put(g.z[b][i] >>> g.param[b], e); ext += e; } }
            parts[4] += base;
            parts[5] += ext;
            parts[3] += body.bits - start - base - ext;
        }

        void writeUpper(Blocks g, long[] codes, int[] lengths, Out head) {
            long start = body.bits;
            for (int b = 0; b < g.k; b++) {
                long[] y = g.z[b];
                int w = g.param[b], longest = 0;
                for (int i = 0; i < y.length; i++) longest = Math.max(longest, len(y[i]));
                head.put(g.p[b], 3); head.put(g.form[b], 2); head.put(g.d[b] > 1 ? 1 : 0, 1);
                if (g.d[b] > 1) head.gamma(g.d[b]);
                if (g.form[b] == 2) {
                    head.put(w, 5);
                    for (int i = 0; i < y.length; i++) { body.put(0, y[i] >>> w); body.put(1, 1); body.put(low(y[i], w), w); }
                    continue;
                }
                head.put(codes[w], lengths[w]);
                if (g.form[b] == 0) head.put(longest > w ? 1 : 0, 1);
                else body.put(longest - w, 7);
                for (int i = 0; i < y.length; i++) body.put(low(y[i], w), w);
                if (longest <= w) continue;
                for (int i = 0; i < y.length; i++) body.put(len(y[i]) > w ? 1 : 0, 1);
                if (g.form[b] == 0) for (int i = 0; i < y.length; i++) if (len(y[i]) > w) body.gamma(len(y[i]) - w);
                for (int i = 0; i < y.length; i++) if (len(y[i]) > w) body.put(y[i] >>> w, g.form[b] == 0 ? len(y[i]) - w : longest - w);
            }
            parts[4] += body.bits - start;
        }
    }

    static long predict(long[] u, int i, int p) {
        long u1 = u[i - 1];
        if (p == 0 || i < 2) return u1;
        long u2 = u[i - 2];
        if (p == 1) return 2 * u1 - u2;
        if (p == 2) return i < 3 ? u1 : 3 * u1 - 3 * u2 + u[i - 3];
        return (p == 3 ? u1 : u2) + ((u1 - u2) >> 1);
    }

    static class In {
        byte[] b;
        long at = 0;

        In(byte[] b) { this.b = b; }

        long get(int w) {
            long v = 0;
            while (w > 0) {
                int room = 8 - (int) (at & 7), take = Math.min(room, w);
                v = v << take | ((b[(int) (at >> 3)] & 0xFF) >>> (room - take)) & ((1 << take) - 1);
                at += take;
                w -= take;
            }
            return v;
        }
        long unary() { long n = 0; while (get(1) == 0) n++; return n; }
        long gamma() { int n = (int) unary(); return 1L << n | get(n); }
        long varint() {
            long v = 0;
            for (int shift = 0; ; shift += 7) { long c = get(8); v |= (c & 0x7F) << shift; if (c < 0x80) return v; }
        }
    }

    /** Reads a frame from its bytes alone, to verify them; ``functions.frame`` has the strict reader. */
    static class Read {
        In meta, body;

        Read(byte[] meta, byte[] body) { this.meta = new In(meta); this.body = new In(body); }

        long[] words() {
            meta.at = 24;
            int flags = (int) meta.get(8), n = (int) meta.varint(), block = (int) meta.varint(), kf = (int) meta.get(8), k = kf & 7, first = kf >> 3;
            int[] s = new int[k];
            long[] d = new long[k], r = new long[k], out = new long[n];
            for (int l = 0; l < k; l++) {
                s[l] = (int) meta.get(8);
                d[l] = 1;
                if ((flags & 1) != 0) { d[l] = meta.varint(); r[l] = meta.varint(); }
            }
            long end = meta.varint() * 8;
            end += meta.at;
            int[] of = new int[n];
            if ((flags & 16) == 0) {
                if (k == 0) java.util.Arrays.fill(of, 0);
                else {
                    for (int i = 0; i < n; i++) of[i] = meta.get(1) == 1 ? first : -1;
                    for (int i = 0; i < n; i++) if (of[i] < 0) { int x = (int) meta.get(len(k - 1)); of[i] = x >= first ? x + 1 : x; }
                }
            }
            meta.at = end;
            int[] lengths = new int[65];
            for (int c = (int) meta.varint(); c > 0; c--) { int w = (int) meta.get(8); lengths[w] = (int) meta.get(8); }
            long[] codes = canonical(lengths);
            double[] powers = new double[19];
            for (int i = 0; i < 19; i++) powers[i] = i == 0 ? 1 : powers[i - 1] * 10;
            for (int l = 0; l < k; l++) {
                int m = 0;
                for (int i = 0; i < n; i++) if (of[i] == l) m++;
                int[] at = new int[m];
                m = 0;
                for (int i = 0; i < n; i++) if (of[i] == l) at[m++] = i;
                long anchor = unzigzag(meta.varint());
                end = meta.varint() * 8;
                end += meta.at;
                long[] u = (flags & 1) != 0 ? upper(m, anchor, block, codes, lengths) : fast(m, anchor, at, block, flags, codes, lengths);
                meta.at = end;
                for (int i = 0; i < m; i++) out[at[i]] = Double.doubleToRawLongBits((double) (u[i] * d[l] + r[l]) / powers[s[l]]);
            }
            long last = 0;
            int lead = 0, size = 0;
            boolean some = false;
            for (int i = 0; i < n; i++) {
                if (of[i] != k) continue;
                if (!some) { last = body.get(64); some = true; }
                else if (body.get(1) == 1) {
                    if (body.get(1) == 1) { lead = (int) body.get(6); size = (int) body.get(6) + 1; }
                    last ^= body.get(size) << (64 - lead - size);
                }
                out[i] = last;
            }
            return out;
        }

        int symbol(long[] codes, int[] lengths) {
            long code = 0;
            for (int n = 1; n <= 64; n++) {
                code = code << 1 | meta.get(1);
                for (int s = 0; s < 65; s++) if (lengths[s] == n && codes[s] == code) return s;
            }
            throw new IllegalStateException("illegal width symbol");
        }

        long[] fast(int m, long anchor, int[] at, int block, int flags, long[] codes, int[] lengths) {
            int k = (m - 1 + block - 1) / block;
            int[] w = new int[k], more = new int[m];
            boolean[] wide = new boolean[k];
            for (int b = 0; b < k; b++) { w[b] = symbol(codes, lengths); wide[b] = meta.get(1) == 1; }
            long[] u = new long[m];
            for (int i = 1; i < m; i++) u[i] = body.get(w[(i - 1) / block]);
            for (int i = 1; i < m; i++) if (wide[(i - 1) / block]) more[i] = (int) body.get(1);
            for (int i = 1; i < m; i++) if (more[i] > 0) more[i] = (int) body.gamma();
            for (int i = 1; i < m; i++) if (more[i] > 0) u[i] |= body.get(more[i]) << w[(i - 1) / block];
            u[0] = anchor;
            for (int i = 1; i < m; i++) u[i] = unzigzag(u[i]) + ((flags & 4) != 0 || (flags & 2) != 0 && at[i] - at[i - 1] != 1 ? anchor : u[i - 1]);
            return u;
        }

        long[] upper(int m, long anchor, int block, long[] codes, int[] lengths) {
            long[] u = new long[m];
            u[0] = anchor;
            for (int a = 1; a < m; a += block) {
                int size = Math.min(block, m - a), p = (int) meta.get(3), form = (int) meta.get(2);
                long d = meta.get(1) == 1 ? meta.gamma() : 1;
                int w = form == 2 ? (int) meta.get(5) : symbol(codes, lengths);
                boolean flag = form == 1 || form == 0 && meta.get(1) == 1;
                long[] z = new long[size];
                if (form == 2) for (int i = 0; i < size; i++) { long high = body.unary(); z[i] = high << w | body.get(w); }
                else {
                    int high = form == 1 ? (int) body.get(7) : 0;
                    int[] more = new int[size];
                    for (int i = 0; i < size; i++) z[i] = body.get(w);
                    for (int i = 0; flag && i < size; i++) more[i] = body.get(1) == 1 ? high + 1 : 0;
                    for (int i = 0; i < size; i++) if (more[i] > 0) more[i] = form == 0 ? (int) body.gamma() : high;
                    for (int i = 0; i < size; i++) if (more[i] > 0) z[i] |= body.get(more[i]) << w;
                }
                for (int i = 0; i < size; i++) u[a + i] = predict(u, a + i, p) + unzigzag(z[i]) * d;
            }
            return u;
        }
    }
}
"""
