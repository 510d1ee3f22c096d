"""Learned linear codecs: PCA, reconstruction, contrastive, neighbour-preserving contrastive (NPCC), OPQ and mixtures.

Encoders are linear with a constant. Training runs in rounds: each task takes Adam steps over its rows from the
broadcast weights in single precision, and the weights are averaged
by rows trained on. All parameters are in `manifest`.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F
from pyspark.sql.types import ArrayType, DoubleType, StructType

from nearcopy.functions.blocks import hash_sample, hash_share, matrix, sum_rows, vectors
from nearcopy.functions.losses import contrastive


@dataclass
class Codec:
    """x -> (x - mean) @ image + image_bias; the text side likewise; z -> z @ back + back_bias."""

    kind: str
    image: np.ndarray | None = None
    image_bias: np.ndarray | None = None
    text: np.ndarray | None = None
    text_bias: np.ndarray | None = None
    back: np.ndarray | None = None
    back_bias: np.ndarray | None = None
    manifest: dict = field(default_factory=dict)

    def encode_block(self, x: np.ndarray, side: str = "image") -> np.ndarray:
        w, b = (
            self.text, self.text_bias
        ) if side == "text" and self.text is not None else (self.image, self.image_bias)
        if w is None:
            return x
        if len(w) == 2 * x.shape[1]:  # a fused encoder: the other half is empty
            x = np.hstack([x, np.zeros_like(x)] if side == "image" else [np.zeros_like(x), x])
        return x @ w + b

    def decode_block(self, z: np.ndarray) -> np.ndarray:
        if self.image is None:
            return z
        if self.back is None:
            raise ValueError(f"codec {self.kind} has no decoder")
        return z @ self.back + self.back_bias

    def _apply(self, df, col, out, f):
        shared = df.sparkSession.sparkContext.broadcast(self)
        df = df.drop(out)
        place, names = df.columns.index(col), [*df.columns, out]

        def run(batches):
            for b in batches:
                x = matrix(b.column(place))
                yield pa.RecordBatch.from_arrays(
                    [*b.columns, vectors(f(shared.value, x) if len(x) else x)], names=names
                )

        return df.mapInArrow(run, StructType([*df.schema.fields]).add(out, ArrayType(DoubleType())))

    def encode(
        self, df: DataFrame, col: str = "x", out: str = "z", side: str = "image", engine: str = "arrow"
    ) -> DataFrame:
        """engine: arrow (NumPy blocks) or expr (a Catalyst expression; for small encoders)."""
        if engine == "expr":
            w, b = (
                self.text, self.text_bias
            ) if side == "text" and self.text is not None else (self.image, self.image_bias)
            x = F.col(col).cast("array<double>")
            if w is None:
                return df.withColumn(out, x)
            rows = F.array(*[F.struct(F.array(*[F.lit(float(v)) for v in w[:, j]]).alias("w"), F.lit(float(b[j])).alias("b")) for j in range(w.shape[1])])
            return df.withColumn(
                out,
                F.transform(
                    rows,
                    lambda r: F.aggregate(
                        F.zip_with(x, r["w"], lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v
                    ) + r["b"],
                ),
            )
        return self._apply(df, col, out, lambda c, x: c.encode_block(x, side))

    def decode(self, df: DataFrame, col: str = "z", out: str = "x_hat") -> DataFrame:
        return self._apply(df, col, out, lambda c, z: c.decode_block(z))

    def size_bytes(self) -> int:
        return sum(v.size * 4 for v in (self.image, self.image_bias, self.text, self.text_bias, self.back, self.back_bias) if v is not None)


class IdentityCodec(Codec):
    def __init__(self):
        super().__init__("identity")


def moments(df: DataFrame, col: str, dim: int) -> tuple[int, np.ndarray, np.ndarray]:
    """Rows, mean and covariance, by one pass; a task sends dim + 1 rows."""

    def partial(batches):
        g, n = np.zeros((dim + 1, dim)), 0
        for b in batches:
            x = matrix(b.column(0))
            if len(x):
                g[:dim] += x.T @ x
                g[dim] += x.sum(axis=0)
                n += len(x)
        return np.arange(dim + 1), np.full(dim + 1, n), g

    found = sum_rows(df.select(col), partial, dim + 1)
    n = found[dim][0] if found else 0
    g = np.array([found[i][1] for i in range(dim + 1)]) if found else np.zeros((dim + 1, dim))
    mean = g[dim] / max(n, 1)
    return n, mean, g[:dim] / max(n, 1) - np.outer(mean, mean)


def width(df: DataFrame, col: str) -> int:
    row = df.select(F.size(col)).where(F.col(col).isNotNull()).first()
    if row is None:
        raise ValueError("there are no vectors")
    return row[0]


def fit_pca_codec(df: DataFrame, col: str = "x", latent_dim: int = 128) -> Codec:
    dim = width(df, col)
    latent_dim = min(latent_dim, dim)
    n, mean, cov = moments(df, col, dim)
    values, basis = np.linalg.eigh((cov + cov.T) / 2)
    basis = basis[:, ::-1][:, :latent_dim]
    sign = np.sign(basis[np.abs(basis).argmax(axis=0), np.arange(latent_dim)])
    basis = basis * np.where(sign == 0, 1, sign)
    return Codec(
        "pca",
        basis,
        -mean @ basis,
        None,
        None,
        basis.T,
        mean,
        {
            "latent_dim": latent_dim,
            "rows": n,
            "variance": float(values[::-1][:latent_dim].sum() / max(values.sum(), 1e-300)),
        },
    )


class _Adam:
    def __init__(self, lr):
        self.lr, self.t, self.m, self.v, self.room = lr, 0, {}, {}, {}

    def step(self, weights: dict[str, np.ndarray], grads: dict[str, np.ndarray]) -> None:
        """In place: new arrays of this size would be mapped and cleared at each step."""
        self.t += 1
        for k, g in grads.items():
            if k not in self.m:
                self.m[k], self.v[k], self.room[k] = np.zeros_like(g), np.zeros_like(g), np.empty((2, *g.shape))
            m, v, (a, b) = self.m[k], self.v[k], self.room[k]
            m *= 0.9
            m += np.multiply(g, 0.1, out=a)
            v *= 0.999
            np.multiply(g, 0.001, out=a)
            a *= g
            v += a
            np.divide(v, 1 - 0.999**self.t, out=b)
            np.sqrt(b, out=b)
            b += 1e-8
            np.divide(m, 1 - 0.9**self.t, out=a)
            a *= self.lr
            a /= b
            weights[k] -= a


def _held(batches, width: int):
    """The matrices of a task's rows, of about HELD_ROWS rows at a time."""
    parts, n = [], 0
    for b in batches:
        if not b.num_rows:
            continue
        parts.append([matrix(b.column(i), np.float32) for i in range(width)])
        n += b.num_rows
        if n >= HELD_ROWS:
            yield [np.concatenate(p) for p in zip(*parts, strict=True)]
            parts, n = [], 0
    if parts:
        yield [np.concatenate(p) for p in zip(*parts, strict=True)]


def train(
    df: DataFrame,
    columns: list[str],
    weights: dict[str, np.ndarray],
    gradients,
    rounds: int,
    epochs: int,
    batch: int,
    lr: float,
    seed: int,
) -> dict[str, np.ndarray]:
    """Rounds of local steps and averaging. gradients(weights, *matrices) -> dict. Rows of a task (of each HELD_ROWS of
    them) are seen in order of a seeded shuffle."""
    shapes = {k: v.shape for k, v in weights.items()}
    names = list(weights)
    for r in range(rounds):
        shared = df.sparkSession.sparkContext.broadcast(weights)

        def partial(batches, shared=shared, r=r):
            total, n = None, 0
            for data in _held(batches, len(columns)):
                w, adam, rng = {k: v.astype(np.float32) for k, v in shared.value.items()}, _Adam(lr), np.random.default_rng((seed, r))
                for _ in range(epochs):
                    order = rng.permutation(len(data[0]))
                    for i in range(0, len(order), batch):
                        rows = order[i : i + batch]
                        if len(rows) > 1 or len(order) == 1:
                            adam.step(w, gradients(w, *[d[rows] for d in data]))
                flat = np.concatenate([w[k].ravel() for k in names])
                size = -(-len(flat) // 4096) * 4096
                chunks = np.zeros(size)
                chunks[: len(flat)] = flat
                chunks *= len(data[0])
                total, n = chunks if total is None else total + chunks, n + len(data[0])
            if total is None:
                return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 1))
            chunks = total.reshape(-1, 4096)
            return np.arange(len(chunks)), np.full(len(chunks), n), chunks

        flat_size = sum(v.size for v in weights.values())
        found = sum_rows(df.select(*columns), partial, -(-flat_size // 4096))
        if not found:
            return weights
        flat = np.concatenate([found[k][1] / found[k][0] for k in sorted(found)])[:flat_size]
        at = 0
        weights = {}
        for k in names:
            n = int(np.prod(shapes[k]))
            weights[k] = flat[at : at + n].reshape(shapes[k])
            at += n
    return weights


def _starting(dim: int, latent: int, seed: int, *names: str) -> dict[str, np.ndarray]:
    """Random orthogonal directions, the same for both sides, so that training starts aligned."""
    q, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    w = q[:, :latent]
    return {n: (w.copy() if n.startswith("w") else w.T.copy() if n.startswith("d") else np.zeros(latent if n.startswith("b") else dim)) for n in names}


#: sample: about how many rows are trained on, by a hash of the id; None: all of them.
_TRAIN = {"rounds": 3, "epochs": 10, "batch": 256, "lr": 0.01, "seed": 0, "sample": None}
#: Rows that a task of a training holds at a time; those of a larger task are trained on in turn, each part as a task.
HELD_ROWS = 1 << 15


def _options(given: dict) -> dict:
    unknown = set(given) - set(_TRAIN)
    if unknown:
        raise TypeError(f"unknown options {sorted(unknown)}")
    return _TRAIN | given


def _run(df, columns, weights, gradients, o, chosen=False):
    """chosen: df has no other rows than those to train on."""
    rows = df.select("id", *columns)
    rows = hash_share(rows, None if chosen else o["sample"], "id")
    return train(rows, columns, weights, gradients, o["rounds"], o["epochs"], o["batch"], o["lr"], o["seed"])


def _mse_gradients(w, x):
    z = x @ w["wx"] + w["bx"]
    e = (z @ w["dx"] + w["cx"] - x) * (2 / len(x))
    dz = e @ w["dx"].T
    return {"dx": z.T @ e, "cx": e.sum(0), "wx": x.T @ dz, "bx": dz.sum(0)}


def fit_mse_codec(df: DataFrame, col: str = "x", latent_dim: int = 128, **options) -> Codec:
    """Least squared reconstruction error; for the text side pass its column."""
    o = _options(options)
    dim = width(df, col)
    latent_dim = min(latent_dim, dim)
    w = _run(df, [col], _starting(dim, latent_dim, o["seed"], "wx", "bx", "dx", "cx"), _mse_gradients, o)
    return Codec("mse", w["wx"], w["bx"], None, None, w["dx"], w["cx"], {"latent_dim": latent_dim, "col": col, **o})


def _linear_grads(x, g, w, b):
    return {w: x.T @ g, b: g.sum(0)}


def fit_contrastive_codec(
    pairs: DataFrame,
    latent_dim: int = 128,
    temperature: float = 0.07,
    image: str = "x",
    text: str = "t",
    space: str = "latent",
    **options,
) -> Codec:
    """space: latent (loss between the encoded sides) or reconstructed (between the decoded ones)."""
    return _fit_pairs(pairs, latent_dim, temperature, image, text, None, 0.0, False, space, 0.0, **options)


def fit_npcc_codec(
    pairs: DataFrame,
    latent_dim: int = 128,
    chunk_size: int = 10_000_000,
    stride: int | None = None,
    lam: float = 1.0,
    temperature: float = 0.07,
    image: str = "x",
    text: str = "t",
    mask_same_vector: bool = False,
    rows: DataFrame | None = None,
    **options,
) -> Codec:
    """Contrastive loss of the pair plus lam times that of an image and its nearest one in the chunk. lam = 0 is
    fit_contrastive_codec. rows: what neighbour_rows gave for the same pairs, chunks and sample, if it is there already."""
    if lam == 0:
        return _fit_pairs(
            pairs, latent_dim, temperature, image, text, None, 0.0, mask_same_vector, "latent", 0.0, **options
        )
    if rows is None:
        rows = neighbour_rows(pairs, chunk_size, stride, image, text, _options(options)["sample"])
    return _fit_pairs(
        rows, latent_dim, temperature, image, text, "x_nn", lam, mask_same_vector, "latent", 0.0, True, **options
    )


def neighbour_rows(
    pairs: DataFrame,
    chunk_size: int = 10_000_000,
    stride: int | None = None,
    image: str = "x",
    text: str = "t",
    sample: int | None = _TRAIN["sample"],
) -> DataFrame:
    """The pairs that are trained on (all with another row in a chunk, or about `sample` of these), each with its nearest
    row in the chunk, which is looked for among all rows; a stored table, as each round of a training reads it."""
    from nearcopy.components import materialize
    from nearcopy.operators.search import chunk_nearest, with_chunks

    asked = None
    if sample is not None:
        chunked = with_chunks(pairs.select("id"), chunk_size, stride)
        shared = chunked.groupBy("chunk_id").count().where("count > 1")
        asked = hash_share(chunked.join(shared, "chunk_id", "left_semi").select("id").distinct(), sample, "id")
    near = materialize(chunk_nearest(pairs.select("id", image), image, chunk_size, stride, asked=asked))
    partner = pairs.select(F.col("id").alias("nn_id"), F.col(image).alias("x_nn"))
    rows = pairs.select("id", image, text).join(near.select("id", "nn_id"), "id").join(partner, "nn_id")
    return materialize(rows.drop("nn_id"))


def fit_hybrid_codec(
    pairs: DataFrame,
    latent_dim: int = 128,
    w_recon: float = 1.0,
    w_contrast: float = 1.0,
    temperature: float = 0.07,
    image: str = "x",
    text: str = "t",
    **options,
) -> Codec:
    """A mixture of contrastive and reconstruction losses."""
    return _fit_pairs(
        pairs,
        latent_dim,
        temperature,
        image,
        text,
        None,
        0.0,
        False,
        "latent",
        w_recon / max(w_contrast, 1e-12),
        **options,
    )


def _fit_pairs(
    pairs, latent_dim, temperature, image, text, near, lam, mask_same, space, recon, chosen=False, **options
):
    o = _options(options)
    dim = width(pairs, image)
    latent_dim = min(latent_dim, dim)
    decoder = space == "reconstructed" or recon > 0

    def gradients(w, x, t, y=None):
        zx, zt = x @ w["wx"] + w["bx"], t @ w["wt"] + w["bt"]
        same = (x[:, None, :1] == x[None, :, :1])[..., 0] & (
            x @ x.T >= (x * x).sum(1)[:, None] - 1e-12
        ) if mask_same else None
        if space == "reconstructed":
            _, gt, gx = contrastive(zt @ w["dt"] + w["ct"], zx @ w["dx"] + w["cx"], temperature, same)
            out = {"dx": zx.T @ gx, "cx": gx.sum(0), "dt": zt.T @ gt, "ct": gt.sum(0)}
            gx, gt = gx @ w["dx"].T, gt @ w["dt"].T
        else:
            _, gt, gx = contrastive(zt, zx, temperature, same)
            out = {}
        if recon:
            e = (zx @ w["dx"] + w["cx"] - x) * (2 * recon / len(x))
            out |= {"dx": zx.T @ e, "cx": e.sum(0)}
            gx = gx + e @ w["dx"].T
        if y is not None:
            zy = y @ w["wx"] + w["bx"]
            _, g1, g2 = contrastive(zx, zy, temperature, same)
            out |= _linear_grads(x, gx + lam * g1, "wx", "bx")
            more = _linear_grads(y, lam * g2, "wx", "bx")
            out["wx"], out["bx"] = out["wx"] + more["wx"], out["bx"] + more["bx"]
        else:
            out |= _linear_grads(x, gx, "wx", "bx")
        return out | _linear_grads(t, gt, "wt", "bt")

    names = ["wx", "bx", "wt", "bt"] + (["dx", "cx"] if decoder else []) + (
        ["dt", "ct"] if space == "reconstructed" else []
    )
    w = _run(
        pairs,
        [image, text, *([near] if near else [])],
        _starting(dim, latent_dim, o["seed"], *names),
        gradients,
        o,
        chosen,
    )
    kind = "npcc" if near else "hybrid" if recon else "contrastive" if space == "latent" else "contrastive-reconstructed"
    return Codec(
        kind,
        w["wx"],
        w["bx"],
        w["wt"],
        w["bt"],
        w.get("dx"),
        w.get("cx"),
        {
            "latent_dim": latent_dim,
            "temperature": temperature,
            "lam": lam,
            "mask_same_vector": mask_same,
            "recon": recon,
            **o,
        },
    )


def fit_fused_codec(pairs: DataFrame, latent_dim: int = 128, image: str = "x", text: str = "t", **options) -> Codec:
    """One encoder over both sides, trained to rebuild them; at search the other half of its input is empty."""
    o = _options(options)
    dim = width(pairs, image)
    latent_dim = min(latent_dim, dim)
    both = pairs.select(
        "id", F.concat(F.col(image).cast("array<double>"), F.col(text).cast("array<double>")).alias("xt")
    )
    w = _run(both, ["xt"], _starting(2 * dim, latent_dim, o["seed"], "wx", "bx", "dx", "cx"), _mse_gradients, o)
    return Codec(
        "fused", w["wx"], w["bx"], w["wx"], w["bx"], w["dx"][:, :dim], w["cx"][:dim], {"latent_dim": latent_dim, **o}
    )


def fit_opq(
    df: DataFrame,
    col: str = "x",
    out_dim: int = 112,
    m: int = 16,
    rounds: int = 5,
    bits: int = 8,
    sample: int = 20_000,
    seed: int = 0,
) -> Codec:
    """An orthogonal projection that suits a product quantizer of m blocks: codebooks and the rotation in turn, on a
    sample of bounded size.

    The start spreads the variance of the principal directions evenly over the blocks. manifest["errors"] has the
    error of each round."""
    dim = width(df, col)
    if out_dim % m:
        raise ValueError("m must divide out_dim")
    if out_dim > dim:
        raise ValueError("out_dim exceeds the dimension")
    x = np.array([r[0] for r in hash_sample(df.select("id", col), sample, "id").select(col).collect()], float)
    mean = x.mean(axis=0)
    x = x - mean
    values, basis = np.linalg.eigh(x.T @ x)
    basis, values = basis[:, ::-1][:, :out_dim], values[::-1][:out_dim]
    load, members = np.zeros(m), [[] for _ in range(m)]
    for j in range(out_dim):
        open_blocks = [b for b in range(m) if len(members[b]) < out_dim // m]
        b = min(open_blocks, key=lambda b: load[b])
        members[b].append(j)
        load[b] += np.log(max(values[j], 1e-12))
    r = basis[:, [j for b in members for j in b]]
    from nearcopy.operators.index import fit_codebooks, quantize

    books, errors = None, []
    for _ in range(rounds):
        z = x @ r
        books = fit_codebooks(z, m, min(1 << bits, len(z)), 2, books)
        y = quantize(z, books)[1]
        errors.append(float(((x @ r - y) ** 2).sum(axis=1).mean() + (x * x).sum(axis=1).mean() - ((x @ r) ** 2).sum(axis=1).mean()))
        u, _, vt = np.linalg.svd(x.T @ y, full_matrices=False)
        r = u @ vt
    return Codec("opq", r, -mean @ r, None, None, r.T, mean, {"out_dim": out_dim, "m": m, "errors": errors})
