"""Closed-form costs."""

from __future__ import annotations


def kv_cache(layers: int, seq: int, kv_heads: int, head_dim: int = 128, width: int = 2) -> int:
    return 2 * layers * seq * kv_heads * head_dim * width


def attention(image: int, text: int) -> tuple[int, int]:
    """Image queries only, against all queries."""
    return image * (image + text), (image + text) ** 2


def text_work(steps: int) -> tuple[int, int]:
    """Text projections with and without the cache."""
    return 1, steps


def fused_traffic(reads: int = 2, writes: int = 1, extra: int = 2) -> float:
    """Share of tensor moves that fusing the gated residual saves: unfused, the gated product is written and
    read once more, while reading x and r and writing the sum stay, and the gate broadcast is read in both."""
    fused = reads + writes + 1
    return 1 - fused / (fused + extra)


def padding_waste(counts: list[int]) -> float:
    return 1 - sum(counts) / (len(counts) * max(counts)) if counts and max(counts) else 0.0


def exchange_bytes(tokens: int, dims: int, devices: int, width: int = 2) -> int:
    """Both directions of the exchange, the local share left out."""
    return 2 * tokens * dims * width * (devices - 1) // devices


def shadow_copy(parameters: int, width: int = 4) -> tuple[int, int]:
    """Bytes of the second copy and multiply-adds a step."""
    return parameters * width, parameters


def tokens_per_step(batch: int, base: int, patch: int = 16) -> int:
    return batch * (base // patch) ** 2


def parameters(layers=32, first=3, d=2048, heads=16, kv=4, head=128, experts=64, hidden=1344, dense_hidden=8192) -> tuple[int, int]:
    """Total and active at one expert a token, of the parts with known shapes."""
    attn = layers * (d * heads * head * 2 + d * kv * head * 2)
    one = 3 * d * hidden
    moe = layers - first
    total = attn + first * 3 * d * dense_hidden + moe * (experts + 1) * one + moe * 2 * d * experts
    return total, attn + first * 3 * d * dense_hidden + moe * 2 * one + moe * 2 * d * experts
