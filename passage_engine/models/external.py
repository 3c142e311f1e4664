"""Checkpoints from elsewhere: an ONNX session for each Python worker.

The graph takes ``input_ids`` (batch x tokens, int64) and ``attention_mask`` and gives the final
hidden states (batch x tokens x width); pooling and head are ours.
"""

from __future__ import annotations

import numpy as np

_sessions: dict[str, object] = {}


def load(path: str, threads: int = 1):
    """The worker's session for a graph, made once."""
    if path not in _sessions:
        import onnxruntime as ort

        options = ort.SessionOptions()
        options.intra_op_num_threads = threads
        _sessions[path] = ort.InferenceSession(path, options, providers=["CPUExecutionProvider"])
    return _sessions[path]


def sentence_probs(session, sents: list[list[int]], weight: np.ndarray, bias: np.ndarray, marker: int, limit: int = 512) -> np.ndarray:
    """Probabilities of one block: mean of each sentence's states, then the two-class head."""
    ids, owner = [marker], [-1]
    for m, s in enumerate(sents):
        s = s[: max(0, limit - len(ids))]
        ids += s
        owner += [m] * len(s)
    states = session.run(None, {"input_ids": np.array([ids], np.int64), "attention_mask": np.ones((1, len(ids)), np.int64)})[0][0]
    pool = np.zeros((len(sents), len(ids)))
    for j, m in enumerate(owner):
        if m >= 0:
            pool[m, j] = 1
    pool /= np.maximum(pool.sum(axis=1, keepdims=True), 1)
    z = pool @ states @ weight + bias
    e = np.exp(z - z.max(axis=1, keepdims=True))
    return (e / e.sum(axis=1, keepdims=True))[:, 1]
