"""Losses of a binary student and their gradients in the margin; focus 0 of the focal loss is cross-entropy."""

from __future__ import annotations

import numpy as np


def sigmoid(margin: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(margin, -40, 40)))


def focal_loss(margin: np.ndarray, label: np.ndarray, focus: float = 2.0, weight: np.ndarray | float = 1.0) -> np.ndarray:
    """-(1 - p)^focus ln p, p the probability given to the true class."""
    p = np.clip(np.where(label == 1, sigmoid(margin), 1 - sigmoid(margin)), 1e-12, 1)
    return -weight * (1 - p) ** focus * np.log(p)


def focal_gradient(margin: np.ndarray, label: np.ndarray, focus: float = 2.0, weight: np.ndarray | float = 1.0) -> np.ndarray:
    p = np.clip(np.where(label == 1, sigmoid(margin), 1 - sigmoid(margin)), 1e-12, 1 - 1e-12)
    toward = focus * (1 - p) ** focus * p * np.log(p) - (1 - p) ** (focus + 1)
    return weight * np.where(label == 1, toward, -toward)


def balanced_weights(label: np.ndarray) -> np.ndarray:
    """Weights that give both classes the same total; ones where a class is missing."""
    ones = label.sum()
    if ones in (0, len(label)):
        return np.ones(len(label))
    return np.where(label == 1, len(label) / (2 * ones), len(label) / (2 * (len(label) - ones)))
