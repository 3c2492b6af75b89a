"""Operators of the manifold engine over points, pairs, trees and models."""
