"""Data model: schemas, graphs, programs, options and results."""

from shardgraph.model.graph import ArrowProgram, EngineOptions, Graph, Result, ShardedGraph, VertexProgram

__all__ = ["ArrowProgram", "EngineOptions", "Graph", "Result", "ShardedGraph", "VertexProgram"]
