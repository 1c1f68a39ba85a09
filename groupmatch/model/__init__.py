"""Patterns, graphs and options."""

from .graph import SocialGraph
from .pattern import GroupPattern, MatchOptions, MembershipRule, PatternEdge, PatternNode

__all__ = ["GroupPattern", "MatchOptions", "MembershipRule", "PatternEdge", "PatternNode", "SocialGraph"]
