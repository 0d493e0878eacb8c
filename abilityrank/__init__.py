"""Ability ranking on Spark: order users by how well they pick options, without an answer key."""
