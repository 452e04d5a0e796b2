"""Plans of whole runs and their rewrites."""
