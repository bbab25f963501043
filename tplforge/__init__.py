"""Template engine for log lines on Spark."""
