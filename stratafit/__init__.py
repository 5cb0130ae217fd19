"""Variance-reduced training of forecasting models by stratified sampling, on Spark."""
