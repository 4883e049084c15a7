"""Where factors come from and go to."""
